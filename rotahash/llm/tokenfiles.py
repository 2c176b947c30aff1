"""Token ids as Arrow IPC files of equal-length sequences.

Documents are range-partitioned by doc_id; each range is encoded in ascending order and written to one
Arrow file whose record batches hold two fixed-size-list columns: ``ids`` (unsigned 16-bit where the
vocabulary allows, else 32-bit) and ``mask`` (false on the padding of a file's last sequence). Because
every list has the same length and the file is not compressed, sequence i of a file is a slice of the
memory map. A second small file lists doc_id and token count of each document of the range, in order.

A file is written under a name of its attempt and then renamed, so repeated or speculative attempts
leave the same whole file. Files go to the folder in spark.checkpoint.dir or to a given folder.

Texts are cut at places where the pre-tokenizer always cuts too; each distinct piece is encoded once a
cache generation by the tokenizers library, and a piece takes ids from the cache only if it has the same bytes.
Texts that hold the string of an added token, and all texts of a tokenizer that normalises, are encoded whole.
Ids are those that the library gives the whole text; a test compares them. By default the string of a special
token becomes that token's id, as in the library; ``special_as_text`` takes such strings as ordinary text.

Defined results: null text is empty and has just the end id; rows with equal doc_id are separate and
ordered by their text; an empty table has no files and no rows.
"""

from __future__ import annotations

import os
import uuid
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import pyarrow.ipc as ipc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rotahash.llm.bytesops import U, lean, slices, span_hashes
from rotahash.llm.durable import durable, new_folder, partitions

LENGTH, END_ID = 1024, 2
CACHE, CACHE_BYTES, SLICE = 1_000_000, 1 << 25, 1 << 21


_START = np.zeros(256, bool)
_START[[*range(65, 91), *range(97, 123)]] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[48:58] = True
_SOLID = np.zeros(256, bool)
_SOLID[33:127] = True


class Encoder:
    """tokenizers behind a cache of pieces, kept as sorted hashes, the pieces' bytes and one array of ids; ``CACHE`` bounds its entries."""

    _own: dict[tuple, Encoder] = {}

    @classmethod
    def of(cls, path: str, special_as_text: bool = False) -> Encoder:
        """The encoder of this worker process."""
        key = (path, special_as_text)
        return cls._own.get(key) or cls._own.setdefault(key, cls(*key))

    def __init__(self, path: str, special_as_text: bool = False):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = special_as_text
        added = self.tokenizer.get_added_tokens_decoder().values()
        self.added = [t.content.encode() for t in added if t.content and not (special_as_text and t.special)]
        self.normalised = self.tokenizer.normalizer is not None
        self.width = np.uint16 if self.tokenizer.get_vocab_size() <= 1 << 16 else np.uint32
        self.line = self._ids("\n")
        self.clear()

    def _ids(self, text: str) -> list[int]:
        return self.tokenizer.encode(text, add_special_tokens=False).ids

    def clear(self) -> None:
        self.keys, self.entry = np.zeros(0, U), np.zeros(0, np.int64)
        self.ids, self.at = np.zeros(0, self.width), np.zeros(1, np.int64)
        self.bytes, self.byte_at = np.zeros(0, np.uint8), np.zeros(1, np.int64)

    def _whole(self, data: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Rows that are not cut into pieces."""
        if self.normalised:
            return np.flatnonzero(np.diff(at))
        text, found = data.tobytes(), []
        for token in self.added:
            k = text.find(token)
            while k >= 0:
                found.append(k)
                k = text.find(token, k + 1)
        return np.unique(np.searchsorted(at, np.array(found, np.int64), "right") - 1)

    @staticmethod
    def cuts(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Starts of the pieces, and which pieces may be encoded next to each other with a line feed between.

        A piece begins at a text's start, at a space between a solid character and a letter, at ASCII
        punctuation after a letter, and at and after a line feed between solid characters. Solid: printable ASCII or a Latin-1 letter.
        """
        n = len(data)
        pad = np.concatenate([data, np.zeros(2, np.uint8)])
        latin = np.zeros(n + 2, bool)  # lead byte of a Latin-1 letter
        latin[:n] = (pad[:n] == 0xC3) & (pad[1 : n + 1] >= 0x80) & (pad[1 : n + 1] != 0x97) & (pad[1 : n + 1] != 0xB7)
        solid_end = _SOLID[data]  # the last byte of a solid character
        solid_end[1:] |= latin[: n - 1]
        letter, solid = _START[pad] | latin, _SOLID[pad] | latin
        before = np.concatenate([[False], solid_end[:-1]])
        cut = np.zeros(n + 1, bool)
        cut[:n] = before & (data == 32) & letter[1 : n + 1]
        letter_end = _START[data]
        letter_end[1:] |= latin[: n - 1]
        cut[1:n] |= letter_end[:-1] & (_SOLID & ~_START & ~_DIGIT)[data[1:]]
        feed = before & (data == 10) & solid[1 : n + 1]
        border = np.zeros(n + 1, bool)
        border[at] = True
        feed[:-1] &= ~border[1:n]
        feed &= ~border[:n]
        cut[:n] &= ~np.append(border[1:n], True) if n else False
        cut[:n] |= feed
        cut[1:] |= feed
        cut |= border
        start = np.flatnonzero(cut[:n])
        end = np.append(start[1:], n)
        plain = solid_end[end - 1] & (solid[start] | ((data[start] == 32) & letter[start + 1]))
        lines = np.concatenate([[0], np.cumsum(data == 10)])
        return start, plain & (lines[end] == lines[start])

    def _fresh(self, data: np.ndarray, start: np.ndarray, end: np.ndarray, plain: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids of pieces, one after another, their counts, and the order taken: the plain ones joined by line feeds, the others one by one."""
        ids, counts, order, alone = [], [], [], [np.flatnonzero(~plain)]
        joined = np.flatnonzero(plain)
        for lo in range(0, len(joined), 4096):
            own = joined[lo : lo + 4096]
            size = end[own] - start[own] + 1
            to = np.cumsum(size)
            at = np.repeat(start[own] - (to - size), size) + np.arange(to[-1])
            text = data[np.minimum(at, len(data) - 1)]
            text[to - 1] = 10
            got = np.asarray(self._ids(text[:-1].tobytes().decode()), self.width)
            line = np.flatnonzero(got == self.line[0]) if len(self.line) == 1 else np.zeros(0, np.int64)
            if len(line) != len(own) - 1:
                alone.append(own)
                continue
            ids.append(np.delete(got, line))
            counts.append(np.diff(np.concatenate([[-1], line, [len(got)]])) - 1)
            order.append(own)
        rest = np.concatenate(alone)
        if len(rest):
            got = [e.ids for e in self.tokenizer.encode_batch_fast([data[s:e].tobytes().decode() for s, e in zip(start[rest].tolist(), end[rest].tolist(), strict=True)], add_special_tokens=False)]
            ids.append(np.fromiter((i for x in got for i in x), self.width))
            counts.append(np.array([len(x) for x in got]))
            order.append(rest)
        return np.concatenate(ids), np.concatenate(counts), np.concatenate(order)

    def _add(self, data: np.ndarray, start: np.ndarray, end: np.ndarray, plain: np.ndarray) -> np.ndarray:
        """Encodes pieces and returns their entries."""
        ids, counts, order = self._fresh(data, start, end, plain)
        size = (end - start)[order]
        to = np.cumsum(size)
        take = np.repeat(start[order] - (to - size), size) + np.arange(to[-1])
        entry = np.empty(len(start), np.int64)
        entry[order] = len(self.at) - 1 + np.arange(len(start))
        self.ids, self.at = np.concatenate([self.ids, ids]), np.concatenate([self.at, self.at[-1] + np.cumsum(counts)])
        self.bytes, self.byte_at = np.concatenate([self.bytes, data[take]]), np.concatenate([self.byte_at, self.byte_at[-1] + to])
        return entry

    def _same(self, entry: np.ndarray, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Whether the pieces, which make up the buffer, have the bytes of their entries."""
        size = end - start
        out = self.byte_at[entry + 1] - self.byte_at[entry] == size
        take = np.minimum(np.repeat(self.byte_at[entry] - start, size) + np.arange(len(data)), max(0, len(self.bytes) - 1))
        return out & ~np.logical_or.reduceat(self.bytes[take] != data, start)

    def batch(self, data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the texts of a buffer, each with the end id, and their offsets."""
        if len(self.keys) > CACHE or len(self.bytes) > CACHE_BYTES:
            self.clear()
        rows = len(at) - 1
        if len(data):
            start, plain = self.cuts(data, at)
            whole = self._whole(data, at)
            if len(whole):  # one piece a row
                inside = np.zeros(len(data), bool)
                for lo, hi in zip(at[whole].tolist(), at[whole + 1].tolist(), strict=True):
                    inside[lo + 1 : hi] = True
                keep = ~inside[start]
                start, plain = start[keep], plain[keep] & ~np.isin(start[keep], at[whole])
            end = np.append(start[1:], len(data))
            keys, first, which = np.unique(span_hashes(data, start, end), return_index=True, return_inverse=True)
            place = np.searchsorted(self.keys, keys)
            known = place < len(self.keys)
            known[known] = self.keys[place[known]] == keys[known]
            new = np.flatnonzero(~known)
            if len(new):
                own = first[new]
                entry = self._add(data, start[own], end[own], plain[own])
                self.keys, self.entry = np.insert(self.keys, place[new], keys[new]), np.insert(self.entry, place[new], entry)
                place = np.searchsorted(self.keys, keys)
            piece = self.entry[place][which]
            odd = np.flatnonzero(~self._same(piece, data, start, end))
            if len(odd):  # other bytes of equal hash: an entry of their own that no hash leads to
                piece[odd] = self._add(data, start[odd], end[odd], plain[odd])
            ends = np.searchsorted(start, at[1:])  # pieces up to each text's end
        else:
            piece, ends = np.zeros(0, np.int64), np.zeros(rows, np.int64)
        end_id = len(self.at) - 1  # one more entry: the end id
        ids, offsets = np.append(self.ids, self.width(END_ID)), np.append(self.at, self.at[-1] + 1)
        piece = np.insert(piece, ends, end_id)
        length = offsets[piece + 1] - offsets[piece]
        to = np.cumsum(length)
        flat = ids[np.repeat(offsets[piece] - (to - length), length) + np.arange(to[-1] if len(to) else 0)]
        return flat, np.concatenate([[0], to[ends + np.arange(rows)]])


def _open(folder: str) -> tuple[pafs.FileSystem, str]:
    if "://" in folder or folder.startswith("file:"):
        return pafs.FileSystem.from_uri(folder)
    return pafs.LocalFileSystem(), folder


def write(docs: DataFrame, tokenizer: str, folder: str | None = None, length: int = LENGTH, special_as_text: bool = False) -> tuple[str, DataFrame]:
    """Writes the files and returns their folder and a manifest (part, n_docs, n_tokens), one row per file."""
    spark = docs.sparkSession
    folder = folder or new_folder(spark, "tokens")
    ordered = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).repartitionByRange(partitions(spark), F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")

    def save(batches):
        part, encoder, files, tmp = TaskContext.get().partitionId(), None, [], uuid.uuid4().hex
        rest, docs_, tokens, out, index = None, 0, 0, None, None
        fs, root = _open(folder)
        for b in batches:
            for lo, hi, data, rows in slices(b.column("text"), SLICE):
                if encoder is None:
                    encoder = Encoder.of(tokenizer, special_as_text)
                    kind = pa.from_numpy_dtype(encoder.width)
                    fs.create_dir(root, recursive=True)
                    files = [fs.open_output_stream(f"{root}/_{tmp}-{x}") for x in ("ids", "docs")]
                    out = ipc.new_file(files[0], _schema(kind, length))
                    index = ipc.new_file(files[1], pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64())]))
                    rest = np.zeros(0, encoder.width)
                flat, at = encoder.batch(data, rows)
                index.write_batch(pa.record_batch([b.column("doc_id").slice(lo, hi - lo), pa.array(np.diff(at))], names=["doc_id", "n_tokens"]))
                docs_, tokens, rest = docs_ + hi - lo, tokens + len(flat), np.concatenate([rest, flat])
                whole = len(rest) // length * length
                if whole:
                    out.write_batch(_batch(rest[:whole], np.ones(whole, bool), length, kind))
                    rest = rest[whole:].copy()
        if encoder is not None:
            if len(rest):
                mask = np.arange(length) < len(rest)
                out.write_batch(_batch(np.concatenate([rest, np.zeros(length - len(rest), encoder.width)]), mask, length, kind))
            for w in (out, index, *files):
                w.close()
            for x in ("ids", "docs"):
                fs.move(f"{root}/_{tmp}-{x}", f"{root}/part-{part:06d}-{x}.arrow")
            yield pa.RecordBatch.from_arrays([pa.array([part]), pa.array([docs_]), pa.array([tokens])], ["part", "n_docs", "n_tokens"])

    return folder, durable(ordered.mapInArrow(lean(save), "part long, n_docs long, n_tokens long"))


def _schema(kind: pa.DataType, length: int) -> pa.Schema:
    return pa.schema([(name, pa.list_(pa.field("item", of, False), length)) for name, of in (("ids", kind), ("mask", pa.bool_()))])


def _batch(ids: np.ndarray, mask: np.ndarray, length: int, kind: pa.DataType) -> pa.RecordBatch:
    fields = _schema(kind, length)
    own = [pa.FixedSizeListArray.from_arrays(pa.array(x), type=f.type) for x, f in zip((ids, mask), fields, strict=True)]
    return pa.RecordBatch.from_arrays(own, schema=fields)


def sequences(folder: str, part: int) -> ipc.RecordBatchFileReader:
    """Reader of one file's sequences: a memory map, and so zero-copy, where the folder is local."""
    fs, root = _open(folder)
    path = f"{root}/part-{part:06d}-ids.arrow"
    return ipc.open_file(pa.memory_map(path) if isinstance(fs, pafs.LocalFileSystem) else fs.open_input_file(path))


def read(folder: str, manifest: DataFrame) -> DataFrame:
    """One row per document, from the files: doc_id, start (ids of all documents before it), n_tokens and its ids' CRC-32 as 32-bit integers."""
    spark = manifest.sparkSession
    parts = sorted((r["part"], r["n_tokens"]) for r in manifest.collect())  # one row per file
    base = spark.sparkContext.broadcast(dict(zip((p for p, _ in parts), np.concatenate([[0], np.cumsum([n for _, n in parts])[:-1]]).tolist() if parts else [], strict=True)))

    def load(batches):
        fs, root = _open(folder)
        for b in batches:
            for part in b.column("part").to_pylist():
                with sequences(folder, part) as reader, fs.open_input_file(f"{root}/part-{part:06d}-docs.arrow") as f, ipc.open_file(f) as index:
                    at, start, k, have = 0, base.value[part], 0, np.zeros(0, np.uint16)
                    for i in range(index.num_record_batches):
                        own = index.get_batch(i)
                        counts, crc, starts = own.column("n_tokens").to_numpy(), [], []
                        for n in counts.tolist():
                            while len(have) - at < n:
                                more = reader.get_batch(k)
                                k += 1
                                ids, mask = (more.column(c).flatten() for c in ("ids", "mask"))
                                ids = ids.to_numpy()
                                if k == reader.num_record_batches:
                                    ids = ids[mask.to_numpy(zero_copy_only=False)]
                                have, at = (np.concatenate([have[at:], ids]) if len(have) > at else ids), 0
                            crc.append(zlib.crc32(have[at : at + n].astype("<u4").tobytes()))
                            starts.append(start)
                            at, start = at + n, start + n
                        yield pa.RecordBatch.from_arrays([own.column("doc_id"), pa.array(starts, pa.int64()), own.column("n_tokens"), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return manifest.select("part").mapInArrow(lean(load), "doc_id long, start long, n_tokens long, ids_crc32 long")
