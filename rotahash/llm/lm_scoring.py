"""Language-model scores of documents: a frozen PPM model trained on the corpus beside a unigram word model.

The one pass over the texts leaves, on shared storage, per segment of a task: its distinct byte strings with
their training counts (0 for strings of held-out texts alone), dealt by the last two bytes of their contexts,
so that every node of order 2 and above is complete in one bucket; its distinct words with their counts, dealt
by hash; and its texts. A segment sends a string or word once, however often it occurs, so frequent ones are
no hot keys. Buckets answer each segment with the totals of its own words and the log probabilities of its own
strings, in the order in which it asked, so answers carry no keys: the segment's texts give them again.

No string is pruned and counts are exact, whatever the size of the corpus: the model is never in one place. Only
orders 0 and 1, at most 2^16 strings, are broadcast, and a bucket works through its contexts in pieces. A segment
ends after ``SEGMENT`` bytes of text, or when its strings or words are many. ``train`` and ``models_of`` serve
``language_id``, whose models are pruned and broadcast.

Defined results: null text is empty: one token, its end. A null doc_id is trained on. With no training
text all counts are 0, and every byte costs log10(256). Equal rows get equal scores.
"""

from __future__ import annotations

import uuid
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rotahash.llm import ppm
from rotahash.llm.bytesops import LOWER, SPACE, U, lean, mix, pack, slices, unpack, word_hashes
from rotahash.llm.durable import durable, partitions

ORDER = 5
VOCABULARY, STRINGS, PIECE, SEGMENT = 1_500_000, 1 << 21, 1 << 15, 1 << 25
GRAMS, WORDS, TEXTS, TRAINED, PAIRS = range(5)
ROWS = "kind int, a long, b long, cell binary"
STRING = (("key", np.uint64), ("count", np.int64))
TEXT = (("doc", np.int64), ("known", np.uint8), ("held", np.uint8), ("bytes", np.int64))
BYTE = (("byte", np.uint8),)
REPLY = (("total", np.int64),)
ANSWER = (("log", np.float64),)
ANSWERS = "kind int, task long, bucket long, cell binary, distinct long, tokens long"


def _row(kind: int, a: int, b: int, cell: bytes | None) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([kind], pa.int32()), pa.array([a], pa.int64()), pa.array([b], pa.int64()), pa.array([cell], pa.binary())], ["kind", "a", "b", "cell"])


def _by_bucket(kind: int, keys: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """The order of sorted keys by bucket, and where each bucket begins in it."""
    bucket = ((mix((keys >> U(8)) & U(0xFFFF)) if kind == GRAMS else keys) % U(buckets)).astype(np.int64)
    order = np.argsort(bucket, kind="stable")
    return order, np.searchsorted(bucket[order], np.arange(buckets + 1))


def _joined(parts: list[bytes]) -> bytes:
    return b"".join(len(x).to_bytes(8, "little") + x for x in parts)


def _split(cell: bytes) -> list[bytes]:
    out, at = [], 0
    while at < len(cell):
        n = int.from_bytes(cell[at : at + 8], "little")
        out.append(cell[at + 8 : at + 8 + n])
        at += 8 + n
    return out


def _scan(docs: DataFrame, buckets: int, order: int) -> DataFrame:
    def scan(batches):
        strings, words, size, segment, trained = ppm.Grams(order), [], 0, 0, 0
        part = TaskContext.get().partitionId() << 20

        def known():
            strings_ = strings.fold()
            for kind, (keys, counts) in ((WORDS, ppm.total(*zip(*words, strict=True)) if words else ([], [])), (GRAMS, strings_)):
                if len(keys):
                    by, at = _by_bucket(kind, keys, buckets)
                    for k in np.flatnonzero(np.diff(at)).tolist():
                        own = by[at[k] : at[k + 1]]
                        yield _row(kind, k, part + segment, pack([keys[own], counts[own]], STRING))
            few, sums = ppm.total([strings_[0] & U(0xFFFF)], [strings_[1]])
            n = len(few)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(n, PAIRS, np.int32)), pa.array(few.astype(np.int64)), pa.array(sums), pa.nulls(n, pa.binary())], ["kind", "a", "b", "cell"])

        for b in batches:
            held_all, ids_all = b.column("held").to_numpy(zero_copy_only=False), b.column("doc_id")
            for lo, hi, data, at in slices(b.column("text")):
                data = LOWER[data]
                held = held_all[lo:hi].astype(bool)
                for rows, weight in ((~held, 1), (held, 0)):
                    if rows.any():
                        strings.add(data[np.repeat(rows, np.diff(at))], np.concatenate([[0], np.cumsum(np.diff(at)[rows])]), weight)
                trained += int((~held).sum())
                hashes, rows = word_hashes(data, at, ~SPACE)
                keys, which = np.unique(hashes, return_inverse=True)
                words.append((keys, np.bincount(which[np.repeat(~held, np.diff(rows))], minlength=len(keys))))
                if len(words) > 15:
                    words = [ppm.total(*zip(*words, strict=True))]
                doc = ids_all.slice(lo, hi - lo)
                valid = doc.is_valid().to_numpy(zero_copy_only=False)
                cell = pack([doc.fill_null(0).to_numpy(), valid, held, np.diff(at)], TEXT)
                yield _row(TEXTS, part + segment, 0, _joined([cell, pack([data], BYTE)]))
                size += len(data)
                if size > SEGMENT or len(words[0][0]) > VOCABULARY or len(strings.parts[0][0]) > STRINGS:
                    yield from known()
                    strings, words, size, segment = ppm.Grams(order), [], 0, segment + 1
        yield from known()
        yield _row(TRAINED, trained, 0, None)

    return docs.mapInArrow(lean(scan), ROWS)


def _strings(rows: DataFrame, order: int) -> DataFrame:
    """By bucket and label (b): the counts of orders 2..N, and how many have how many binary digits."""

    def add(table):
        label = table.column("b")[0].as_py()
        keys, counts = unpack(table.column("cell").to_pylist(), STRING)
        keys, counts = ppm.total([keys], [counts])
        out = []
        for n in range(order, 1, -1):
            digits = np.bincount(np.floor(np.log2(np.maximum(counts, 1))).astype(np.int64), minlength=64)
            out.append((n, pack([keys, counts], STRING), digits.tolist()))
            keys, counts = ppm.lower(keys, counts, n)
        return pa.table({"label": pa.array([label] * len(out), pa.int64()), "n": pa.array([x[0] for x in out], pa.int32()), "cell": pa.array([x[1] for x in out], pa.binary()), "digits": pa.array([x[2] for x in out], pa.list_(pa.int64()))})

    return rows.groupBy("a", "b").applyInArrow(lean(add), "label long, n int, cell binary, digits array<long>")


def train(rows: DataFrame, order: int, limit: int) -> dict[int, list[list[bytes]]]:
    """By label, packed keys and counts of each order, at most ``limit`` strings of each, on the driver."""
    sums = durable(_strings(rows, order))
    seen = sums.select("label", "n", F.posexplode("digits").alias("d", "k")).groupBy("label", "n", "d").agg(F.sum("k").alias("k")).collect()
    many: dict = defaultdict(lambda: [0] * 64)
    for r in seen:
        many[r["label"], r["n"]][r["d"]] = r["k"]
    least = {}
    for label in {x for x, _ in many}:
        floor = 0
        for n in range(2, order + 1):
            while sum(many[label, n][floor:]) > limit:
                floor += 1
            least[label, n] = 1 << floor

    def cut(batches):
        for b in batches:
            out = []
            for label, n, cell in zip(b.column("label").to_pylist(), b.column("n").to_pylist(), b.column("cell").to_pylist(), strict=True):
                keys, counts = unpack([cell], STRING)
                keep = counts >= least[label, n]
                out.append(pack([keys[keep], counts[keep]], STRING))
            yield pa.RecordBatch.from_arrays([b.column("label"), b.column("n"), pa.array(out, pa.binary())], ["label", "n", "cell"])

    models: dict = defaultdict(lambda: [[] for _ in range(order + 1)])
    for r in sums.select("label", "n", "cell").mapInArrow(lean(cut), "label long, n int, cell binary").collect():
        models[r["label"]][r["n"]].append(bytes(r["cell"]))
    for cells in models.values():  # orders 0 and 1 are sums of order 2
        keys, counts = ppm.total(*[[x] for x in unpack(cells[2], STRING)])
        for n in (2, 1):
            keys, counts = ppm.lower(keys, counts, n)
            cells[n - 1] = [pack([keys, counts], STRING)]
    return dict(models)


def frozen(order: int, cells: list[list[bytes]]) -> ppm.Model:
    return ppm.Model(order, [ppm.total(*[[x] for x in unpack(own, STRING)]) for own in cells])


_MODELS: dict[str, dict[int, ppm.Model]] = {}


def models_of(shared) -> dict[int, ppm.Model]:
    """The broadcast models by label, built once in a worker."""
    name, order, cells = shared.value
    if name not in _MODELS:
        _MODELS.clear()
        _MODELS[name] = {label: frozen(order, own) for label, own in cells.items()}
    return _MODELS[name]


def adaptive_scores(docs: DataFrame, order: int = ORDER) -> DataFrame:
    """doc_id and log10 probability of each text under a model that starts empty and learns as it goes; one text at a time."""

    def score(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array([ppm.adaptive((t or "").encode(), order) for t in b.column("text").to_pylist()], pa.float64())], ["doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(score, "doc_id long, score double")


def _totals(rows: DataFrame) -> DataFrame:
    """By bucket: to each segment the totals of its words; and one row (task -1) with the bucket's distinct words and tokens."""

    def answer(table):
        cells, tasks = table.column("cell").to_pylist(), table.column("b").to_pylist()
        parts = [unpack([c], STRING) for c in cells]
        keys, counts = ppm.total([p[0] for p in parts], [p[1] for p in parts])
        out = [pack([counts[np.searchsorted(keys, p[0])]], REPLY) for p in parts]
        n, bucket = len(out), table.column("a")[0].as_py()
        return pa.table({"kind": pa.array([WORDS] * (n + 1), pa.int32()), "task": pa.array([*tasks, -1], pa.int64()), "bucket": pa.array([bucket] * (n + 1), pa.int64()), "cell": pa.array([*out, None], pa.binary()), "distinct": pa.array([0] * n + [int((counts > 0).sum())], pa.int64()), "tokens": pa.array([0] * n + [int(counts.sum())], pa.int64())})

    return rows.groupBy("a").applyInArrow(lean(answer), ANSWERS)


def string_logs(keys: np.ndarray, counts: np.ndarray, order: int, few: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """log10 probability of the last byte of each string after the bytes before it.

    keys and counts have every counted string of the contexts that occur, by their last two bytes; few has
    orders 0 and 1 of the whole corpus.
    """
    out = np.zeros(len(keys))
    context = (keys >> U(8)) & U(0xFFFF)
    by = np.argsort(context, kind="stable")
    ends = np.append(np.flatnonzero(np.diff(context[by])) + 1, len(by))
    lo = 0
    while lo < len(by):
        hi = int(ends[np.searchsorted(ends, min(lo + PIECE, len(by)))])
        own = np.sort(by[lo:hi])
        used = own[counts[own] > 0]
        seen = [(keys[used], counts[used])]
        for n in range(order, 2, -1):
            seen.insert(0, ppm.lower(*seen[0], n))
        model = ppm.Model(order, [*few, *seen], exact=True) if len(few[0][0]) else ppm.Model(0, few[:1])
        for k in range(0, len(own), PIECE):
            ask = own[k : k + PIECE]
            symbols = np.stack([(keys[ask] >> U(8 * j)) & U(0xFF) for j in range(order, -1, -1)], 1).astype(np.uint8).ravel()
            out[ask] = model.code(symbols, order + (order + 1) * np.arange(len(ask)))
        lo = hi
    return out


def _probabilities(rows: DataFrame, order: int) -> DataFrame:
    """By bucket: to each segment the log probabilities of its strings."""
    pairs = rows.where(F.col("kind") == PAIRS).groupBy("a").agg(F.sum("b").alias("b")).where("b > 0").orderBy("a").collect()  # at most 2^16
    keys, counts = np.array([r["a"] for r in pairs], U), np.array([r["b"] for r in pairs], np.int64)
    shared = rows.sparkSession.sparkContext.broadcast([ppm.lower(keys, counts, 1), (keys, counts)])

    def answer(table):
        cells, tasks = table.column("cell").to_pylist(), table.column("b").to_pylist()
        parts = [unpack([c], STRING) for c in cells]
        keys, counts = ppm.total([p[0] for p in parts], [p[1] for p in parts])
        logs = string_logs(keys, counts, order, shared.value)
        out = [pack([logs[np.searchsorted(keys, p[0])]], ANSWER) for p in parts]
        bucket = table.column("a")[0].as_py()
        none = pa.array([0] * len(out), pa.int64())
        return pa.table({"kind": pa.array([GRAMS] * len(out), pa.int32()), "task": pa.array(tasks, pa.int64()), "bucket": pa.array([bucket] * len(out), pa.int64()), "cell": pa.array(out, pa.binary()), "distinct": none, "tokens": none})

    return rows.where(F.col("kind") == GRAMS).groupBy("a").applyInArrow(lean(answer), ANSWERS)


def _asked(parts: list[np.ndarray], kind: int, replies, buckets: int, layout) -> tuple[np.ndarray, np.ndarray]:
    """The distinct keys of a segment, sorted, and the buckets' answers to them."""
    keys = np.unique(np.concatenate([np.zeros(0, U), *parts]))
    order, _ = _by_bucket(kind, keys, buckets)
    out = np.zeros(len(keys), layout[0][1])
    (got,) = unpack([c for _, c in sorted((b, c) for k, b, c in replies if k == kind)], layout)
    out[order] = got
    return keys, out


def _scored(texts: DataFrame, answers: DataFrame, ends: int, size: int, order: int, buckets: int) -> DataFrame:
    def score(left, right):
        replies = list(zip(*(right.column(c).to_pylist() for c in ("kind", "bucket", "cell")), strict=True))
        held_back, out = [], []
        for cell in left.column("cell").to_pylist():
            head, body = _split(cell)
            doc, known, held, width = unpack([head], TEXT)
            (data,) = unpack([body], BYTE)
            at = np.concatenate([[0], np.cumsum(width)])
            hashes, rows = word_hashes(data, at, ~SPACE)
            symbols, places, offsets = ppm.framed(data, at, order)
            word, word_at = np.unique(hashes, return_inverse=True)
            gram, gram_at = np.unique(ppm.grams(symbols, places, order), return_inverse=True)
            held_back.append((doc, known, held, rows, word, word_at.astype(np.int32), gram, gram_at.astype(np.int32), offsets))
        words, total = _asked([h[4] for h in held_back], WORDS, replies, buckets, REPLY)
        grams, likely = _asked([h[6] for h in held_back], GRAMS, replies, buckets, ANSWER)
        logs = np.log10(total + 1.0)
        for doc, known, held, at, word, word_at, gram, gram_at, offsets in held_back:
            own = np.searchsorted(words, word)
            sums = np.concatenate([[0], np.cumsum(logs[own][word_at])])
            hits = np.concatenate([[0], np.cumsum((total[own] > 0)[word_at])])
            tokens = np.diff(at) + 1
            base = sums[at[1:]] - sums[at[:-1]] + np.log10(ends + 1.0) - tokens * np.log10(float(size))
            ppm_score = np.add.reduceat(likely[np.searchsorted(grams, gram)][gram_at], offsets[:-1])
            out.append(pa.table({"doc_id": pa.array(doc, mask=known == 0), "held_out": pa.array(held == 1), "n_tokens": pa.array(tokens), "n_known": pa.array(hits[at[1:]] - hits[at[:-1]] + (ends > 0)), "base_score": pa.array(base), "score": pa.array(ppm_score)}))
        kinds = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64())])
        return pa.concat_tables([t.cast(kinds) for t in out]) if out else kinds.empty_table()

    return texts.groupBy("a").cogroup(answers.groupBy("task")).applyInArrow(lean(score), "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double")


def score(docs: DataFrame, modulus: int = 7, held: int = 2, order: int = ORDER) -> DataFrame:
    """One row per document: doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score."""
    spark = docs.sparkSession
    is_held = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % modulus == held, F.lit(False))
    buckets = partitions(spark)
    scan = durable(_scan(docs.select("doc_id", "text", is_held.alias("held")), buckets, order))
    answers = durable(_totals(scan.where(F.col("kind") == WORDS)))
    ends = scan.where(F.col("kind") == TRAINED).agg(F.sum("a")).first()[0] or 0
    distinct, tokens = answers.where("task = -1").agg(F.coalesce(F.sum("distinct"), F.lit(0)), F.coalesce(F.sum("tokens"), F.lit(0))).first()
    n, v = tokens + ends, distinct + (ends > 0)
    answers = answers.where("task >= 0").unionByName(_probabilities(scan, order))
    scored = _scored(scan.where(F.col("kind") == TEXTS), answers, ends, n + v + 1, order, buckets)
    return scored.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(n).cast("long").alias("train_tokens"), "base_score", "score")
