"""Token files, the vector join and the pipeline."""

import re
import zlib
from collections import Counter

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from rotahash.llm import embedding_join, tokenfiles
from rotahash.llm.bytesops import raw
from rotahash.llm.queries import tokenizer_path


def reference():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path())
    return lambda text: [*t.encode(text or "", add_special_tokens=False).ids, 2]


@settings(max_examples=300, deadline=None)
@given(st.lists(st.lists(st.sampled_from([*" \n\t\r abzéÑ×'1.,!\u0085\x1c日ſ😀", "'s", "<|endoftext|>"]), max_size=30).map("".join), min_size=1, max_size=6))
def test_pieces_encode_as_whole_texts(texts):
    import pyarrow as pa

    encode, own = reference(), tokenfiles.Encoder.of(tokenizer_path())
    ids, at = own.batch(*raw(pa.array(texts)))
    assert [ids[at[i] : at[i + 1]].tolist() for i in range(len(texts))] == [encode(t) for t in texts]


def test_token_files_round_trip(docs, texts, tmp_path):
    encode = reference()
    folder, manifest = tokenfiles.write(docs, tokenizer_path(), str(tmp_path / "files"), length=64)
    got = sorted(tokenfiles.read(folder, manifest).collect())
    start, stream = 0, []
    for r, k in zip(got, sorted(texts), strict=True):
        ids = encode(texts[k])
        assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32) == (k, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
        stream += ids
    read = []
    for part in sorted(r.part for r in manifest.collect()):
        with tokenfiles.sequences(folder, part) as reader:
            for i in range(reader.num_record_batches):
                b = reader.get_batch(i)
                assert b.schema.field("ids").type.list_size == b.schema.field("mask").type.list_size == 64
                ids, mask = b.column("ids").flatten().to_numpy(zero_copy_only=True), b.column("mask").flatten().to_numpy(zero_copy_only=False)
                read += ids[mask].tolist()
    assert read == stream


def test_pieces_of_equal_hash_and_long_words(monkeypatch):
    """Words that a polynomial hash modulo 2^64 takes for one, special tokens amid a text, and pieces whose hashes are made equal."""
    import pyarrow as pa

    encode = reference()
    a, b = "a", "b"
    for _ in range(10):
        a, b = a + b, b + a
    texts = [a, b, f"x {a} y", f"x {b} y", "hello <|endoftext|> world", "<|endoftext|>", "a<|endoftext|><|endoftext|>b\n", "", "<|endoftext|", "no special token"]
    for zero in (False, True):
        if zero:
            monkeypatch.setattr(tokenfiles, "span_hashes", lambda data, start, end: (end - start).astype(np.uint64) % np.uint64(3))
        own = tokenfiles.Encoder(tokenizer_path())
        for order in (texts, texts[::-1]):
            ids, at = own.batch(*raw(pa.array(order)))
            assert [ids[at[i] : at[i + 1]].tolist() for i in range(len(order))] == [encode(t) for t in order]
    own = tokenfiles.Encoder(tokenizer_path(), special_as_text=True)
    ids, _ = own.batch(*raw(pa.array(["a <|endoftext|> b"])))
    assert 50256 not in ids and own.tokenizer.decode(ids[:-1].tolist()) == "a <|endoftext|> b"


def test_token_files_odd_input(odd, empty):
    rows = tokenfiles.read(*tokenfiles.write(odd, tokenizer_path())).collect()
    assert len(rows) == odd.count() and {r.n_tokens for r in rows if r.doc_id in (1, 2)} == {1}
    assert tokenfiles.read(*tokenfiles.write(empty, tokenizer_path())).count() == 0


def brute(vectors, threshold=0.95):
    ids = sorted(vectors)
    good = {k: np.array(v, float) for k, v in vectors.items() if v is not None and len(v) and None not in v and np.isfinite(np.array(v, float)).all() and np.any(v)}
    links, top = Counter(), {k: k for k in ids}

    def find(a):
        while top[a] != a:
            a = top[a]
        return a

    for x, i in enumerate(ids):
        for j in ids[:x]:
            if i in good and j in good and len(good[i]) == len(good[j]):
                a, b = good[i], good[j]
                if a @ b / np.sqrt((a @ a) * (b @ b)) >= threshold:
                    links[i] += 1
                    links[j] += 1
                    low, high = sorted((find(i), find(j)))
                    top[high] = low
    return {k: (links[k], find(k), find(k) == k) for k in ids}


@pytest.mark.parametrize("kind", ["float", "double"])
def test_vector_join_equals_brute_force(spark, monkeypatch, kind):
    monkeypatch.setattr(embedding_join, "TILE", 40)
    monkeypatch.setattr(embedding_join, "SHOWN", 50)
    monkeypatch.setattr(embedding_join, "HOME", 20)
    monkeypatch.setattr(embedding_join, "LEAF", 4)
    monkeypatch.setattr(embedding_join, "SAMPLE", 200)
    rng = np.random.default_rng(10)
    center = rng.standard_normal(24)
    rows = {k: rng.standard_normal(24).astype(np.float32).tolist() for k in range(150)}
    rows |= {k: (center + 0.16 * rng.standard_normal(24)).astype(np.float32).tolist() for k in range(150, 300)}
    rows |= {k: rows[3] for k in range(300, 310)} | {k: (np.array(rows[5]) * (k - 300)).astype(np.float32).tolist() for k in range(310, 315)}
    rows |= {400: None, 401: [0.0] * 24, 402: [], 403: [1.0, None] + [0.0] * 22, 404: [float("nan")] * 24, 405: [float("inf")] + [1.0] * 23, 406: [1.0], 407: [2.0], 408: [-1.0], 409: [1e-30] * 24, 410: [1e-30] * 24}
    df = spark.createDataFrame([(k, v, "x", 1) for k, v in rows.items()], f"vec_id long, embedding array<{kind}>, id string, weight int")
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in embedding_join.embedding_join(df).collect()}
    assert got == brute(rows)
    assert embedding_join.embedding_join(df.limit(0)).count() == 0


def test_vector_join_of_repeated_ids_and_clashing_names(spark):
    """Equal rows of one id are one vector; different vectors of one id link each for itself; names of the join's own columns are free."""
    a, b, c = [1.0, 0.0, 0.0], [1.0, 0.01, 0.0], [0.0, 1.0, 0.0]
    rows = [(1, a), (1, a), (2, b), (3, c), (3, a), (None, a), (4, None), (4, None)]
    names = "key long, home int, block string, vector binary, weight int, component long, links long, h long, v int, _id long"
    df = spark.createDataFrame([(k, v, 1, 2, "x", b"x", 3, 4, 5, 6, 7, 8) for k, v in rows], f"vec_id long, embedding array<double>, {names}")
    got = sorted(((r.vec_id, r.n_links, r.component_id, r.kept) for r in embedding_join.embedding_join(df).collect()), key=str)
    # classes: a (ids 1, 3), b (id 2), c (id 3)
    assert got == sorted([(1, 2, 1, True), (1, 2, 1, True), (2, 2, 1, False), (3, 0, 3, True), (3, 2, 1, False), (None, 0, None, False), (4, 0, 4, True), (4, 0, 4, True)], key=str)


def test_vector_tiles_prune(spark):
    """The leaves of a tile leave fewer tests than all pairs, and lose none of the links, where vectors have room to lie apart."""
    rng = np.random.default_rng(3)
    x = rng.standard_normal((3000, 8)).astype(np.float32)
    x[1500:] = x[:1500] + 0.01 * rng.standard_normal((1500, 8))
    x = x.astype(np.float32)
    unit = x / np.linalg.norm(x, axis=1)[:, None]
    links, tests = np.zeros(3000, np.int64), 0
    for block in range(8):
        tile = embedding_join.Tile(np.arange(3000), np.full(3000, 2), block, [bytes([4]) + v.tobytes() for v in x], np.ones(3000, np.int64), 0.999)
        links += tile.run()[0]
        tests += tile.tests
    assert links.tolist() == ((unit.astype(np.float64) @ unit.T.astype(np.float64) >= 0.999).sum(1) - 1).tolist()
    assert tests < 0.5 * 8 * 3000 * 2999 / 2


def test_vector_join_on_the_given_table(spark, tiny):
    df = spark.read.parquet(f"{tiny}/embeddings.parquet")
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in embedding_join.embedding_join(df).collect()}
    x = {r.vec_id: r.embedding for r in df.collect()}
    m = np.array([x[k] for k in sorted(x)], float)
    m /= np.linalg.norm(m, axis=1)[:, None]
    links = (m @ m.T >= 0.95).sum(1) - 1
    assert [got[k][0] for k in sorted(x)] == links.tolist()


def test_pipeline_equals_its_parts(spark, tiny):
    """run() against a plain version of the stages after the classifier."""
    import corpus_pipeline as c

    docs = c.drop_toxic(spark, spark.read.parquet(f"{tiny}/documents.parquet"), tiny).cache()
    sets, left = {}, []
    for r in sorted(docs.collect(), key=lambda r: r.doc_id):
        w = re.findall(rb"[0-9a-z\x80-\xff]+", r.text.lower().encode())
        sets[r.doc_id] = frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])
    top = {k: k for k in sets}

    def find(a):
        while top[a] != a:
            a = top[a]
        return a

    for i in sets:
        for j in sets:
            both = len(sets[i] & sets[j]) if j < i else 0
            if both and both >= 0.8 * (len(sets[i]) + len(sets[j]) - both) - 1e-9:
                a, b = sorted((find(i), find(j)))
                top[b] = a
    left = {k for k in sets if find(k) == k}
    one = c.drop_near_copies(spark, docs, tiny)
    assert {r.doc_id for r in one.collect()} == left and one.columns == docs.columns
    texts = {r.doc_id: r for r in one.collect()}
    items = [" ".join(w.decode() for w in re.findall(rb"[0-9a-z\x80-\xff]+", r.text.lower().encode())) for r in spark.read.parquet(f"{tiny}/benchmark.parquet").collect()]
    leaked = {k for k, r in texts.items() if any(f" {x} " in " " + " ".join(w.decode() for w in re.findall(rb"[0-9a-z\x80-\xff]+", r.text.lower().encode())) + " " for x in items)}
    clean = c.drop_contaminated(spark, one, tiny)
    assert {r.doc_id for r in clean.collect()} == left - leaked
    mixed = c.mix_sources(spark, clean, tiny)
    assert mixed.columns == docs.columns
    times = Counter(r.doc_id for r in mixed.collect())
    assert set(times) <= left - leaked and max(times.values()) <= 3
    encode, start, want = reference(), 0, []
    for k in sorted(times):
        ids = encode(texts[k].text)
        for _ in range(times[k]):
            want.append((k, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
            start += len(ids)
    assert sorted(map(tuple, c.run(spark, tiny).collect())) == want


def test_stages_take_odd_and_empty_input(spark, odd, empty, tiny):
    import corpus_pipeline as c

    for rows in (odd, empty):
        docs = rows
        for k, (_, stage) in enumerate(c.STAGES):
            out = stage(spark, docs, tiny)
            if k + 1 < len(c.STAGES):
                assert out.columns == docs.columns
                docs = out.persist()
            out.count()
