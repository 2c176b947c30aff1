"""Operators on texts against brute force, and their results on odd input."""

import hashlib
import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from rotahash.llm import decontaminate, jaccard_join, language_id, licenses, lm_scoring, mixing, ppm, suffix_dedup, toxicity
from rotahash.llm.bytesops import U

WORDS = re.compile(rb"[0-9a-z\x80-\xff]+")
PLAIN = re.compile(rb"[^\x20\x09-\x0D]+")


def words(text):
    return WORDS.findall((text or "").lower().encode())


def lower(text):
    return bytes(c + 32 if 65 <= c <= 90 else c for c in (text or "").encode())


# ---- suffix-array dedup ----


def removed(rows, length=100):
    """Brute force: (doc_id -> mask) with a set of all strings seen."""
    seen, out = set(), {}
    for doc_id, text in sorted(rows.items()):
        data = (text or "").encode()
        gone = np.zeros(len(data), bool)
        for i in range(len(data) - length + 1):
            s = data[i : i + length]
            if s in seen:
                gone[i : i + length] = True
            seen.add(s)
        out[doc_id] = gone
    return out


def check_dedup(df, rows):
    want = removed(rows)
    got = {r.doc_id: r for r in suffix_dedup.deduplicate(df, text=True).collect()}
    assert got.keys() == rows.keys()
    for k, gone in want.items():
        data = np.frombuffer((rows[k] or "").encode(), np.uint8)
        kept = data[~gone].tobytes()
        spans = int((np.diff(np.concatenate([[0], gone.astype(int)])) > 0).sum())
        r = got[k]
        assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) == (len(data), int(gone.sum()), spans, hashlib.sha256(kept).hexdigest())
        assert bytes(r.kept) == kept and len(r.spans) == spans


@pytest.mark.parametrize("crowd", [0, 64])
def test_dedup_equals_brute_force(docs, texts, monkeypatch, crowd):
    monkeypatch.setattr(suffix_dedup, "CROWD", crowd)
    check_dedup(docs.where("length(text) < 6000"), {k: v for k, v in texts.items() if len(v) < 6000})


def test_dedup_of_an_anchor_wide_over_many_tasks(spark, monkeypatch):
    """No task sees a crowd, but all together do: the strings leave the merge and the result stays."""
    rng = np.random.default_rng(4)
    line = "a notice of some sixty bytes that stands in all of the texts"
    tails = ["".join(chr(97 + c) for c in rng.integers(0, 26, 80)) for _ in range(6)]
    rows = {i: "".join(chr(97 + c) for c in rng.integers(0, 26, 40)) + line + tails[i % 6] for i in range(48)}
    df = spark.createDataFrame(list(rows.items()), "doc_id long, text string").repartition(12)
    kinds = []
    for wide in (4, 4096):
        monkeypatch.setattr(suffix_dedup, "WIDE", wide)
        check_dedup(df, rows)
        met = suffix_dedup._meet(suffix_dedup._scan(df, 4))
        kinds.append({r.kind for r in met.select("kind").distinct().collect()})
    assert suffix_dedup.CROWDED in kinds[0] and suffix_dedup.CROWDED not in kinds[1]
    assert suffix_dedup.BOUNDARY in kinds[1]


def test_dedup_periodic_overlapping_and_boundary(spark):
    rng = np.random.default_rng(1)
    base = "".join(chr(97 + c) for c in rng.integers(0, 26, 400))
    rows = {1: base, 2: "x" + base[50:200] + "y" + base[180:330] + "z", 3: "ab" * 300, 4: base[:99], 5: base[:100], 6: "q" * 250, 7: base[100:199] + "!" + base[199:300], 8: None, 9: ""}
    check_dedup(spark.createDataFrame(list(rows.items()), "doc_id long, text string").repartition(5), rows)


def test_dedup_of_crowds(spark):
    rng = np.random.default_rng(2)
    line = "the same notice stands in every one of these many documents and it is longer than a hundred bytes so it goes from all but one"
    rows = {i: "".join(chr(97 + c) for c in rng.integers(0, 26, 150)) + line + "".join(chr(97 + c) for c in rng.integers(0, 26, 150)) for i in range(300)}
    check_dedup(spark.createDataFrame(list(rows.items()), "doc_id long, text string").repartition(3), rows)


def test_transforms_merge_to_sorted_blocks():
    rng = np.random.default_rng(3)
    texts = [rng.integers(97, 99, n).astype(np.uint8) for n in (300, 1, 40, 200)]
    shards = [(np.concatenate(texts[:2]), np.array([300, 301])), (np.concatenate(texts[2:]), np.array([40, 240]))]
    place, block = suffix_dedup.merge(shards, depth=8)
    whole, at = b"".join(t.tobytes() for t in texts), np.cumsum([0, *map(len, texts)])
    want = defaultdict(set)
    for k, t in enumerate(texts):
        for i in range(len(t) - 7):
            want[whole[at[k] + i : at[k] + i + 8]].add(int(at[k] + i))
    got = defaultdict(set)
    for p, b in zip(place.tolist(), block.tolist(), strict=True):
        got[b].add(p)
    assert sorted(map(sorted, got.values())) == sorted(sorted(v) for v in want.values() if len(v) > 1)


def test_transform_is_the_bwt():
    text = np.frombuffer(b"banana$ananas", np.uint8)
    order, back, symbol = suffix_dedup.transform(text, np.array([6, 13]))
    whole = [98, 97, 110, 97, 110, 97, -2, 36, 97, 110, 97, 110, 97, 115, -1]
    assert sorted(range(15), key=lambda i: [x for x in whole[i:]]) == order.tolist()
    assert [order[b] for b in back] == [(i - 1) % 15 for i in order]
    assert [s if s >= 0 else -1 for s in symbol.tolist()] == [max(whole[i - 1], -1) for i in order]


def test_dedup_odd_input(odd, empty):
    got = suffix_dedup.deduplicate(odd).collect()
    assert len(got) == odd.count()
    by = {r.doc_id: r for r in got}
    assert by[1].n_bytes == by[2].n_bytes == 0 and by[6].n_removed < by[7].n_removed
    assert suffix_dedup.deduplicate(empty).count() == 0


# ---- language-model scores and languages ----


def test_ppm_probabilities_sum_to_one():
    grams = ppm.Grams(3)
    data = np.frombuffer(b"the cat sat on the mat and the rat ran", np.uint8)
    grams.add(data, np.array([0, len(data)]))
    for escape in ("C", "D"):
        for limit in (1 << 20, 10):
            model = ppm.Model.of(3, *grams.fold(), limit=limit, escape=escape)
            for context in (b"the", b"\xff\xff\xff", b"zzz", b"at "):
                total = sum(10 ** model.code(np.frombuffer(context + bytes([x]), np.uint8), np.array([3]))[0] for x in range(256))
                assert abs(total - 1) < 1e-9


def naive_ppm(train, text, order):
    """Log10 probability by dictionaries, escape estimate D."""
    seen = [defaultdict(Counter) for _ in range(order + 1)]
    for t in train:
        s = b"\xff" * order + t + b"\xff"
        for i in range(order, len(s)):
            for n in range(order + 1):
                seen[n][s[i - n : i]][s[i]] += 1
    s, total = b"\xff" * order + text + b"\xff", 0.0
    for i in range(order, len(s)):
        out = set()
        for n in range(order, -2, -1):
            if n < 0:
                total -= math.log10(256 - len(out))
                break
            node = {c: k for c, k in seen[n][s[i - n : i]].items() if c not in out}
            if not node:
                continue
            t = sum(node.values())
            if s[i] in node:
                total += math.log10((node[s[i]] - 0.5) / t)
                break
            total += math.log10(len(node) / 2 / t)
            out |= node.keys()
    return total


def test_lm_scores_equal_brute_force(docs, texts):
    df = docs.where("length(text) < 3000")
    rows = {k: v for k, v in texts.items() if len(v) < 3000}
    held = {k: zlib.crc32(str(k).encode()) % 7 == 2 for k in rows}
    counts, ends = Counter(), 0
    for k, t in rows.items():
        if not held[k]:
            counts.update(PLAIN.findall(lower(t)))
            ends += 1
    n, v = sum(counts.values()) + ends, len(counts) + 1
    got = {r.doc_id: r for r in lm_scoring.score(df).collect()}
    assert got.keys() == rows.keys()
    train = [lower(t) for k, t in rows.items() if not held[k]]
    for i, (k, t) in enumerate(sorted(rows.items())):
        own = PLAIN.findall(lower(t))
        base = sum(math.log10((counts[w] + 1) / (n + v + 1)) for w in own) + math.log10((ends + 1) / (n + v + 1))
        r = got[k]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[k], len(own) + 1, sum(counts[w] > 0 for w in own) + 1, n)
        assert math.isclose(r.base_score, base, rel_tol=1e-9)
        if i < 3:
            assert math.isclose(r.score, naive_ppm(train, lower(t), lm_scoring.ORDER), rel_tol=1e-6)


def test_lm_scores_keep_every_string(spark, monkeypatch):
    """Over 2^20 different strings of an order, and tasks in several segments: nothing is pruned."""
    monkeypatch.setattr(lm_scoring, "STRINGS", 1 << 17)
    letters = np.random.default_rng(3).integers(97, 123, (220, 8000)).astype(np.uint8)
    rows = [(k, x.tobytes().decode()) for k, x in enumerate(letters)]
    held = np.array([zlib.crc32(str(k).encode()) % 7 == 2 for k, _ in rows])
    grams, at = ppm.Grams(lm_scoring.ORDER), np.arange(0, (~held).sum() * 8000 + 1, 8000)
    grams.add(letters[~held].ravel(), at)
    keys, counts = grams.fold()
    assert len(keys) > 1 << 20
    want = ppm.Model.of(lm_scoring.ORDER, keys, counts, limit=1 << 30).score(letters.ravel(), np.arange(0, letters.size + 1, 8000))
    got = {r.doc_id: r.score for r in lm_scoring.score(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert len(got) == 220 and all(math.isclose(got[k], want[k], rel_tol=1e-9) for k in got)


def test_lm_adaptive_and_odd(odd, empty):
    assert math.isclose(ppm.adaptive(b"", 2), -math.log10(256))
    assert ppm.adaptive(b"ab" * 50, 2) > ppm.adaptive(bytes(range(100)), 2)
    got = lm_scoring.score(odd).collect()
    assert len(got) == odd.count()
    assert {r.n_tokens for r in got if r.doc_id in (1, 2, 3)} == {1}
    assert lm_scoring.score(empty).count() == 0
    assert lm_scoring.adaptive_scores(odd.where("doc_id < 6")).count() == 5


def test_language_is_found_on_held_out_texts(docs, odd, empty):
    got = {r.doc_id: r for r in language_id.identify(docs).collect()}
    langs = {r.doc_id: r.lang for r in docs.collect()}
    held = [k for k in langs if zlib.crc32(str(k).encode()) % 5 == 0]
    assert all(got[k].held_out for k in held) and len(held) == sum(r.held_out for r in got.values())
    assert np.mean([got[k].lang_pred == langs[k] for k in held]) > 0.97
    assert all(0 <= r.score <= 1 for r in got.values())
    rows = language_id.identify(odd).collect()
    assert len(rows) == odd.count()
    assert all(r.lang_pred == "und" for r in rows if r.doc_id in (1, 2, 3, 9)) and all(r.lang_pred in ("en", "fr", "de") for r in rows if r.doc_id in (4, 6, 8, 10))
    assert language_id.identify(empty).count() == 0
    assert {r.lang_pred for r in language_id.identify(docs.selectExpr("doc_id", "text", "cast(null as string) lang").limit(5)).collect()} == {"und"}


def test_language_scores_equal_brute_force(spark):
    """One dictionary PPM a language, learned from the rows that are not held out, and equal priors."""
    rng = np.random.default_rng(11)
    letters = {"aa": "abcde ", "bb": "bcdef ", "cc": "cd\u00e9fg "}
    rows = [(k, "x" + "".join(rng.choice(list(letters[x]), int(rng.integers(3, 30)))), x) for k, x in enumerate(["aa", "bb", "cc"] * 20)]
    train = {x: [t.encode() for k, t, own in rows if own == x and zlib.crc32(str(k).encode()) % 5] for x in letters}
    got = {r.doc_id: r for r in language_id.identify(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    for k, t, _ in rows[:15]:
        code = {x: naive_ppm(own, t.encode(), language_id.ORDER) for x, own in train.items()}
        best = max(sorted(code), key=code.get)
        assert got[k].lang_pred == best
        assert math.isclose(got[k].score, 1 / sum(10 ** (c - code[best]) for c in code.values()), rel_tol=1e-6)


# ---- n-gram Jaccard join ----


def shingle_set(text):
    w = words(text)
    return frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])


def linked(rows, threshold=0.8):
    """Brute force: links and least reachable id."""
    ids = sorted(rows)
    sets = {k: shingle_set(rows[k]) for k in ids}
    links, top = Counter(), {k: k for k in ids}

    def find(a):
        while top[a] != a:
            a = top[a]
        return a

    for x, i in enumerate(ids):
        for j in ids[:x]:
            both = len(sets[i] & sets[j])
            if both and both >= threshold * (len(sets[i]) + len(sets[j]) - both) - 1e-9:
                links[i] += 1
                links[j] += 1
                a, b = sorted((find(i), find(j)))
                top[b] = a
    return {k: (find(k), links[k]) for k in ids}


def test_jaccard_join_equals_brute_force(docs, texts):
    got = {r.doc_id: (r.class_id, r.n_links) for r in jaccard_join.jaccard_join(docs).collect()}
    assert got == linked(texts)


def test_jaccard_join_of_a_hot_group(spark, monkeypatch):
    """A group far larger than a bucket and a tile keeps all its links."""
    monkeypatch.setattr(jaccard_join, "BUCKET", 8)
    monkeypatch.setattr(jaccard_join, "TILE", 16)
    monkeypatch.setattr(jaccard_join, "LOAD", 2000)  # ten sets
    rng = np.random.default_rng(4)
    base = [f"w{i}" for i in range(200)]
    rows = {}
    for k in range(90):
        own = list(base)
        own[int(rng.integers(200))] = f"x{k}"
        rows[k] = " ".join(own)
    for k in range(90, 120):
        rows[k] = rows[0]
    for k in range(120, 200):
        rows[k] = " ".join(f"r{rng.integers(10**6)}" for _ in range(50))
    got = {r.doc_id: (r.class_id, r.n_links) for r in jaccard_join.jaccard_join(spark.createDataFrame(list(rows.items()), "doc_id long, text string")).collect()}
    assert got == linked(rows)


def test_jaccard_join_keeps_the_links_of_a_hot_group_at_the_threshold(spark):
    """300 near copies whose pairs lie just above the threshold share buckets that are split to the last depth."""
    base = " ".join(f"w{i}" for i in range(96))
    rows = {k: f"{base} " + " ".join(f"x{k}y{i}" for i in range(10)) for k in range(300)}  # 92 shingles of 112 in common: .82
    assert jaccard_join.runs_for(0.8, jaccard_join.LAST) == 31 and jaccard_join.recall(0.8, runs=31) > jaccard_join.TARGET
    got = {r.doc_id: (r.class_id, r.n_links) for r in jaccard_join.jaccard_join(spark.createDataFrame(list(rows.items()), "doc_id long, text string")).collect()}
    want = linked(rows)
    assert all(x == (0, 299) for x in want.values()) and [k for k in rows if got[k][0]] == []
    assert sum(n for _, n in got.values()) >= jaccard_join.TARGET * sum(n for _, n in want.values())


def test_jaccard_join_odd_input(odd, empty):
    rows = {r.doc_id: r for r in jaccard_join.jaccard_join(odd).collect()}
    assert rows[4].class_id == rows[5].class_id == 4 and rows[7].class_id == 6
    assert rows[1].n_links == rows[2].n_links == rows[3].n_links == 0
    kept = jaccard_join.keep_one(odd)
    assert kept.columns == odd.columns
    assert sorted(r.doc_id for r in kept.collect() if r.doc_id is not None) == [1, 2, 3, 4, 6, 8, 9, 10]
    assert jaccard_join.keep_one(empty).count() == 0
    assert jaccard_join.recall(0.8) > 0.99 and jaccard_join.recall(0.8, jaccard_join.FIRST) > 0.9999


# ---- decontamination ----


def test_tiling_catches_reordered_passages():
    item = np.arange(1, 31, dtype=U)
    text = np.concatenate([np.arange(100, 140, dtype=U), item[15:], np.arange(200, 220, dtype=U), item[:15], item[:4]])
    tiles = decontaminate.tile(item, text)
    assert sorted((i, n) for i, _, n in tiles) == [(0, 15), (15, 15)]
    assert sum(n for _, _, n in decontaminate.tile(item, item[::-1].copy())) == 0
    assert decontaminate.tile(item, np.zeros(0, U)) == []


def naive_tiles(item, text, least=5):
    """Greedy string tiling by its definition: the longest unmarked match each time."""
    used_i, used_t, covered = set(), set(), 0
    while True:
        best = (0, 0, 0)
        for i in range(len(item)):
            for j in range(len(text)):
                n = 0
                while i + n < len(item) and j + n < len(text) and item[i + n] == text[j + n] and i + n not in used_i and j + n not in used_t:
                    n += 1
                best = max(best, (n, -i, -j))
        n, i, j = best[0], -best[1], -best[2]
        if n < least:
            return covered
        used_i |= set(range(i, i + n))
        used_t |= set(range(j, j + n))
        covered += n


def test_tiling_covers_as_the_definition():
    rng = np.random.default_rng(6)
    for _ in range(60):
        item, text = rng.integers(1, 4, 24).astype(U), rng.integers(1, 4, 40).astype(U)
        assert sum(n for _, _, n in decontaminate.tile(item, text)) == naive_tiles(item.tolist(), text.tolist())


def test_decontamination_equals_brute_force(spark):
    """Every document tiled against every item by the definition, and the item that covers most."""
    rng = np.random.default_rng(7)
    items = {k: [f"w{x}" for x in rng.integers(0, 4, int(rng.integers(3, 24)))] for k in range(8)}
    docs = {k: [f"w{x}" for x in rng.integers(0, 4, int(rng.integers(0, 40)))] for k in range(25)}
    docs[25] = docs[3][:9] + items[2] + docs[4][:9]
    table = lambda rows, name: spark.createDataFrame([(k, " ".join(w)) for k, w in rows.items()], f"{name} long, text string")
    got = {r.doc_id: r for r in decontaminate.report(table(docs, "doc_id"), table(items, "item_id")).collect()}
    assert got.keys() == docs.keys()
    for k, text in docs.items():
        cover = {i: naive_tiles(item, text) / len(item) for i, item in items.items()}
        most = max(cover.values())
        assert math.isclose(got[k].coverage, most, abs_tol=1e-12)
        assert got[k].item_id == (min(i for i, c in cover.items() if c == most) if most else None)
        assert got[k]["items"] == [i for i, c in cover.items() if c >= decontaminate.THRESHOLD]
        assert got[k].contaminated == bool(got[k]["items"])
    assert 2 in got[25]["items"]


def test_decontamination(spark, docs, texts, tiny, odd, empty):
    bench = spark.read.parquet(f"{tiny}/benchmark.parquet")
    items = {r.item_id: r.text for r in bench.collect()}
    got = {r.doc_id: r for r in decontaminate.report(docs, bench).collect()}
    for k, t in texts.items():
        whole = " ".join(w.decode() for w in words(t))
        inside = {i for i, x in items.items() if f" {' '.join(w.decode() for w in words(x))} " in f" {whole} "}
        assert inside <= set(got[k].items)
        assert got[k].contaminated == bool(got[k].items)
    chunked = {r.doc_id: r.asDict() for r in decontaminate.report(docs, bench, chunk_chars=2000).collect()}
    assert chunked == {k: r.asDict() for k, r in got.items()}
    clean = decontaminate.decontaminate(docs, bench)
    assert sorted(r.doc_id for r in clean.collect()) == sorted(k for k, r in got.items() if not r.contaminated)
    assert decontaminate.decontaminate(odd, bench).count() == odd.count()
    nothing = spark.createDataFrame([(1, None), (2, ""), (3, "one two")], "item_id long, text string")
    assert decontaminate.report(odd, nothing).where("contaminated").count() == 0
    assert decontaminate.report(empty, bench).count() == 0 and decontaminate.report(odd, bench.limit(0)).count() == odd.count()
    reordered = spark.createDataFrame([(1, "Zeta one two three four five. Six SEVEN eight, nine ten!")], "item_id long, text string")
    doc = spark.createDataFrame([(1, "intro words six seven eight nine ten and then one two three four five ok"), (2, "one two three four")], "doc_id long, text string")
    assert [r.doc_id for r in decontaminate.report(doc, reordered).where("contaminated").collect()] == [1]


# ---- licences ----


def test_licences_equal_brute_force(docs, texts, odd, empty):
    def pairs(text):
        w = words(text)
        return set(zip(w, w[1:], strict=False))

    templates = [(n, pairs(t)) for n, t in licenses.TEMPLATES]
    got = {r.doc_id: r for r in licenses.scan(docs).collect()}
    for k, text in texts.items():
        lines = text.split("\n")
        body = " \n ".join(x for x in lines if words(x)[:1] != [b"copyright"])
        best, many = (0.0, None, None), 0
        for place, unit in [(-1, pairs(body)), *((i, pairs(x)) for i, x in enumerate(lines))]:
            dice = [(2 * len(unit & t) / (len(unit) + len(t)) if unit else 0.0, n) for n, t in templates]
            many += max(d for d, _ in dice) >= licenses.THRESHOLD
            for d, n in dice:
                if d >= licenses.THRESHOLD and d > best[0]:
                    best = (d, n, place)
        assert (got[k].license, got[k].line, got[k].n_matches) == (best[1], best[2], many) and math.isclose(got[k].dice, best[0])
    assert licenses.scan(odd).where("license is not null").count() == 0 and licenses.scan(odd).count() == odd.count()
    assert licenses.scan(empty).count() == 0


def test_a_whole_licence_with_edits(spark):
    text = "Copyright (c) 2020 Somebody\n" + licenses.MIT.replace("Software without restriction", "Program without restriction").replace(". ", ".\n\n")
    got = licenses.scan(spark.createDataFrame([(1, text), (2, licenses.MIT[:300])], "doc_id long, text string")).orderBy("doc_id").collect()
    assert (got[0].license, got[0].line) == ("MIT", -1) and got[1].license is None


def test_a_licence_inside_a_longer_text(spark):
    """A block wrapped over lines, a notice amid other words of its line, two blocks, and a part too short to match."""
    wrap = lambda text, n=9: "\n".join(" ".join(text.split()[i : i + n]) for i in range(0, len(text.split()), n))
    prose = " ".join(f"word{i}" for i in range(900))
    rows = [(1, f"{prose}\nCopyright 2020 Foo\n{wrap(licenses.MIT)}\n{prose}"), (2, f"{prose}\nFoo Inc. All rights reserved. More"), (3, f"{prose}\n{wrap(licenses.MIT)}\n{prose}\n{wrap(licenses.ISC)}"), (4, f"{prose}\n{wrap(licenses.MIT[:500])}\n{prose}")]
    got = {r.doc_id: (r.license, round(r.dice, 6), r.line, r.n_matches) for r in licenses.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: ("MIT", 1, 2, 1), 2: ("all-rights-reserved", 1, 1, 1), 3: ("MIT", 1, 1, 2), 4: (None, 0, None, 0)}


# ---- toxicity ----


def test_toxicity_held_out_accuracy(spark, odd, empty):
    rng = np.random.default_rng(8)
    bad = ["vile", "filth", "hateful"]
    rows, labels = [], []
    for k in range(1200):
        w = [f"w{rng.integers(300)}" for _ in range(40)]
        toxic = k % 6 == 0
        if toxic:
            for x in rng.choice(bad, 2):
                w[rng.integers(40)] = x
        rows.append((k, " ".join(w)))
        labels.append((k, int(k % 3 != 0), int(toxic)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    half = spark.createDataFrame(labels[:600] + [(None, 1, 1), (5, None, None)], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in toxicity.classify(docs, half).collect()}
    held = range(600, 1200)
    assert np.mean([got[k].rejected == (k % 6 == 0) for k in held]) > 0.98
    again = {r.doc_id: r.p_toxic for r in toxicity.classify(docs, half).collect()}
    assert all(again[k] == got[k].p_toxic for k in got)
    kept = toxicity.reject(odd, half)
    assert kept.columns == odd.columns and kept.count() == odd.count()
    assert toxicity.classify(empty, half).count() == 0
    none = toxicity.classify(odd, half.limit(0)).collect()
    assert len(none) == odd.count() and not any(r.rejected for r in none)


def plain_fit(x, y, earlier, steps=600, decay=1e-5):
    """Dense logistic regression on the words whose chi-square tells the classes apart; the chosen words and the weights."""
    seen, expect = x.sum(0), x.sum(0) * y.mean()
    use = (seen >= 4) & ((x.T @ y - expect) ** 2 > 4 * expect * (1 - y.mean()))
    a = np.column_stack([x[:, use], earlier, np.ones(len(y))])
    w = v = np.zeros(a.shape[1])
    for t in range(steps):
        grad = a.T @ ((1 / (1 + np.exp(-a @ v)) - y) / len(y)) + decay * np.append(v[:-1], 0)
        step = v - 4 / (1 + x[:, use].sum() / len(y)) * grad
        v, w = step + t / (t + 3) * (step - w), step
    return use, w


def plain_score(model, x, earlier):
    use, w = model
    return 1 / (1 + np.exp(-np.column_stack([x[:, use], earlier, np.ones(len(x))]) @ w))


def test_toxicity_equals_a_plain_chain(spark):
    """The chain refitted on dense words: the second model sees out-of-fold answers of the first."""
    rng = np.random.default_rng(12)
    x = (rng.random((400, 50)) < 0.15).astype(float)
    good = ((x[:, 0] + x[:, 1] + rng.random(400) * 0.6) > 0.7).astype(float)
    toxic = ((x[:, 2] + x[:, 3] - 0.5 * good + rng.random(400) * 0.5) > 0.5).astype(float)
    docs = spark.createDataFrame([(k, " ".join(f"term{j}" for j in np.flatnonzero(row))) for k, row in enumerate(x)], "doc_id long, text string")
    labels = spark.createDataFrame([(k, int(good[k]), int(toxic[k])) for k in range(300)], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in toxicity.classify(docs, labels).collect()}
    fold = np.array([((k * 0x9E3779B97F4A7C15 & ((1 << 64) - 1)) >> 40) % 4 for k in range(300)])
    fit, none = x[:300], np.zeros((400, 0))
    first, out = plain_fit(fit, good[:300], none[:300]), np.zeros(300)
    for f in range(4):
        held = fold == f
        out[held] = plain_score(plain_fit(fit[~held], good[:300][~held], none[: int((~held).sum())]), fit[held], none[: int(held.sum())])
    second = plain_fit(fit, toxic[:300], out[:, None])
    quality = plain_score(first, x, none)
    want = plain_score(second, x, quality[:, None])
    for k in range(400):
        assert math.isclose(got[k].p_quality, quality[k], rel_tol=1e-6) and math.isclose(got[k].p_toxic, want[k], rel_tol=1e-6)


# ---- mixing ----


def test_mixing_targets():
    got = {n: t for n, _, t in mixing.targets([("b", 100), ("a", 10), (None, 50), ("c", 1000)])}
    assert math.isclose(sum(got.values()), 1160) and got["a"] == 30 and got[None] <= 150
    assert mixing.targets([]) == [] and mixing.targets([("a", 0)]) == [("a", 0, 0.0)]


def test_mixing_meets_targets(docs, texts, odd, empty):
    sized = mixing.sized(docs)
    assert {r.doc_id: r["size"] for r in sized.collect()} == {k: len(PLAIN.findall(t.encode())) for k, t in texts.items()}
    got = mixing.mix(sized).collect()
    by = defaultdict(list)
    for r in got:
        by[r.source].append(r)
    assert sum(r.taken for r in got) <= sum(r["size"] for r in got)
    for rows in by.values():
        largest = max(r["size"] for r in rows)
        assert abs(sum(r.taken for r in rows) - rows[0].target) <= 2 * largest
        assert all(r.taken % max(r["size"], 1) == 0 and r.taken <= 3 * r["size"] for r in rows)
    again = {r.doc_id: r.taken for r in mixing.mix(mixing.sized(docs.repartition(7))).collect()}
    assert again == {r.doc_id: r.taken for r in got}
    odd_rows = mixing.mix(mixing.sized(odd, ("doc_id", "source", "id", "_h", "_rest", "key"))).collect()
    assert len(odd_rows) == odd.count() and {r["_h"] for r in odd_rows} == {"h"} and {r["_rest"] for r in odd_rows} == {"r"}
    assert mixing.mix(mixing.sized(empty)).count() == 0


def test_mixing_equals_the_queue_by_definition(spark):
    """The cut is that of a full sort by virtual finish time."""
    rng = np.random.default_rng(9)
    rows = [(k, f"s{k % 4}", int(rng.integers(1, 30))) for k in range(200)]
    df = spark.createDataFrame(rows, "doc_id long, source string, size long")
    got = {r.doc_id: r for r in mixing.mix(df).collect()}
    hashed = {r.doc_id: r.h for r in df.selectExpr("doc_id", "xxhash64(7, doc_id) h").collect()}
    copies = []
    for name in sorted({s for _, s, _ in rows}):
        upto, own = 0, sorted((r for r in rows if r[1] == name), key=lambda r: (hashed[r[0]], r[0]))
        for k, _, n in own:
            upto += n
            r = got[k]
            copies += [((upto + r.source_size * e) / r.target, hashed[k], k, e, n) for e in range(3)]
    taken, spent = Counter(), 0
    for _, _, k, _, n in sorted(copies):
        spent += n
        if spent > sum(n for _, _, n in rows):
            break
        taken[k] += n
    assert {k: r.taken for k, r in got.items()} == {k: taken[k] for k, _, _ in rows}
