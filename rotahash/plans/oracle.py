"""DuckDB SQL of the sketches, written from their definitions and not from the Spark plans."""

from __future__ import annotations

from rotahash.functions.hashes import walk
from rotahash.operators.permutations import feistel_keys, mix_constants
from rotahash.params import SketchParams

WORDS = "SELECT DISTINCT w AS set_id, doc_id AS elem FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^a-z0-9]+')) AS w FROM documents) WHERE w <> ''"


#: Worked out before what uses them, whose joins would else be reordered badly.
KEPT = ("base", "reads", "read_at")


def ctes(parts: dict[str, str], final: str) -> str:
    return "WITH " + ",\n".join(f"{k} AS {'MATERIALIZED ' if k in KEPT else ''}({v})" for k, v in parts.items()) + "\n" + final


def perm(tag: str, n: int) -> str:
    return f"SELECT s.seed, r.pos, row_number() OVER (PARTITION BY s.seed ORDER BY md5(concat(s.seed, ':{tag}:', r.pos)), r.pos) - 1 AS rank FROM seeds s, (SELECT unnest(range({n})) AS pos) r"


def slot_perm(tag: str, slots: int, n: int) -> str:
    return f"SELECT s.seed, t.slot, r.pos, row_number() OVER (PARTITION BY s.seed, t.slot ORDER BY md5(concat(s.seed, ':{tag}', t.slot, ':', r.pos)), r.pos) - 1 AS rank FROM seeds s, (SELECT unnest(range({slots})) AS slot) t, (SELECT unnest(range({n})) AS pos) r"


def hex32(*parts: str) -> str:
    return f"CAST(concat('0x', substr(md5(concat({', '.join(parts)})), 1, 8)) AS BIGINT)"


def hashed(x: str, kind: str, p: SketchParams, size: int, tag: str) -> str:
    """SQL expression of x under the hash function of the row's seed; x is BIGINT."""

    def by_seed(of) -> str:
        return "CASE seed " + " ".join(f"WHEN {s} THEN {of(s)}" for s in p.seeds) + " END"

    if kind == "2u":
        return by_seed(lambda s: "CAST((({}::HUGEINT * {} + {}) % {}) % {} AS BIGINT)".format(x, *p.linear(s, tag, size), size))
    if kind == "4u":

        def cubic(s):
            a, b, c, d, q = p.cubic(s, tag, size)
            return f"CAST((((((({a}::HUGEINT * {x} + {b}) % {q}) * {x} + {c}) % {q}) * {x} + {d}) % {q}) % {size} AS BIGINT)"

        return by_seed(cubic)
    bits = size.bit_length() - 1
    if kind == "mix":

        def mix(s):
            y = x
            for odd, c in mix_constants(s, bits):
                y = f"(({y} * {odd} + {c}) & {(1 << bits) - 1})"
                y = f"xor({y}, {y} >> {max(1, bits // 2)})"
            return y

        return by_seed(mix)
    if kind == "feistel":
        bits, steps = walk(size)
        half = bits // 2
        mask = (1 << half) - 1

        def rounds(s, v):
            left, right = f"({v} >> {half})", f"({v} & {mask})"
            for key in feistel_keys(s):
                f = f"((((({right})::HUGEINT * {key % (1 << 30) | 1} + {key % 65521}) % {(1 << 61) - 1})::BIGINT >> 7) & {mask})"
                left, right = right, f"xor({left}, {f})"
            return f"((({left}) << {half}) | ({right}))"

        if not steps:
            return by_seed(lambda s: rounds(s, x))
        return by_seed(lambda s: f"list_reduce(list_concat([{rounds(s, x)}], CAST(range({steps}) AS BIGINT[])), lambda v, i: CASE WHEN v < {size} THEN v ELSE {rounds(s, 'v')} END)")
    if kind == "murmur":
        # Spark's Murmur3 of an int and a long: rounds on 32-bit words, as fixed by that function
        return by_seed(lambda s: _pmod_signed(_murmur_long(x, _murmur_int(s, 42)), size))
    if kind == "identity":
        return x
    raise ValueError(f"{kind} has no SQL")


#: Fixed values of Murmur3, 32 bits: the two factors of a word, the step of the state, the two factors of the end.
MURMUR = (0xCC9E2D51, 0x1B873593, 0xE6546B64, 0x85EBCA6B, 0xC2B2AE35)
WORD = 1 << 32


def let(value: str, body) -> str:
    """body of a name that stands for value, so that the text stays short."""
    return f"list_transform([{value}], lambda v: {body('v')})[1]"


def _times(x: str, factor: int) -> str:
    return f"CAST(({x}::HUGEINT * {factor}) % {WORD} AS BIGINT)"


def _turned(x: str, r: int) -> str:
    return let(x, lambda v: f"((({v} << {r}) | ({v} >> {32 - r})) & {WORD - 1})")


def _murmur_step(h: str, k: str) -> str:
    state = f"xor({h}, {_times(_turned(_times(k, MURMUR[0]), 15), MURMUR[1])})"
    return f"(({_turned(state, 13)} * 5 + {MURMUR[2]}) & {WORD - 1})"


def _murmur_end(h: str, size: int) -> str:
    out = f"xor({h}, {size})"
    for shift, factor in ((16, MURMUR[3]), (13, MURMUR[4]), (16, None)):
        out = let(out, lambda v, n=shift: f"xor({v}, {v} >> {n})")
        out = _times(out, factor) if factor else out
    return out


def _murmur_long(x: str, seed: int) -> str:
    return _murmur_end(_murmur_step(_murmur_step(str(seed), f"({x} & {WORD - 1})"), f"(({x} >> 32) & {WORD - 1})"), 8)


def _murmur_int(x: int, seed: int) -> int:
    """The same of one 32-bit number, in Python: the state that a row's seed leaves."""

    def turned(v, r):
        return (v << r | v >> (32 - r)) % WORD

    h = (turned(seed ^ turned(x * MURMUR[0] % WORD, 15) * MURMUR[1] % WORD, 13) * 5 + MURMUR[2]) % WORD ^ 4
    h = (h ^ h >> 16) * MURMUR[3] % WORD
    h = (h ^ h >> 13) * MURMUR[4] % WORD
    return h ^ h >> 16


def _pmod_signed(h: str, size: int) -> str:
    return let(let(h, lambda v: f"CASE WHEN {v} >= {WORD // 2} THEN {v} - {WORD} ELSE {v} END"), lambda v: f"(({v} % {size}) + {size}) % {size}")


def _head(postings: dict[str, str], p: SketchParams) -> dict[str, str]:
    """Up to ``q``: the shuffled positions. ``postings``: CTEs whose last is post(set_id, elem)."""
    out = {"seeds": f"SELECT unnest([{', '.join(map(str, p.seeds))}]) AS seed"} | postings
    if p.split == "perm":
        out["sigma"] = perm("sigma", p.D)
        out["q"] = "SELECT s.seed, p.set_id, s.rank AS q FROM post p JOIN sigma s ON s.pos = p.elem"
    else:
        out["q"] = f"SELECT seed, set_id, {hashed('elem', p.split, p, p.D, p.split)} AS q FROM (SELECT s.seed, p.set_id, CAST(p.elem AS BIGINT) AS elem FROM post p, seeds s)"
    return out


def std(postings: dict[str, str], p: SketchParams) -> dict[str, str]:
    out = {"seeds": f"SELECT unnest([{', '.join(map(str, p.seeds))}]) AS seed"} | postings
    out["perms"] = slot_perm("std", p.slots, p.D)
    out["sig"] = "SELECT t.seed, p.set_id, t.slot, min(t.rank) AS h FROM post p JOIN perms t ON t.pos = p.elem GROUP BY ALL"
    return out


def rot(postings: dict[str, str], p: SketchParams) -> dict[str, str]:
    out = _head(postings, p)
    out["turned"] = f"SELECT q.seed, set_id, slot, ((q - slot - 1) % {p.D} + {p.D}) % {p.D} AS pos FROM q, (SELECT unnest(range({p.slots})) AS slot)"
    if p.inner == "perm":
        out["pi"] = perm("sigma" if p.share else "pi", p.D)
        out["sig"] = "SELECT t.seed, set_id, slot, min(rank) AS h FROM turned t JOIN pi ON pi.seed = t.seed AND pi.pos = t.pos GROUP BY ALL"
    else:
        out["sig"] = f"SELECT seed, set_id, slot, min({hashed('pos', p.inner, p, p.D, f'inner-{p.inner}')}) AS h FROM turned GROUP BY ALL"
    return out


def binned(postings: dict[str, str], p: SketchParams) -> dict[str, str]:
    """Up to ``sig`` of binned MinHash with any filling."""
    K, M, d, D = p.K, p.slots, p.d, p.D
    out = _head(postings, p)
    out["base"] = f"SELECT seed, set_id, q, q // {d} AS bin, q % {d} AS off FROM q"
    out["occ"] = "SELECT DISTINCT seed, set_id, bin FROM base"
    scan = f"slot % {K}" if p.first_scan == "rotate" else f"{hex32('seed', quote(':scan:'), 'slot')} % {K}"
    extra = {"plain": "0", "per_round": f"(slot + 1) // {K}", "per_cycle": f"(slot + 1) // {d}", "lcm": f"slot // lcm({K}, {d})"}[p.shift]
    out["slots"] = f"SELECT seed, slot, {scan} AS bin0, slot + 1 + {extra} AS turn, CASE WHEN {hex32('seed', quote(':coin:'), 'slot')} % 2 = 1 THEN 1 ELSE -1 END AS coin FROM seeds, (SELECT unnest(range({M})) AS slot)"
    out["grid"] = "SELECT * FROM (SELECT DISTINCT set_id FROM occ), slots"
    out["scan"] = "SELECT g.*, o.bin AS hit FROM grid g LEFT JOIN occ o ON o.seed = g.seed AND o.set_id = g.set_id AND o.bin = g.bin0"
    out["gap"] = f"SELECT e.seed, e.set_id, e.slot, min(((o.bin - e.bin0) % {K} + {K}) % {K}) AS rightward, min(((e.bin0 - o.bin) % {K} + {K}) % {K}) AS leftward FROM scan e JOIN occ o ON o.seed = e.seed AND o.set_id = e.set_id WHERE e.hit IS NULL GROUP BY ALL"
    if p.fill == "none":
        donor, dist = "NULL", "NULL"
    elif p.donor == "clockwise":
        donor, dist = f"(e.bin0 + g.rightward) % {K}", "g.rightward"
    elif p.donor == "two_way":
        donor = f"CASE WHEN e.coin > 0 THEN (e.bin0 + g.rightward) % {K} ELSE (e.bin0 - g.leftward + {K}) % {K} END"
        dist = "CASE WHEN e.coin > 0 THEN g.rightward ELSE g.leftward END"
    else:
        out["probes"] = f"SELECT seed, slot, attempt, {hex32('seed', quote(':probe:'), 'slot', quote(':'), 'attempt')} % {K} AS bin FROM seeds, (SELECT unnest(range({M})) AS slot), (SELECT unnest(range({p.attempts})) AS attempt)"
        out["drawn"] = "SELECT o.seed, o.set_id, r.slot, arg_min(r.bin, r.attempt) AS bin FROM occ o JOIN probes r ON o.seed = r.seed AND o.bin = r.bin GROUP BY ALL"
        donor, dist = f"coalesce(w.bin, (e.bin0 + g.rightward) % {K})", "g.rightward"
    more = " LEFT JOIN drawn w ON w.seed = e.seed AND w.set_id = e.set_id AND w.slot = e.slot" if p.donor == "uniform" and p.fill != "none" else ""
    out["reads"] = f"SELECT e.seed, e.set_id, e.slot, e.turn, coalesce(e.hit, {donor}) AS bin, CASE WHEN e.hit IS NOT NULL THEN 0 ELSE {dist} END AS dist FROM scan e LEFT JOIN gap g ON g.seed = e.seed AND g.set_id = e.set_id AND g.slot = e.slot{more}"
    on = "b.seed = r.seed AND b.set_id = r.set_id AND b.bin = r.bin"
    if p.fill in ("none", "copy"):
        move = f" + any_value(r.dist) * {D + 1}" if p.copy_offset else ""
        out["sig"] = f"SELECT r.seed, r.set_id, r.slot, min(b.q){move} AS h FROM reads r LEFT JOIN base b ON {on} GROUP BY r.seed, r.set_id, r.slot"
    elif p.fill == "rotate":
        pos = f"((b.off - r.turn) % {d} + {d}) % {d}"
        if p.inner == "feistel":
            out["sig"] = f"SELECT seed, set_id, slot, min({hashed('pos', 'feistel', p, d, 'pi')} + bin * {d}) AS h FROM (SELECT r.seed, r.set_id, r.slot, r.bin, {pos} AS pos FROM reads r JOIN base b ON {on}) GROUP BY ALL"
        else:
            out["pi"] = perm("pi", d) if not p.share else f"SELECT seed, pos, row_number() OVER (PARTITION BY seed ORDER BY rank) - 1 AS rank FROM sigma WHERE pos < {d}"
            out["read_at"] = f"SELECT r.seed, r.set_id, r.slot, r.bin, {pos} AS pos FROM reads r JOIN base b ON {on}"
            out["sig"] = f"SELECT t.seed, t.set_id, t.slot, min(pi.rank + t.bin * {d}) AS h FROM read_at t JOIN pi ON pi.seed = t.seed AND pi.pos = t.pos GROUP BY ALL"
    else:
        out["perms"] = slot_perm("inner", M, d)
        rank = f"CASE WHEN r.dist = 0 AND r.slot < {K} THEN b.off ELSE t.rank END" if p.implicit else "t.rank"
        out["sig"] = f"SELECT r.seed, r.set_id, r.slot, min({rank} + r.bin * {d}) AS h FROM reads r JOIN base b ON {on} JOIN perms t ON t.seed = r.seed AND t.slot = r.slot AND t.pos = b.off GROUP BY ALL"
    return out


def firstk(postings: dict[str, str], p: SketchParams) -> dict[str, str]:
    out = _head(postings, p)
    out["sig"] = f"SELECT seed, set_id, slot, q AS h FROM (SELECT *, row_number() OVER (PARTITION BY seed, set_id ORDER BY q) - 1 AS slot FROM q) WHERE slot < {p.K}"
    return out


def quote(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"


def ratio(a: str, b: str, digits: int = 6) -> str:
    """The quotient rounded half up, from integers."""
    scale = 10**digits
    return f"CASE WHEN ({b}) = 0 THEN NULL ELSE CAST((({a}) * {2 * scale} + ({b})) // (({b}) * 2) AS DOUBLE) / {scale}.0 END"


def exact(pairs: str = "pairs") -> dict[str, str]:
    """exact(id1, id2, inter, uni, j) of the CTE pairs(id1, id2) over post."""
    return {
        "sizes": "SELECT set_id, count(*) AS n FROM post GROUP BY 1",
        "common": f"SELECT k.id1, k.id2, count(b.elem) AS inter FROM {pairs} k JOIN post a ON a.set_id = k.id1 LEFT JOIN post b ON b.set_id = k.id2 AND b.elem = a.elem GROUP BY 1, 2",
        "exact": f"SELECT id1, id2, inter, x.n + y.n - inter AS uni, {ratio('inter', 'x.n + y.n - inter')} AS j FROM common JOIN sizes x ON x.set_id = id1 JOIN sizes y ON y.set_id = id2",
    }


def estimates(unfilled: bool = False, slots: int | None = None) -> dict[str, str]:
    """est(seed, id1, id2, hits, m, j_hat) of pairs over sig."""
    m = "count(*) FILTER (WHERE a.h IS NOT NULL OR b.h IS NOT NULL)" if unfilled else "count(*)"
    where = f" WHERE a.slot < {slots}" if slots else ""
    rows = f"SELECT a.seed, k.id1, k.id2, count(*) FILTER (WHERE a.h = b.h) AS hits, {m} AS m FROM pairs k JOIN sig a ON a.set_id = k.id1 JOIN sig b ON b.set_id = k.id2 AND b.seed = a.seed AND b.slot = a.slot{where} GROUP BY 1, 2, 3"
    return {"hit": rows, "est": f"SELECT *, {ratio('hits', 'm')} AS j_hat FROM hit"}
