"""N-gram Jaccard self-join by chosen paths.

A document is the set of its hashed five-word shingles. In each of at least ``RUNS`` independent runs a set is
sent down a path of sampled shared tokens: the token at a node is the set's least shingle under the
node's hash function, so two sets take the same branch with probability equal to their Jaccard
similarity. Paths begin with ``FIRST`` tokens. A bucket of at most ``BUCKET`` sets is compared by brute
force; a larger one is split on the next sampled token, at most ``LAST`` in all, after which it is
compared in tiles of at most about ``TILE`` sets and ``LOAD`` shingles, so no group is ever held whole by one task. A pair of similarity s meets in a run with
probability s^depth; ``runs_for`` gives the runs that find a pair at the threshold with probability ``TARGET``. The
sets of buckets that are split walk as many further runs as the depth ``LAST`` needs, so large groups lose no
more than small ones. What meets is verified exactly on whole sets, so no pair below the threshold is linked.

Equal sets form one class before anything else; only class representatives travel. Each pair is
verified once, in the first run where it meets. A tile returns per document its number of links and a
local root, never the pairs themselves, and the roots' components are the groups.

Defined results: null, empty and wordless texts have no set: they are alone in their group with 0 links.
A text of 1-4 words is the set of that one shorter shingle. Rows of equal doc_id count as one document
and share a group. A null doc_id gives a null group and 0 links.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rotahash.llm.bytesops import U, binary_rows, distinct_sorted, lean, mix, shingles, slices, word_hashes
from rotahash.operators.components import components
from rotahash.llm.durable import durable, free_name, partitions

K, THRESHOLD = 5, 0.8
RUNS, FIRST, LAST = 16, 3, 6
BUCKET, TILE, LOAD = 64, 1024, 1 << 20
TARGET = 0.9999


def recall(similarity: float, depth: int = LAST, runs: int = RUNS) -> float:
    """Probability that a pair meets in some run."""
    return 1 - (1 - similarity**depth) ** runs


def runs_for(similarity: float, depth: int, target: float = TARGET) -> int:
    """Least number of runs in which a pair meets with probability ``target``."""
    meets = similarity**depth
    return 1 if meets >= target else math.ceil(math.log1p(-target) / math.log1p(-meets))


def sets_of(column, lo_hi=False):
    """Slices of a text column as (lo, hi, sorted distinct shingles, offsets)."""
    for lo, hi, data, at in slices(column, lower=True):
        yield lo, hi, *distinct_sorted(*shingles(*word_hashes(data, at), K))


def sketches(docs: DataFrame, begin: int = 0, end: int = RUNS) -> DataFrame:
    """doc_id, number of shingles, two hashes that identify the set, and the tokens of its paths in the runs from begin up to end."""
    runs = end - begin
    factors = mix(np.arange(begin * LAST + 1, end * LAST + 1, dtype=U)) | U(1)

    def sketch(batches):
        for b in batches:
            out = [[], [], [], [], []]
            for lo, hi, values, at in sets_of(b.column("text")):
                n = np.diff(at)
                full = np.flatnonzero(n)
                tokens = np.zeros((hi - lo, runs * LAST), U)
                ident = np.zeros((2, hi - lo), U)
                if len(full):
                    first = at[:-1][full]
                    for j, f in enumerate(factors):
                        tokens[full, j] = np.minimum.reduceat(values * f, first)
                    ident[0, full] = np.add.reduceat(mix(values), first)
                    ident[1, full] = np.add.reduceat(mix(values ^ U(0x5851F42D4C957F2D)), first)
                tokens = mix(tokens).reshape(hi - lo, runs, LAST)
                key = np.zeros((hi - lo, runs), U)
                for d in range(FIRST):
                    key = mix(key * U(0x9E3779B97F4A7C15) + tokens[:, :, d])
                out[0].append(n)
                out[1].append(ident[0].view(np.int64))
                out[2].append(ident[1].view(np.int64))
                out[3].append(key.view(np.int64).ravel())
                out[4].append((tokens[:, :, FIRST:] >> U(32)).astype(np.uint32).view(np.int32).ravel())
            cells = [np.concatenate(x) if x else np.zeros(0, np.int64) for x in out]
            lists = [pa.ListArray.from_arrays(pa.array(np.arange(0, len(c) + 1, w, dtype=np.int32)), pa.array(c, t)) for c, w, t in ((cells[3], runs, pa.int64()), (cells[4], runs * (LAST - FIRST), pa.int32()))]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *(pa.array(c) for c in cells[:3]), *lists], ["doc_id", "n", "set_a", "set_b", "keys", "more"])

    return docs.select("doc_id", "text").mapInArrow(lean(sketch), "doc_id long, n long, set_a long, set_b long, keys array<long>, more array<int>")


def _walks(reps: DataFrame, begin: int = 0) -> DataFrame:
    """(id, n, run, bucket, more): the path of each set in each run, numbered from begin."""
    steps = LAST - FIRST
    rows = reps.select("id", "n", F.posexplode("keys").alias("run", "bucket"), "more")
    return rows.select("id", "n", (F.col("run") + begin).alias("run"), "bucket", F.slice("more", F.col("run") * steps + 1, F.lit(steps)).alias("more"))


def _shared(now: DataFrame) -> DataFrame:
    """The rows whose bucket has at least two sets, with its size and the number of its sets' shingles."""
    return now.join(now.groupBy("run", "bucket").agg(F.count("*").alias("size"), F.sum("n").alias("load")).where("size > 1"), ["run", "bucket"])


def _buckets(reps: DataFrame, further) -> DataFrame:
    """(id, run, bucket, size, load): the bucket of at least two sets in which each set's path ends, run by run.

    further: of a DataFrame of ids, their walks in the further runs; it is asked for the sets of buckets that are split.
    """
    steps = LAST - FIRST
    now, done = _walks(reps), None
    for level in range(steps + 1):
        joined = _shared(now)
        if level < steps:
            joined = durable(joined)
        small = joined if level == steps else joined.where(F.col("size") <= BUCKET)
        small = small.select("id", "run", "bucket", "size", "load")
        done = small if done is None else done.unionByName(small)
        if level == steps:
            break
        large = joined.where(F.col("size") > BUCKET)
        if not large.limit(1).count():
            break
        if level == 0:
            more = durable(_shared(further(large.select("id").distinct())))
            done = done.unionByName(more.where(F.col("size") <= BUCKET).select("id", "run", "bucket", "size", "load"))
            large = large.unionByName(more.where(F.col("size") > BUCKET))
        now = large.select("id", "n", "run", F.xxhash64("bucket", F.element_at("more", level + 1)).alias("bucket"), "more")
    return done


def _tiled(met: DataFrame) -> DataFrame:
    """Rows (tile, side, run, id, weight, paths): a bucket that is too large for one tile becomes pairs of tiles. side 2: the pair of a tile with itself."""
    width = F.greatest(F.ceil(F.col("size") / F.lit(TILE)), F.least(F.ceil(F.col("load") / F.lit(LOAD)), F.col("size"))).cast("int")
    own = F.pmod(F.xxhash64("id", "bucket"), width).cast("int")
    rows = met.withColumn("_own", own).withColumn("_width", width).withColumn("_other", F.explode(F.sequence(F.lit(0), F.col("_width") - 1)))
    a, b = F.least("_own", "_other"), F.greatest("_own", "_other")
    return rows.select(F.xxhash64("run", "bucket", a, b).alias("tile"), F.when(F.col("_own") == F.col("_other"), 2).otherwise((F.col("_own") > F.col("_other")).cast("int")).alias("side"), "run", "id", "weight", "paths")


def _groups(batches):
    """Whole tiles of a stream sorted by tile, some at a time: (tables of numpy columns)."""
    rest = None
    for b in batches:
        t = pa.Table.from_batches([b]) if rest is None else pa.concat_tables([rest, pa.Table.from_batches([b])])
        key = t.column("tile").to_numpy()
        cut = int(np.searchsorted(key, key[-1])) if len(key) else 0
        if cut:
            yield t.slice(0, cut).combine_chunks()
        rest = t.slice(cut)
    if rest is not None and rest.num_rows:
        yield rest.combine_chunks()


def _paths(column) -> np.ndarray:
    """Matrix of the runs' buckets; 0: none."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    at, flat = column.offsets.to_numpy(), column.flatten()
    run = flat.field(0).to_numpy()
    out = np.zeros((len(column), int(run.max(initial=0)) + 1), np.int64)
    row = np.repeat(np.arange(len(column)), np.diff(at))
    out[row, run] = flat.field(1).to_numpy()
    return out


def _pairs(tile: np.ndarray, side: np.ndarray):
    """Index pairs of rows of one tile: all pairs of side 2, and those of sides 0 and 1."""
    at = np.arange(len(tile))
    d = 1
    while len(at):
        at = at[at + d < len(tile)]
        at = at[tile[at] == tile[at + d]]
        if not len(at):
            return
        use = at[(side[at] == 2) | (side[at] != side[at + d])]
        if len(use):
            yield use, use + d
        d += 1


def _first_meeting(paths: np.ndarray, run: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    same = (paths[i] == paths[j]) & (paths[i] != 0)
    return same.argmax(1) == run[i]


def _asked(paths: np.ndarray, side: np.ndarray, run: int, ids: np.ndarray) -> np.ndarray:
    """Which pairs of a tile meet there for the first time, as a matrix."""
    ask = (side[:, None] == 2) | (side[:, None] != side[None, :])
    ask &= ids[:, None] != ids[None, :]
    for r in range(run + 1):
        p = paths[:, r]
        same = (p[:, None] == p[None, :]) & (p != 0)[:, None]
        ask &= same if r == run else ~same
    return ask


def _needed(tiles: DataFrame) -> DataFrame:
    """(tile, side, run, id, weight, paths) of the rows that have a pair meeting for the first time."""

    def find(batches):
        for t in _groups(batches):
            tile, side, run = (t.column(c).to_numpy() for c in ("tile", "side", "run"))
            paths, need = _paths(t.column("paths")), np.zeros(t.num_rows, bool)
            for i, j in _pairs(tile, side):
                new = _first_meeting(paths, run, i, j)
                need[i[new]] = need[j[new]] = True
            yield from t.filter(pa.array(need)).to_batches()

    spark = tiles.sparkSession
    return tiles.repartition(partitions(spark), "tile").sortWithinPartitions("tile").mapInArrow(lean(find), tiles.schema)


def _verify(values: list[np.ndarray], threshold: float, ask: np.ndarray) -> np.ndarray:
    """Matrix of the asked pairs whose exact similarity reaches the threshold."""
    m, n = len(values), np.array([len(v) for v in values])
    if m == 2:
        common = np.array([[0, len(np.intersect1d(values[0], values[1], assume_unique=True))]] * 2).reshape(2, 2)
        common[1, 0], common[1, 1], common[0, 0] = common[0, 1], n[1], n[0]
    else:
        ids, col = np.unique(np.concatenate(values), return_inverse=True)
        row = np.repeat(np.arange(m), n)
        hits = np.bincount(col)
        keep = hits[col] > 1
        order = np.argsort(col[keep], kind="stable")
        row, col = row[keep][order], col[keep][order]
        common = np.zeros((m, m), np.float32)
        for lo in range(0, len(ids), 4096):
            a, b = np.searchsorted(col, [lo, lo + 4096])
            if b > a:
                block = np.zeros((m, 4096), np.float32)
                block[row[a:b], col[a:b] - lo] = 1
                common += block @ block.T
    union = n[:, None] + n[None, :] - common
    return ask & (common >= threshold * union - 1e-6)


def _links(rows: DataFrame, threshold: float) -> DataFrame:
    """(id, links, root): in each tile, the weight of the sets linked to each set, and the least id it reaches there."""

    def link(batches):
        for t in _groups(batches):
            tile, side, run, ids, weight = (t.column(c).to_numpy() for c in ("tile", "side", "run", "id", "weight"))
            paths, cells = _paths(t.column("paths")), t.column("shingles")
            cells = cells.combine_chunks() if isinstance(cells, pa.ChunkedArray) else cells
            links, root = np.zeros(t.num_rows, np.int64), np.array(ids)
            start = np.flatnonzero(np.concatenate([[True], tile[1:] != tile[:-1]]))
            for lo, hi in zip(start.tolist(), [*start[1:].tolist(), len(tile)], strict=True):
                m = hi - lo
                if m < 2:
                    continue
                ask = _asked(paths[lo:hi], side[lo:hi], int(run[lo]), ids[lo:hi])
                got = _verify([np.frombuffer(cells[k].as_py(), U) for k in range(lo, hi)], threshold, ask)
                links[lo:hi] = got @ weight[lo:hi]
                own = root[lo:hi]
                while True:
                    low = np.minimum(own, np.where(got, own[None, :], np.iinfo(np.int64).max).min(1))
                    if (low == own).all():
                        break
                    own = low
                root[lo:hi] = own
            has = pa.array(links > 0)
            yield pa.RecordBatch.from_arrays([pa.array(ids).filter(has), pa.array(links).filter(has), pa.array(root).filter(has)], ["id", "links", "root"])

    spark = rows.sparkSession
    return rows.repartition(partitions(spark), "tile").sortWithinPartitions("tile").mapInArrow(lean(link), "id long, links long, root long")


def _shingle_rows(docs: DataFrame) -> DataFrame:
    def cut(batches):
        for b in batches:
            for lo, hi, values, at in sets_of(b.column("text")):
                yield pa.RecordBatch.from_arrays([b.column("id").slice(lo, hi - lo), binary_rows(values, at)], ["id", "shingles"])

    return docs.mapInArrow(lean(cut), "id long, shingles binary")


def jaccard_join(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """One row per document: doc_id, class_id (least doc_id of its group), copy_id (least doc_id with the same set), n_links (other documents linked directly, copies included), n_shingles."""
    spark = docs.sparkSession
    runs = max(RUNS, runs_for(threshold, FIRST))
    table = durable(sketches(docs, 0, runs))
    classes = table.where("n > 0 and doc_id is not null").groupBy("set_a", "set_b").agg(F.min("doc_id").alias("id"), F.count("*").alias("weight"), F.any_value("keys").alias("keys"), F.any_value("more").alias("more"), F.any_value("n").alias("n"))
    classes = durable(classes)

    def further(ids):
        own = docs.select("doc_id", "text").join(ids.select(F.col("id").alias("doc_id")), "doc_id", "left_semi")
        sets = sketches(own, runs, max(runs, runs_for(threshold, LAST))).where("n > 0").dropDuplicates(["doc_id", "set_a", "set_b"])
        return _walks(sets.withColumnRenamed("doc_id", "id"), runs)

    done = durable(_buckets(classes.select("id", "n", "keys", "more"), further))
    met = done.groupBy("id").agg(F.collect_list(F.struct("run", "bucket", "size", "load")).alias("m"))  # at most one entry a run
    met = met.join(classes.select("id", "weight"), "id")
    met = met.select("id", "weight", F.explode("m").alias("x"), F.transform("m", lambda s: F.struct(s.run.alias("run"), s.bucket.alias("bucket"))).alias("paths")).select("id", "weight", "x.*", "paths")
    need = durable(_needed(_tiled(met)))
    ids = need.select("id").distinct()
    texts = docs.where("doc_id is not null").select(F.col("doc_id").alias("id"), "text").join(ids, "id", "left_semi")
    rows = need.join(_shingle_rows(texts), "id")
    found = durable(_links(rows, threshold))
    group = components(found.select(F.col("id").alias("a"), F.col("root").alias("b")))
    links = found.groupBy("id").agg(F.sum("links").alias("links"))
    linked = links.join(group, "id", "left").select(F.col("id").alias("_id"), "links", "component")
    known = classes.select(F.col("set_a").alias("_a"), F.col("set_b").alias("_b"), "id", "weight").join(linked, F.col("id") == F.col("_id"), "left")
    out = table.select("doc_id", "n", "set_a", "set_b").join(known, (F.col("set_a") == F.col("_a")) & (F.col("set_b") == F.col("_b")) & (F.col("n") > 0) & F.col("doc_id").isNotNull(), "left")
    return out.select("doc_id", F.coalesce("component", "id", "doc_id").alias("class_id"), F.coalesce("id", "doc_id").alias("copy_id"), (F.coalesce(F.col("weight") - 1, F.lit(0)) + F.coalesce("links", F.lit(0))).alias("n_links"), F.col("n").alias("n_shingles"))


def keep_one(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of docs, all columns as they were, one for each group: that of the least doc_id.

    Rows of equal doc_id count as one document; one of them stays, the first by text and then by the other
    columns. Rows of null doc_id stay.
    """
    found = durable(jaccard_join(docs, threshold).select("doc_id", "class_id"))
    name = free_name(docs, "gone")
    gone = found.where("doc_id <> class_id").select(F.col("doc_id").alias(name)).distinct()
    kept = docs.join(gone, docs["doc_id"] == gone[name], "left_anti")
    again = found.where("doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").select(F.col("doc_id").alias(name))
    if not again.limit(1).count():
        return kept
    again = durable(again)
    row = free_name(docs, "row")
    orderable = [c for c, t in docs.dtypes if c != "doc_id" and not t.startswith("map")]
    order = Window.partitionBy("doc_id").orderBy(*orderable)
    repeated = kept.join(again, docs["doc_id"] == again[name], "left_semi").withColumn(row, F.row_number().over(order)).where(F.col(row) == 1).drop(row)
    return kept.join(again, docs["doc_id"] == again[name], "left_anti").unionByName(repeated)
