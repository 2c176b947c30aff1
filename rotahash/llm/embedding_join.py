"""Near-duplicate vectors by a subspace pigeonhole join.

Unit vectors are turned by a fixed rotation (signs and Hadamard butterflies, padded to a power of two), which
spreads a difference over all axes, and cut into ``BLOCKS`` low-dimensional blocks. Two vectors with cosine
of at least t differ by at most 2-2t in squared distance, so in some block by at most its share of that
budget. Each block is range-joined: its space is cut into boxes by a tree of splits, planned on a sample of at
most ``SAMPLE`` vectors, which only routes; a vector is at home in one box and is shown in the boxes of lower
number that its radius reaches. Inside a task a finer tree over the vectors at home, which copies nothing,
leaves the few small leaves a vector has to be tested with. A pair belongs to the first block where it is
within budget and is verified there by its cosine in double precision.

Equal vectors are one before the join. Boxes are cut into tiles of at most ``TILE`` home vectors and
``SHOWN`` shown ones, and tiles meet pairwise, so a box that holds a third of all vectors is spread. A tile
returns per vector its number of links and a local root; pairs are not returned.

The block distances are made of elementwise operations only, so every task finds the same bits, and no
pair at the edge of the budget is lost between two blocks.

Defined results: vectors that are null, zero, empty or hold null or non-finite components link with nothing
and are their own component; vectors of different lengths don't link; rows of equal vec_id are one vector
if equal, else each links for itself under the same id. Rows of a null vec_id return null components.
"""

from __future__ import annotations

import itertools
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rotahash.llm.bytesops import U, lean, mix
from rotahash.llm.durable import durable, partitions
from rotahash.llm.jaccard_join import _groups
from rotahash.operators.components import components

BLOCKS, THRESHOLD = 8, 0.95
SAMPLE, BOXES, HOME = 1 << 15, 1024, 8192
TILE, SHOWN, LEAF = 16384, 32768, 256
PAIRS, BROADCAST = 1 << 16, 1 << 17
KINDS = "key long, home int, block int, id long, weight long, vector binary"


def _padded(size: int) -> int:
    return 1 << max(0, size - 1).bit_length()


def rotate(x: np.ndarray, rounds: int = 2) -> np.ndarray:
    """The rows of x, padded with zeros to a power of two, under a fixed rotation; a row's result doesn't depend on the other rows."""
    size = _padded(x.shape[1])
    signs = [(np.random.default_rng(1000 * size + r).integers(0, 2, size) * 2.0 - 1.0)[:, None] / math.sqrt(size) for r in range(rounds)]
    done = np.empty((len(x), size))
    for lo in range(0, len(x), 256):  # so few that they stay in the cache
        out = np.zeros((size, min(256, len(x) - lo)))
        out[: x.shape[1]] = x[lo : lo + 256].T
        for sign in signs:
            out *= sign
            width = 1
            while width < size:
                view = out.reshape(-1, 2, width, out.shape[1])
                a, b = view[:, 0] + view[:, 1], view[:, 0] - view[:, 1]
                view[:, 0], view[:, 1] = a, b
                width *= 2
        done[lo : lo + 256] = out.T
    return done


#: First byte of a packed vector: the type of its components.
KIND = {4: np.float32, 8: np.float64}


def _units(cells: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Unit vectors as doubles, and rotated."""
    x = np.frombuffer(b"".join(c[1:] for c in cells), KIND[cells[0][0]]).reshape(len(cells), -1).astype(np.float64)
    x = x / np.abs(x).max(1, keepdims=True)
    x = x / np.sqrt((x * x).sum(1, keepdims=True))
    return x, rotate(x)


def _edges(size: int) -> list[tuple[int, int]]:
    """The blocks of a rotated vector."""
    blocks = min(BLOCKS, size)
    at = [round(i * size / blocks) for i in range(blocks + 1)]
    return list(itertools.pairwise(at))


def _share(threshold: float, edges: list) -> float:
    """A block's part of the squared distance, with room for rounding."""
    return (2 - 2 * threshold) / len(edges) * (1 + 1e-9) + 1e-12


class Tree:
    """Boxes that cover a space: nodes are (axis, place, left, right), leaves (-1, 0, number of the leaf, -1)."""

    def __init__(self, points: np.ndarray, most: int, leaves: int, least: float = 0.0):
        """Splits at medians of the widest axis until a leaf has at most ``most`` points, is narrower than ``least``, or there are ``leaves``."""
        self.axis, self.place, self.left, self.right = [-1], [0.0], [0], [-1]
        queue, done = [(0, np.arange(len(points)))], []
        while queue:
            node, own = queue.pop(0)
            if len(own) > most and len(done) + len(queue) + 2 <= leaves:
                p = points[own]
                low, high = np.quantile(p, (0.05, 0.95), axis=0) if least else (p.min(0), p.max(0))
                a = int(np.argmax(high - low))
                cut = float(np.median(p[:, a]))
                below = p[:, a] < cut
                if high[a] - low[a] > least and below.any() and not below.all():
                    self.axis[node], self.place[node] = a, cut
                    for side, part in ((self.left, own[below]), (self.right, own[~below])):
                        side[node] = len(self.axis)
                        queue.append((len(self.axis), part))
                        self.axis.append(-1), self.place.append(0.0), self.left.append(0), self.right.append(-1)
                    continue
            self.left[node] = len(done)
            done.append(own)
        self.members = done
        self.axis, self.place, self.left, self.right = (np.array(v) for v in (self.axis, self.place, self.left, self.right))

    def reached(self, points: np.ndarray, share: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row, leaf, whether it is the point's own) of every leaf whose box is within the squared distance of a point."""
        row, node = np.arange(len(points)), np.zeros(len(points), np.int64)
        gap, home = np.zeros(points.shape), np.ones(len(points), bool)
        rows, leaves, homes = [], [], []
        while len(row):
            axis = self.axis[node]
            end = axis < 0
            rows.append(row[end]), leaves.append(self.left[node[end]]), homes.append(home[end])
            row, node, gap, home, axis = row[~end], node[~end], gap[~end], home[~end], axis[~end]
            if not len(row):
                break
            away = points[row, axis] - self.place[node]  # below 0: the left child is near
            near, far = np.where(away < 0, self.left[node], self.right[node]), np.where(away < 0, self.right[node], self.left[node])
            other = gap.copy()
            at = np.arange(len(row))
            other[at, axis] = np.maximum(other[at, axis], np.abs(away))
            go = (other * other).sum(1) <= share
            row, node = np.concatenate([row, row[go]]), np.concatenate([near, far[go]])
            gap, home = np.concatenate([gap, other[go]]), np.concatenate([home, np.zeros(int(go.sum()), bool)])
        return np.concatenate([np.zeros(0, np.int64), *rows]), np.concatenate([np.zeros(0, np.int64), *leaves]), np.concatenate([np.zeros(0, bool), *homes])


def plan(distinct: DataFrame, threshold: float) -> dict[int, list[Tree]]:
    """By vector length the trees of the blocks, from a sample; a length that the sample lacks has single boxes."""
    n = distinct.count()
    every = max(1, -(-n // SAMPLE))
    rows = distinct.where(F.pmod(F.xxhash64("vector"), F.lit(every)) == 0).select("vector").limit(2 * SAMPLE).collect()  # bounded
    by: dict[int, list[bytes]] = {}
    for r in rows:
        by.setdefault((len(r[0]) - 1) // r[0][0], []).append(bytes(r[0]))
    out = {}
    for size, cells in by.items():
        _, turned = _units(sorted(cells))
        edges = _edges(turned.shape[1])
        radius = math.sqrt(_share(threshold, edges))
        out[size] = [Tree(turned[:, lo:hi], max(1, HOME // every), BOXES, 2 * radius) for lo, hi in edges]
    for tree in itertools.chain(*out.values()):
        tree.members = []  # only the boxes travel
    return out


def _cells(vectors: DataFrame, threshold: float, trees) -> DataFrame:
    """A row per block and box in which a vector is at home or shown."""

    def deal(batches):
        for b in batches:
            raws, ids, weight = b.column("vector").to_pylist(), b.column("id").to_numpy(), b.column("weight").to_numpy()
            sizes = np.array([(len(r) - 1) // r[0] for r in raws])
            for size in np.unique(sizes).tolist():
                take = np.flatnonzero(sizes == size)
                _, turned = _units([raws[i] for i in take])
                edges = _edges(turned.shape[1])
                share = _share(threshold, edges)
                for block, (lo, hi) in enumerate(edges):
                    tree = trees.value[size][block] if size in trees.value else Tree(turned[:0, lo:hi], 1, 1)
                    row, box, home = tree.reached(turned[:, lo:hi], share)
                    own = np.zeros(len(take), np.int64)
                    own[row[home]] = box[home]
                    k = np.flatnonzero(home | (box < own[row]))
                    key = mix(mix(np.full(len(k), size * 64 + block, U)) + box[k].astype(U))
                    for i in range(0, len(k), 8192):
                        j = k[i : i + 8192]
                        r = take[row[j]]
                        yield pa.RecordBatch.from_arrays(
                            [pa.array(key[i : i + 8192].view(np.int64)), pa.array(home[j].astype(np.int32)), pa.array(np.full(len(j), block, np.int32)), pa.array(ids[r]), pa.array(weight[r]), pa.array([raws[x] for x in r], pa.binary())],
                            ["key", "home", "block", "id", "weight", "vector"],
                        )

    return vectors.mapInArrow(lean(deal), KINDS)


def _tiles(rows: DataFrame) -> DataFrame:
    """Rows of each pair of tiles. side: 2 a home tile with itself, 0 and 1 two home tiles, 3 and 4 home and shown."""
    sizes = rows.groupBy("key").agg(F.sum("home").alias("at_home"), F.sum(1 - F.col("home")).alias("shown")).where("at_home > 1 or (at_home > 0 and shown > 0)")
    sizes = sizes.select(F.col("key").alias("_key"), F.ceil(F.col("at_home") / TILE).cast("int").alias("h"), F.ceil(F.col("shown") / SHOWN).cast("int").alias("s"))
    sizes = durable(sizes)
    if sizes.count() <= BROADCAST:  # as many as the plan has boxes, unless there are many lengths
        sizes = F.broadcast(sizes)
    spread = F.xxhash64("id", "key")
    rows = rows.join(sizes, F.col("key") == F.col("_key")).withColumn("own", F.pmod(spread, F.when(F.col("home") == 1, F.col("h")).otherwise(F.col("s"))).cast("int"))
    at_home, by_home = F.sequence(F.lit(0), F.col("h") - 1), F.when(F.col("s") > 0, F.sequence(F.lit(0), F.col("s") - 1)).otherwise(F.array().cast("array<int>"))

    def pair(kind, a, b, side):
        return F.struct(F.lit(kind).alias("kind"), a.alias("a"), b.alias("b"), side.alias("side"))

    own = F.col("own")
    meet = F.when(
        F.col("home") == 1,
        F.concat(
            F.transform(at_home, lambda o: pair(0, F.least(own, o), F.greatest(own, o), F.when(own == o, 2).when(own < o, 0).otherwise(1))),
            F.transform(by_home, lambda o: pair(1, own, o, F.lit(3))),
        ),
    ).otherwise(F.transform(at_home, lambda o: pair(1, o, own, F.lit(4))))
    out = rows.withColumn("p", F.explode(meet))
    return out.select(F.xxhash64("key", "p.kind", "p.a", "p.b").alias("tile"), "p.side", "block", "id", "weight", "vector")


def unite(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Joins the groups of a[i] and b[i]; label has the least index of each group."""
    while True:
        x, y = label[a], label[b]
        apart = np.flatnonzero(x != y)
        if not len(apart):
            return
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label[:] = up


class Tile:
    """The links of one tile."""

    def __init__(self, ids, side, block: int, cells, weight, threshold: float):
        self.x, self.turned = _units(cells)
        self.ids, self.side, self.block, self.weight, self.threshold = ids, side, block, weight, threshold
        self.edges = _edges(self.turned.shape[1])
        self.share = _share(threshold, self.edges)
        self.links, self.label = np.zeros(len(ids), np.int64), np.arange(len(ids))
        self.tests = 0

    def distance(self, a: np.ndarray, b: np.ndarray, k: int) -> np.ndarray:
        """Squared distances of pairs in block k, the same bits in every task."""
        lo, hi = self.edges[k]
        gap = self.turned[a, lo:hi] - self.turned[b, lo:hi]
        return (gap * gap).sum(1)

    def near(self, a: np.ndarray, b: np.ndarray, k: int) -> np.ndarray:
        """Which of all pairs of a and b are within block k's budget."""
        lo, hi = self.edges[k]
        p, q = self.turned[a, lo:hi], self.turned[b, lo:hi]
        out = (p * p).sum(1)[:, None] + (q * q).sum(1)[None, :] - 2 * (p @ q.T)
        edge = np.abs(out - self.share) < 1e-9
        out = out <= self.share
        if edge.any():
            i, j = np.nonzero(edge)
            out[i, j] = self.distance(a[i], b[j], k) <= self.share
        return out

    def dense(self, a: np.ndarray, b: np.ndarray, own: np.ndarray) -> None:
        """Many candidates: own says which pairs of a and b may be tested."""
        own = own & (self.ids[a][:, None] != self.ids[b][None, :]) & self.near(a, b, self.block)
        for k in range(self.block):  # the pair belongs to the first block where it is near
            own &= ~self.near(a, b, k)
        own &= self.x[a] @ self.x[b].T >= self.threshold
        if own.any():
            self.links[a] += own @ self.weight[b]
            self.links[b] += self.weight[a] @ own
            some = own.any(1)
            unite(self.label, a[some], b[own.argmax(1)[some]])
            some = own.any(0)
            unite(self.label, b[some], a[own.argmax(0)[some]])
            i, j = np.nonzero(own & (self.label[a][:, None] != self.label[b][None, :]))
            unite(self.label, a[i], b[j])

    def sparse(self, a: np.ndarray, b: np.ndarray) -> None:
        """Pairs a[i], b[i]."""
        ok = self.ids[a] != self.ids[b]
        a, b = a[ok], b[ok]
        for k in [self.block, *range(self.block)]:
            close = self.distance(a, b, k) <= self.share
            close = close if k == self.block else ~close
            a, b = a[close], b[close]
        hit = np.einsum("ij,ij->i", self.x[a], self.x[b]) >= self.threshold
        a, b = a[hit], b[hit]
        if len(a):
            np.add.at(self.links, a, self.weight[b])
            np.add.at(self.links, b, self.weight[a])
            unite(self.label, a, b)

    def run(self) -> tuple[np.ndarray, np.ndarray]:
        lo, hi = self.edges[self.block]
        points = self.turned[:, lo:hi]
        left, right = np.flatnonzero(np.isin(self.side, (0, 2, 3))), np.flatnonzero(np.isin(self.side, (1, 2, 4)))
        itself = self.side[0] == 2
        if len(left) and len(right):
            tree = Tree(points[left], LEAF, 1 << 30)
            row, leaf, home = tree.reached(points[right], self.share)
            if itself:  # a pair of two leaves is tested in the lower one
                own = np.zeros(len(right), np.int64)
                own[row[home]] = leaf[home]
                keep = home | (leaf < own[row])
                row, leaf = row[keep], leaf[keep]
            order = np.argsort(leaf, kind="stable")
            row, at = row[order], np.searchsorted(leaf[order], np.arange(len(tree.members) + 1))
            squares = (points * points).sum(1)
            one = np.ones(len(points))
            a32 = np.column_stack([-2 * points, one, squares]).astype(np.float32)
            b32 = np.column_stack([points, squares, one]).astype(np.float32)
            slack = np.float32(self.share + 1e-5)  # the test in single precision only proposes
            for n, members in enumerate(tree.members):
                a, others = left[members], right[row[at[n] : at[n + 1]]]
                for i in range(0, len(a), 4 * LEAF):  # many equal points make a large leaf
                    for j in range(0, len(others), 16384):
                        self._test(a[i : i + 4 * LEAF], others[j : j + 16384], a32, b32, slack, itself)
        low = self.ids.copy()
        np.minimum.at(low, self.label, self.ids)
        return self.links, low[self.label]

    def _test(self, a, b, a32, b32, slack, itself) -> None:
        self.tests += len(a) * len(b)
        found = a32[a] @ b32[b].T <= slack
        if itself:  # the leaf with itself: each pair once
            same = np.flatnonzero(np.isin(b, a))
            found[:, same] &= a[:, None] < b[same][None, :]
        k = np.count_nonzero(found)
        if not k:
            return
        if k > 0.02 * found.size and k > 4096:
            for j in range(0, len(b), 4096):
                self.dense(a, b[j : j + 4096], found[:, j : j + 4096])
            return
        flat = np.flatnonzero(found)
        for i in range(0, len(flat), PAIRS):
            self.sparse(a[flat[i : i + PAIRS] // len(b)], b[flat[i : i + PAIRS] % len(b)])


def _links(tiles: DataFrame, threshold: float) -> DataFrame:
    """(id, links, root): in each tile, the weight of the vectors linked to each, and the least id reached there."""

    def link(batches):
        for t in _groups(batches):
            tile, side, block, ids, weight = (t.column(c).to_numpy() for c in ("tile", "side", "block", "id", "weight"))
            cells = t.column("vector").to_pylist()
            links, root = np.zeros(len(ids), np.int64), np.array(ids)
            start = np.flatnonzero(np.concatenate([[True], tile[1:] != tile[:-1]]))
            for lo, hi in zip(start.tolist(), [*start[1:].tolist(), len(tile)], strict=True):
                if hi - lo > 1:
                    links[lo:hi], root[lo:hi] = Tile(ids[lo:hi], side[lo:hi], int(block[lo]), cells[lo:hi], weight[lo:hi], threshold).run()
            has = pa.array(links > 0)
            yield pa.RecordBatch.from_arrays([pa.array(ids).filter(has), pa.array(links).filter(has), pa.array(root).filter(has)], ["id", "links", "root"])

    spark = tiles.sparkSession
    return tiles.repartition(partitions(spark), "tile").sortWithinPartitions("tile").mapInArrow(lean(link), "id long, links long, root long")


def embedding_join(table: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """One row per vector: vec_id, n_links, component_id, kept."""
    spark = table.sparkSession
    single = dict(table.dtypes)["embedding"] == "array<float>"
    rows = table.select("vec_id", F.col("embedding").cast("array<float>" if single else "array<double>").alias("v"))
    largest = F.array_max(F.transform("v", lambda x: F.abs(x)))
    good = F.col("v").isNotNull() & (F.size("v") > 0) & F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & (largest > 0)
    rows = rows.withColumn("v", F.when(F.coalesce(good, F.lit(False)) & F.col("vec_id").isNotNull(), F.col("v")))

    def packed(batches):
        for b in batches:
            kind = KIND[4 if single else 8]
            cells = [bytes([kind().itemsize]) + x.values.to_numpy().astype(kind).tobytes() if x.is_valid else None for x in b.column("v")]
            yield pa.RecordBatch.from_arrays([b.column("vec_id"), pa.array(cells, pa.binary())], ["vec_id", "vector"])

    rows = durable(rows.mapInArrow(lean(packed), "vec_id long, vector binary"))
    distinct = durable(rows.where("vector is not null").distinct().groupBy("vector").agg(F.min("vec_id").alias("id"), F.count("*").alias("weight")))
    trees = spark.sparkContext.broadcast(plan(distinct, threshold))
    found = durable(_links(_tiles(_cells(distinct, threshold, trees)), threshold))
    group = components(found.select(F.col("id").alias("a"), F.col("root").alias("b")))
    linked = found.groupBy("id").agg(F.sum("links").alias("links")).join(group, "id", "left")
    known = distinct.select("id", "weight", F.xxhash64("vector").alias("_h"), F.col("vector").alias("_v")).join(linked.select(F.col("id").alias("_id"), "links", "component"), F.col("id") == F.col("_id"), "left")
    out = rows.withColumn("h", F.xxhash64("vector")).join(known, (F.col("h") == F.col("_h")) & (F.col("vector") == F.col("_v")), "left")
    component = F.coalesce("component", "id", "vec_id")
    return out.select("vec_id", (F.coalesce(F.col("weight") - 1, F.lit(0)) + F.coalesce("links", F.lit(0))).alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(False)).alias("kept"))
