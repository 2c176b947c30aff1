"""Queries of the relational operators around the sketches, with their SQL twins."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rotahash.functions import hashes, sqlfns
from rotahash.operators import estimates as E
from rotahash.operators import sketches as S
from rotahash.operators.overlaps import overlaps
from rotahash.params import SketchParams
from rotahash.plans import oracle as O
from rotahash.plans.sketch_queries import ALL, BASKETS, PAIRS, W, baskets, frequent_sql, frequent_words, pairs_of, part_universe, suppliers, universe
from rotahash.plans.storage import new_folder, settled
from rotahash.sources import tables as T
from rotahash.streaming import bins

QUERIES: dict = {}
SQL: dict[str, str] = {}
TOKENS = "unnest(regexp_split_to_array(lower(text), '[^a-z0-9]+'))"


def add(name: str, of, sql: str | None = None) -> None:
    QUERIES[name] = of
    if sql:
        SQL[name] = sql


def table(name: str):
    return lambda spark, d: T.load_table(spark, d, name)


docs, lineitem, events, orders = table("documents"), table("lineitem"), table("events"), table("orders")

# ---- scans, sources and sinks ----
add("scan_documents_pruned", lambda s, d: docs(s, d).where("lang = 'en'").select("doc_id", "n_chars"), "SELECT doc_id, n_chars FROM documents WHERE lang = 'en'")


def bucketed(spark: SparkSession, d: str) -> DataFrame:
    """Signatures written once by bucket of their set and read back: later joins on the set move no rows."""
    name = f"rotahash_sig_{uuid.uuid4().hex}"
    S.sketch(suppliers(spark, d), SketchParams(part_universe(spark, d), 64, split="2u")).write.bucketBy(8, "set_id").sortBy("slot").saveAsTable(name)
    out = settled(spark.table(name).groupBy("set_id").agg(F.count("*").alias("slots"), F.min("h").alias("least")))
    spark.sql(f"DROP TABLE {name}")
    return out


add("write_bucketed_signatures", bucketed, O.ctes(O.binned({"post": "SELECT DISTINCT l_suppkey AS set_id, l_partkey AS elem FROM lineitem"}, SketchParams(1 << 15, 64, split="2u")), "SELECT set_id, count(*) AS slots, min(h) AS least FROM sig GROUP BY 1"))


def roundtrip(spark: SparkSession, d: str) -> DataFrame:
    """Benchmark words through CSV, JSON and ORC files; each gives the same postings."""
    root = new_folder(spark, "io")
    rows = T.load_table(spark, d, "benchmark").select("item_id", F.explode(T.tokens(F.col("text"))).alias("word"))
    out = None
    for kind in ("csv", "json", "orc", "parquet"):
        rows.write.format(kind).option("header", True).save(f"{root}/{kind}")
        one = T.read_sets(spark, f"{root}/{kind}", kind, "item_id", "word", "item_id long, word string").groupBy("set_id").agg(F.count("*").alias("words")).withColumn("format", F.lit(kind))
        out = one if out is None else out.unionByName(one)
    return out


add("csv_json_roundtrip", roundtrip, f"SELECT item_id AS set_id, count(DISTINCT w) AS words, format FROM (SELECT item_id, {TOKENS} AS w FROM benchmark), (SELECT unnest(['csv', 'json', 'orc', 'parquet']) AS format) WHERE w <> '' GROUP BY ALL")

# ---- projections, generators, filters ----
add("filter_df_range", lambda s, d: T.word_postings(docs(s, d)).groupBy("set_id").agg(F.count("*").alias("df")).where(F.col("df").between(20, 200)), O.ctes({"words": O.WORDS}, "SELECT set_id, count(*) AS df FROM words GROUP BY 1 HAVING count(*) BETWEEN 20 AND 200"))
add(
    "project_tokens",
    lambda s, d: docs(s, d).select("doc_id", F.posexplode(T.tokens(F.col("text"))).alias("pos", "word")),
    "SELECT doc_id, i AS pos, w[i + 1] AS word FROM (SELECT doc_id, w, unnest(range(len(w))) AS i FROM (SELECT doc_id, list_filter(regexp_split_to_array(lower(text), '[^a-z0-9]+'), lambda x: x <> '') AS w FROM documents))",
)
add("json_keys", lambda s, d: events(s, d).select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
add("hour_buckets", lambda s, d: events(s, d).groupBy(F.hour("ts").alias("hour"), F.date_trunc("day", "ts").cast("date").alias("day")).agg(F.count("*").alias("n")), "SELECT hour(ts) AS hour, CAST(date_trunc('day', ts) AS DATE) AS day, count(*) AS n FROM events GROUP BY ALL")


def dictionary(spark: SparkSession, d: str) -> DataFrame:
    """Ids 0.. of the words in their order: ranks inside ranges of first letters plus the sizes of the ranges before, so no task sorts all."""
    words = T.word_postings(docs(spark, d)).select("set_id").distinct().withColumn("r", F.substring("set_id", 1, 2))
    before = words.groupBy("r").agg(F.count("*").alias("n")).withColumn("base", F.sum("n").over(Window.orderBy("r")) - F.col("n"))
    own = F.dense_rank().over(Window.partitionBy("r").orderBy("set_id")) - 1
    return words.join(F.broadcast(before.select("r", "base")), "r").select(F.col("set_id").alias("token"), (F.col("base") + own).cast("long").alias("elem"))


add("dictionary_ids", dictionary, O.ctes({"words": O.WORDS}, "SELECT set_id AS token, CAST(dense_rank() OVER (ORDER BY set_id) - 1 AS BIGINT) AS elem FROM (SELECT DISTINCT set_id FROM words)"))
add(
    "string_hashes",
    lambda s, d: T.load_table(s, d, "benchmark").select("item_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("s"), F.conv(F.substring(F.md5("text"), 1, 8), 16, 10).cast("long").alias("n")),
    "SELECT item_id, md5(text) AS m, sha256(text) AS s, CAST(concat('0x', substr(md5(text), 1, 8)) AS BIGINT) AS n FROM benchmark",
)
add(
    "math_mod_bits",
    lambda s, d: events(s, d).select(F.col("event_id").alias("id")).select(F.col("id").alias("x"), F.pmod(F.col("id") * 7 - 3000, F.lit(97)).alias("m"), F.shiftright(F.col("id") * 12345, 5).alias("r"), F.col("id").bitwiseXOR(F.lit(345)).alias("e"), F.bit_count("id").cast("int").alias("b")),
    "SELECT x, ((x * 7 - 3000) % 97 + 97) % 97 AS m, (x * 12345) >> 5 AS r, xor(x, 345) AS e, CAST(bit_count(x) AS INTEGER) AS b FROM (SELECT event_id AS x FROM events)",
)
add(
    "decimal_and_cast",
    lambda s, d: orders(s, d).select(F.col("o_orderkey").alias("id")).select(F.col("id").alias("x"), hashes.mulmod(F.lit((1 << 40) - 87), F.col("id") + (1 << 39), 1099511627791).alias("q"), F.pmod((F.lit((1 << 40) - 87).cast("decimal(20,0)") * (F.col("id") + (1 << 39)).cast("decimal(18,0)")), F.lit(1099511627791).cast("decimal(20,0)")).cast("long").alias("wide")),
    f"SELECT x, CAST(({(1 << 40) - 87}::HUGEINT * (x + {1 << 39})) % 1099511627791 AS BIGINT) AS q, CAST(({(1 << 40) - 87}::HUGEINT * (x + {1 << 39})) % 1099511627791 AS BIGINT) AS wide FROM (SELECT o_orderkey AS x FROM orders)",
)

# ---- joins ----
add(
    "broadcast_dim_join",
    lambda s, d: T.load_table(s, d, "supplier").join(F.broadcast(T.load_table(s, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(T.load_table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n")),
    "SELECT r_name, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1",
)
add(
    "smj_customer_parts",
    lambda s, d: orders(s, d).select("o_orderkey", "o_custkey").hint("merge").join(lineitem(s, d).select("l_orderkey", "l_partkey"), F.col("o_orderkey") == F.col("l_orderkey")).select(F.col("o_custkey").alias("set_id"), F.col("l_partkey").alias("elem")).distinct(),
    "SELECT DISTINCT o_custkey AS set_id, l_partkey AS elem FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
)
add("shuffle_hash_pairs", lambda s, d: (lambda p: p.select("elem", F.col("set_id").alias("a")).hint("shuffle_hash").join(p.select("elem", F.col("set_id").alias("b")), "elem").where("a < b").groupBy("a", "b").agg(F.count("*").alias("inter")))(frequent_words(60)(s, d)), O.ctes(frequent_sql(60), "SELECT a.set_id AS a, b.set_id AS b, count(*) AS inter FROM post a JOIN post b ON a.elem = b.elem AND a.set_id < b.set_id GROUP BY 1, 2"))


def size_filter(spark: SparkSession, d: str) -> DataFrame:
    n = suppliers(spark, d).groupBy("set_id").agg(F.count("*").alias("n"))
    a, b = n.select(F.col("set_id").alias("id1"), F.col("n").alias("n1")), n.select(F.col("set_id").alias("id2"), F.col("n").alias("n2"))
    return a.join(F.broadcast(b), (F.col("id1") < F.col("id2")) & (F.col("n1") * 100 >= F.col("n2") * 99) & (F.col("n2") * 100 >= F.col("n1") * 99))


add("size_filter_pairs", size_filter, "WITH n AS (SELECT l_suppkey AS id, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY 1) SELECT a.id AS id1, a.n AS n1, b.id AS id2, b.n AS n2 FROM n a JOIN n b ON a.id < b.id AND a.n * 100 >= b.n * 99 AND b.n * 100 >= a.n * 99")
P16 = SketchParams(1 << 15, 16, fill="none")


def grid(spark: SparkSession, d: str) -> DataFrame:
    """Every slot of every basket with its bin's minimum, or null."""
    base = S.binned(baskets(spark, d), P16.with_(D=part_universe(spark, d)))
    minima = base.groupBy("set_id", F.col("bin").cast("int").alias("slot")).agg(F.min("q").alias("h"))
    slots = spark.range(16).select(F.col("id").cast("int").alias("slot"))
    return base.select("set_id").distinct().crossJoin(F.broadcast(slots)).join(minima, ["set_id", "slot"], "left")


add("slot_grid_left_outer", grid, O.ctes(O.binned(BASKETS, P16), "SELECT set_id, CAST(slot AS INTEGER) AS slot, h FROM sig"))


def empty_slots(spark: SparkSession, d: str) -> DataFrame:
    base = S.binned(baskets(spark, d), P16.with_(D=part_universe(spark, d)))
    full = base.select("set_id", F.col("bin").cast("int").alias("slot")).distinct()
    slots = spark.range(16).select(F.col("id").cast("int").alias("slot"))
    return base.select("set_id").distinct().crossJoin(F.broadcast(slots)).join(full, ["set_id", "slot"], "left_anti")


add("empty_slots_anti", empty_slots, O.ctes(O.binned(BASKETS, P16), "SELECT set_id, CAST(slot AS INTEGER) AS slot FROM sig WHERE h IS NULL"))
add("postings_of_candidates_semi", lambda s, d: T.word_postings(docs(s, d)).join(docs(s, d).where("lang = 'de'").select(F.col("doc_id").alias("elem")), "elem", "left_semi").groupBy("elem").agg(F.count("*").alias("n")), O.ctes({"words": O.WORDS}, "SELECT elem, count(*) AS n FROM words WHERE elem IN (SELECT doc_id FROM documents WHERE lang = 'de') GROUP BY 1"))


def nearest_before(spark: SparkSession, d: str) -> DataFrame:
    """For each purchase the last view of the same user before it: one sort per user instead of a range join."""
    kinds = events(spark, d).select("user_id", "event_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = kinds.withColumn("before", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w))
    return seen.where("event_type = 'purchase'").select("event_id", "user_id", "before")


add("nearest_event_before", nearest_before, "SELECT event_id, user_id, before FROM (SELECT *, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before FROM events) WHERE event_type = 'purchase'")


def in_window(spark: SparkSession, d: str) -> DataFrame:
    """Events of each user in the hour before each of the user's purchases: an equi-join on the user and the hour cell, then the exact range."""
    e = events(spark, d).select("user_id", "event_id", "ts")
    cell = F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600)
    buys = events(spark, d).where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("buy_id"), F.col("ts").alias("t"))
    buys = buys.withColumn("_c", F.floor(F.unix_timestamp(F.col("t").cast("timestamp")) / 3600)).withColumn("cell", F.explode(F.array(F.col("_c") - 1, F.col("_c"))))
    joined = buys.join(e.withColumn("cell", cell), ["user_id", "cell"]).where("ts >= t - interval 1 hour and ts < t")
    return joined.groupBy("buy_id").agg(F.count("*").alias("n"))


add("events_in_window", in_window, "SELECT b.event_id AS buy_id, count(*) AS n FROM events b JOIN events e ON e.user_id = b.user_id AND e.ts >= b.ts - INTERVAL 1 HOUR AND e.ts < b.ts WHERE b.event_type = 'purchase' GROUP BY 1")
add("lateral_probe", lambda s, d: T.load_table(s, d, "customer").select(F.col("c_custkey").cast("int").alias("slot")).withColumn("attempt", F.explode(F.sequence(F.lit(0), F.lit(7)))).withColumn("bin", F.conv(F.substring(hashes.md5_key(42, "probe", F.col("slot"), F.col("attempt")), 1, 8), 16, 10).cast("long") % 16), "SELECT CAST(slot AS INTEGER) AS slot, CAST(attempt AS INTEGER) AS attempt, CAST(concat('0x', substr(md5(concat('42:probe:', slot, ':', attempt)), 1, 8)) AS BIGINT) % 16 AS bin FROM (SELECT c_custkey AS slot FROM customer), (SELECT unnest(range(8)) AS attempt)")

# ---- aggregates ----
add("distinct_elements", lambda s, d: lineitem(s, d).groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("n")), "SELECT l_suppkey, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY 1")
add("approx_set_sizes", lambda s, d: lineitem(s, d).groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey").alias("hll"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("sketch"), F.theta_sketch_estimate(F.theta_sketch_agg("l_partkey")).alias("theta"), F.count_distinct("l_partkey").alias("n")))
add(
    "occupied_bitmap",
    lambda s, d: S.binned(suppliers(s, d), SketchParams(part_universe(s, d), 64)).groupBy("set_id").agg(F.bit_count(F.bit_or(F.expr("shiftleft(1L, cast(bin as int))"))).cast("int").alias("occupied")),
    O.ctes(O.binned({"post": "SELECT DISTINCT l_suppkey AS set_id, l_partkey AS elem FROM lineitem"}, SketchParams(1 << 15, 64)), "SELECT set_id, CAST(count(DISTINCT bin) AS INTEGER) AS occupied FROM base GROUP BY 1"),
)
ERR = [("rotbin", S.sketch, W.with_(seeds=(1, 2))), ("copy", S.sketch, W.with_(seeds=(1, 2), fill="copy"))]


def squared(spark: SparkSession, d: str) -> DataFrame:
    """Squared errors times 64^2*uni^2 as integers: (method, seed, id1, id2, decile, e)."""
    post = settled(frequent_words(16)(spark, d))
    truth = E.exact_jaccard(post, pairs_of(post))
    out = None
    for label, make, p in ERR:
        est = E.estimate_pairs(make(post, p.with_(D=universe(spark, d))), pairs_of(post)).join(truth, ["id1", "id2"])
        one = est.select(F.lit(label).alias("method"), "seed", "id1", "id2", F.floor(F.col("inter") * 10 / F.col("uni")).cast("int").alias("decile"), (F.col("hits") * F.col("uni") - F.col("inter") * 64).alias("e"))
        out = one if out is None else out.unionByName(one)
    return out


def squared_sql(final: str) -> str:
    texts = []
    for label, _, p in ERR:
        parts = O.binned(frequent_sql(16), p) | PAIRS | O.exact() | O.estimates()
        texts.append(f"SELECT * FROM ({O.ctes(parts, f'SELECT {O.quote(label)} AS method, e.seed, e.id1, e.id2, CAST((inter * 10) // uni AS INTEGER) AS decile, hits * uni - inter * 64 AS e FROM est e JOIN exact x ON x.id1 = e.id1 AND x.id2 = e.id2')})")
    return O.ctes({"err": " UNION ALL ".join(texts)}, final)


def sums() -> list:
    return [F.count("*").alias("n"), F.sum(F.abs("e")).cast("long").alias("off")]



SUM_SQL = "count(*) AS n, CAST(sum(abs(e)) AS BIGINT) AS off FROM err"
add("mse_rollup", lambda s, d: squared(s, d).rollup("method", "decile").agg(*sums()), squared_sql(f"SELECT method, decile, {SUM_SQL} GROUP BY ROLLUP (method, decile)"))
add("mse_cube", lambda s, d: squared(s, d).cube("method", "seed").agg(*sums()), squared_sql(f"SELECT method, seed, {SUM_SQL} GROUP BY CUBE (method, seed)"))
add("mse_grouping_sets", lambda s, d: squared(s, d).groupingSets([["method"], ["seed"], []], "method", "seed").agg(*sums()), squared_sql(f"SELECT method, seed, {SUM_SQL} GROUP BY GROUPING SETS ((method), (seed), ())"))
add("mse_pivot", lambda s, d: squared(s, d).groupBy("decile").pivot("method", ["copy", "rotbin"]).agg(F.count("e")), squared_sql("SELECT decile, count(*) FILTER (WHERE method = 'copy') AS copy, count(*) FILTER (WHERE method = 'rotbin') AS rotbin FROM err GROUP BY 1"))
add("mse_unpivot", lambda s, d: squared(s, d).groupBy("decile").pivot("method", ["copy", "rotbin"]).agg(F.count("e")).unpivot("decile", ["copy", "rotbin"], "method", "n"), squared_sql("SELECT decile, method, count(*) AS n FROM err GROUP BY ALL"))
add("error_stats", lambda s, d: squared(s, d).groupBy("method").agg(F.round(F.avg("e"), 3).alias("mean"), F.round(F.stddev_pop("e"), 3).alias("sd"), F.percentile("e", 0.5).alias("median"), F.max("e").alias("most")), squared_sql("SELECT method, round(avg(e), 3) AS mean, round(stddev_pop(e), 3) AS sd, quantile_cont(e, 0.5) AS median, max(e) AS most FROM err GROUP BY 1"))


def first_attempt(spark: SparkSession, d: str) -> DataFrame:
    """The first probe of each slot that hits an even bin."""
    p = QUERIES["lateral_probe"](spark, d)
    return p.where("bin % 2 = 0").groupBy("slot").agg(F.min_by("bin", "attempt").alias("bin"), F.min("attempt").alias("attempt"))


add("donor_first_attempt", first_attempt, f"SELECT slot, arg_min(bin, attempt) AS bin, min(attempt) AS attempt FROM ({SQL['lateral_probe']}) WHERE bin % 2 = 0 GROUP BY 1")

# ---- windows, ranks, limits ----


def clockwise(spark: SparkSession, d: str) -> DataFrame:
    """Empty slots take the next value to the right, around the ring: the ring is laid out twice and read by a frame of K rows."""
    sig = grid(spark, d)
    twice = sig.withColumn("at", F.explode(F.array(F.col("slot"), F.col("slot") + 16)))
    w = Window.partitionBy("set_id").orderBy("at").rowsBetween(0, 15)
    return twice.withColumn("h", F.first("h", ignorenulls=True).over(w)).where("at < 16").select("set_id", "slot", "h")


add("clockwise_fill", clockwise, O.ctes(O.binned(BASKETS, P16.with_(fill="copy", donor="clockwise")), "SELECT set_id, CAST(slot AS INTEGER) AS slot, h FROM sig"))


def running(spark: SparkSession, d: str) -> DataFrame:
    """Hits of each pair after 1, 2, .. 64 slots: the error against M in one pass."""
    post = frequent_words(6)(spark, d)
    sig = S.sketch(post, W.with_(D=universe(spark, d)))
    a, b = sig.select(F.col("set_id").alias("id1"), "slot", F.col("h").alias("h1")), sig.select(F.col("set_id").alias("id2"), "slot", F.col("h").alias("h2"))
    w = Window.partitionBy("id1", "id2").orderBy("slot").rowsBetween(Window.unboundedPreceding, 0)
    return pairs_of(post).join(a, "id1").join(b, ["id2", "slot"]).select("id1", "id2", "slot", F.sum((F.col("h1") == F.col("h2")).cast("long")).over(w).alias("hits"))


add("running_hits", running, O.ctes(O.binned(frequent_sql(6), W) | PAIRS, "SELECT id1, id2, CAST(a.slot AS INTEGER) AS slot, CAST(sum(CAST(a.h = b.h AS BIGINT)) OVER (PARTITION BY id1, id2 ORDER BY a.slot ROWS UNBOUNDED PRECEDING) AS BIGINT) AS hits FROM pairs JOIN sig a ON a.set_id = id1 JOIN sig b ON b.set_id = id2 AND a.slot = b.slot"))
SIZES = "WITH n AS (SELECT l_suppkey AS s, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY 1) "


def sizes(spark: SparkSession, d: str) -> DataFrame:
    return lineitem(spark, d).groupBy(F.col("l_suppkey").alias("s")).agg(F.count_distinct("l_partkey").alias("n"))


def ranked(spark: SparkSession, d: str) -> DataFrame:
    """Ranks read off the histogram of sizes: the window holds a row for each distinct size, not for each supplier."""
    n = settled(sizes(spark, d))
    w = Window.orderBy(F.desc("n"))
    ranks = n.groupBy("n").agg(F.count("*").alias("c")).select("n", (F.sum("c").over(w) - F.col("c") + 1).cast("int").alias("r"), F.dense_rank().over(w).alias("dr"))
    return n.join(ranks, "n").select("s", "n", "r", "dr")


add("rank_suppliers", ranked, SIZES + "SELECT s, n, CAST(rank() OVER (ORDER BY n DESC) AS INTEGER) AS r, CAST(dense_rank() OVER (ORDER BY n DESC) AS INTEGER) AS dr FROM n")
add("lag_sizes", lambda s, d: sizes(s, d).select("s", F.lag("n").over(Window.orderBy("n", "s")).alias("before"), F.lead("n").over(Window.orderBy("n", "s")).alias("after")), SIZES + "SELECT s, lag(n) OVER (ORDER BY n, s) AS before, lead(n) OVER (ORDER BY n, s) AS after FROM n")
add("ntile_sizes", lambda s, d: sizes(s, d).select("s", F.ntile(4).over(Window.orderBy("n", "s")).alias("q"), F.round(F.percent_rank().over(Window.orderBy("n")), 6).alias("pr")), SIZES + "SELECT s, CAST(ntile(4) OVER (ORDER BY n, s) AS INTEGER) AS q, round(percent_rank() OVER (ORDER BY n), 6) AS pr FROM n")
add("range_frame_daily", lambda s, d: events(s, d).select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_timestamp(F.col("ts").cast("timestamp"))).rangeBetween(-86400, 0)).alias("n")), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(date_trunc('second', ts)) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM events")
add("topk_similar_docs", lambda s, d: QUERIES["shuffle_hash_pairs"](s, d).orderBy(F.desc("inter"), "a", "b").limit(20), SQL["shuffle_hash_pairs"] + " ORDER BY inter DESC, 1, 2 LIMIT 20")
add("sampled_pairs", lambda s, d: docs(s, d).select("doc_id").orderBy(F.md5(F.concat(F.lit("7:"), F.col("doc_id").cast("string"))), "doc_id").limit(50), "SELECT doc_id FROM documents QUALIFY row_number() OVER (ORDER BY md5(concat('7:', doc_id)), doc_id) <= 50")

# ---- sets ----


def two_flags(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """Parts of the returned lines, and of the accepted ones."""
    rows = lineitem(spark, d)
    return rows.where("l_returnflag = 'R'").select(F.col("l_partkey").alias("p")), rows.where("l_returnflag = 'A'").select(F.col("l_partkey").alias("p"))


ONE, TWO = "SELECT l_partkey AS p FROM lineitem WHERE l_returnflag = 'R'", "SELECT l_partkey AS p FROM lineitem WHERE l_returnflag = 'A'"
for label, of, word in (("intersection", "intersect", "INTERSECT"), ("difference", "subtract", "EXCEPT"), ("intersection_all", "intersectAll", "INTERSECT ALL"), ("difference_all", "exceptAll", "EXCEPT ALL")):
    add(f"set_{label}_rows", lambda s, d, of=of: (lambda x: getattr(x[0], of)(x[1]))(two_flags(s, d)), f"{ONE} {word} {TWO}")
add("set_union_rows", lambda s, d: (lambda x: x[0].union(x[1]).distinct())(two_flags(s, d)), f"{ONE} UNION {TWO}")


def array_sets(spark: SparkSession, d: str) -> DataFrame:
    """Similarity of each supplier's parts to those of supplier 1, from packed arrays."""
    packed = lineitem(spark, d).groupBy("l_suppkey").agg(F.collect_set("l_partkey").alias("e"))
    one = packed.where("l_suppkey = 1").select(F.col("e").alias("o"))
    rows = packed.crossJoin(F.broadcast(one))
    return rows.select("l_suppkey", F.size(F.array_intersect("e", "o")).alias("inter"), F.size(F.array_union("e", "o")).alias("uni"), F.size(F.array_except("e", "o")).alias("own"))


add("array_set_ops", array_sets, "WITH p AS (SELECT DISTINCT l_suppkey, l_partkey AS e FROM lineitem), o AS (SELECT e FROM p WHERE l_suppkey = 1), c AS (SELECT l_suppkey, count(*) AS n, count(*) FILTER (WHERE e IN (SELECT e FROM o)) AS i FROM p GROUP BY 1) SELECT l_suppkey, CAST(i AS INTEGER) AS inter, CAST(n + (SELECT count(*) FROM o) - i AS INTEGER) AS uni, CAST(n - i AS INTEGER) AS own FROM c")


def packed_estimate(spark: SparkSession, d: str) -> DataFrame:
    post = settled(frequent_words(24)(spark, d))
    packed = S.pack(S.sketch(post, W.with_(D=universe(spark, d))))
    a, b = packed.select(F.col("set_id").alias("id1"), F.col("sig").alias("s1")), packed.select(F.col("set_id").alias("id2"), F.col("sig").alias("s2"))
    hits = F.aggregate(F.zip_with("s1", "s2", lambda x, y: F.when(x == y, 1).otherwise(0)), F.lit(0), lambda s, x: s + x)
    return pairs_of(post).join(a, "id1").join(b, "id2").select("id1", "id2", hits.cast("long").alias("hits"))


add("packed_estimate", packed_estimate, O.ctes(O.binned(frequent_sql(24), W) | PAIRS | O.estimates(), "SELECT id1, id2, hits FROM est"))


def bin_map(spark: SparkSession, d: str) -> DataFrame:
    """Baskets as maps from occupied bin to its least offset."""
    p = P16.with_(D=part_universe(spark, d))
    minima = S.binned(baskets(spark, d), p).groupBy("set_id", "bin").agg(F.min("off").alias("o"))
    maps = minima.groupBy("set_id").agg(F.map_from_entries(F.collect_list(F.struct("bin", "o"))).alias("m"))
    low = F.map_filter("m", lambda k, v: k < 8)
    return maps.select("set_id", F.size(F.map_keys("m")).alias("bins"), F.size(low).alias("low"), F.array_min(F.map_values("m")).alias("least"))


add("bin_offset_map", bin_map, O.ctes(O.binned(BASKETS, P16), "SELECT set_id, CAST(count(DISTINCT bin) AS INTEGER) AS bins, CAST(count(DISTINCT bin) FILTER (WHERE bin < 8) AS INTEGER) AS low, min(off) AS least FROM base GROUP BY 1"))

# ---- functions of SQL text and Arrow twins ----


def arrow_path(spark: SparkSession, d: str) -> DataFrame:
    """Signatures of suppliers by the packed Arrow path; equal to the relational ones."""
    packed = suppliers(spark, d).groupBy("set_id").agg(F.collect_list("elem").alias("elems"))
    sig = sqlfns.packed_udf(SketchParams(part_universe(spark, d), 64, split="2u"))
    return packed.select("set_id", F.posexplode(sig("elems")).alias("slot", "h"))


SUPP = O.binned({"post": "SELECT DISTINCT l_suppkey AS set_id, l_partkey AS elem FROM lineitem"}, SketchParams(1 << 15, 64, split="2u"))
add("udf_rotbin", arrow_path, O.ctes(SUPP, "SELECT set_id, CAST(slot AS INTEGER) AS slot, h FROM sig"))


def aggregate_path(spark: SparkSession, d: str) -> DataFrame:
    agg = sqlfns.aggregate_udf(SketchParams(part_universe(spark, d), 64, split="2u"))
    return suppliers(spark, d).groupBy("set_id").agg(agg("elem").alias("sig")).select("set_id", F.posexplode("sig").alias("slot", "h"))


add("udaf_signature", aggregate_path, O.ctes(SUPP, "SELECT set_id, CAST(slot AS INTEGER) AS slot, h FROM sig"))


def banded(spark: SparkSession, d: str) -> DataFrame:
    sqlfns.register(spark, SketchParams(part_universe(spark, d), 64, split="2u"))
    suppliers(spark, d).groupBy("set_id").agg(F.collect_list("elem").alias("elems")).createOrReplaceTempView("rotahash_sets")
    return spark.sql("SELECT set_id, band, key FROM (SELECT set_id, rh_rotbin_sig(elems) AS sig FROM rotahash_sets) s, LATERAL rh_bands(s.sig, 4)")


add("udtf_bands", banded, O.ctes(SUPP, "SELECT set_id, CAST(slot // 4 AS INTEGER) AS band, md5(string_agg(CAST(h AS VARCHAR), ',' ORDER BY slot)) AS key FROM sig GROUP BY ALL"))


def sql_surface(spark: SparkSession, d: str) -> DataFrame:
    """Estimate and truth of supplier pairs in SQL text. The pairs that share a part come with their counts from the view rotahash_pairs, so no set or signature is sent for a pair."""
    D = part_universe(spark, d)
    sqlfns.register(spark, SketchParams(D, 64, split="2u"))
    lineitem(spark, d).createOrReplaceTempView("rotahash_lines")
    lines = spark.sql("SELECT l_suppkey AS set_id, l_partkey AS elem FROM rotahash_lines")
    slots = spark.sql(f"SELECT id AS set_id, slot * {D}L + h AS elem FROM (SELECT l_suppkey AS id, rh_rotbin_sig(collect_set(l_partkey)) AS s FROM rotahash_lines GROUP BY 1) LATERAL VIEW posexplode(s) t AS slot, h")
    overlaps(lines, beside=slots).createOrReplaceTempView("rotahash_pairs")
    return spark.sql("SELECT id1, id2, round(hits / 64, 6) AS j_hat, round(inter / uni, 6) AS j FROM rotahash_pairs")


add("sql_surface", sql_surface, O.ctes(SUPP | ALL | O.exact() | O.estimates(), "SELECT e.id1, e.id2, round(hits / 64.0, 6) AS j_hat, round(inter / CAST(uni AS DOUBLE), 6) AS j FROM est e JOIN exact x ON x.id1 = e.id1 AND x.id2 = e.id2"))

# ---- streams, each with the batch result as its SQL ----


def arrivals(ordered: DataFrame) -> tuple[str, DataFrame, int]:
    """Home of a stream, the stream, whose files (in the folder ``in``) hold ordered rows range by range, written by many tasks, and the partitions of its state."""
    spark = ordered.sparkSession
    home = new_folder(spark, "stream")
    ordered.write.option("maxRecordsPerFile", 4000).parquet(f"{home}/in")
    return home, bins.read_events(spark, f"{home}/in", ordered.schema, bins.in_order(spark, f"{home}/in")), bins.state_partitions(spark, ordered.count())


def streamed(of, mode: str = "complete"):
    def run(spark: SparkSession, d: str) -> DataFrame:
        home, rows, partitions = arrivals(events(spark, d).orderBy("ts"))
        name = f"rotahash_{uuid.uuid4().hex}"
        return bins.run_to_end(of(rows), name, mode, f"{home}/state", partitions)

    return run


def text_time(df: DataFrame) -> DataFrame:
    """Times as seconds, which every engine and zone states alike."""
    return df.select(*[F.unix_timestamp(c).alias(c) if t == "timestamp" else F.col(c) for c, t in df.dtypes])


TUMBLING = "SELECT CAST(epoch(time_bucket(INTERVAL 1 HOUR, ts)) AS BIGINT) AS start, CAST(epoch(time_bucket(INTERVAL 1 HOUR, ts)) AS BIGINT) + 3600 AS stop, event_type, count(*) AS n FROM events GROUP BY ALL"
add("stream_tumbling", lambda s, d: text_time(streamed(lambda e: bins.counted(e, F.window("ts", "1 hour")))(s, d)), TUMBLING)
add(
    "stream_sliding",
    lambda s, d: text_time(streamed(lambda e: bins.counted(e, F.window("ts", "1 hour", "30 minutes")))(s, d)),
    "SELECT b - 1800 * k AS start, b - 1800 * k + 3600 AS stop, event_type, count(*) AS n FROM (SELECT CAST(epoch(time_bucket(INTERVAL 30 MINUTE, ts)) AS BIGINT) AS b, event_type FROM events), (SELECT unnest([0, 1]) AS k) GROUP BY ALL",
)
add("stream_session", lambda s, d: text_time(streamed(lambda e: e.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "20 minutes").alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "user_id", "n"))(s, d)), "WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 20 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT CAST(floor(epoch(min(ts))) AS BIGINT) AS start, user_id, count(*) AS n FROM s GROUP BY user_id, k")
add("stream_dedup", lambda s, d: streamed(lambda e: e.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"), "append")(s, d), "SELECT DISTINCT event_id, user_id FROM events")
STREAM_P = SketchParams(1 << 20, 16, split="2u")
add(
    "stream_bin_minima",
    lambda s, d: streamed(lambda e: bins.bin_minima(e, STREAM_P))(s, d),
    f"WITH e AS (SELECT 42 AS seed, user_id, CAST(concat('0x', substr(md5(concat(event_type, ':', hour(ts))), 1, 10)) AS BIGINT) % {1 << 20} AS elem FROM events), q AS (SELECT user_id, {O.hashed('elem', '2u', STREAM_P, 1 << 20, '2u')} AS q FROM e) SELECT user_id, q // {STREAM_P.d} AS bin, min(q) AS v FROM q GROUP BY ALL",
)


def late(spark: SparkSession, d: str) -> DataFrame:
    """Windows of a stream whose files come in the wrong order: rows behind the watermark are dropped, so counts are at most those of the batch."""
    home, rows, partitions = arrivals(events(spark, d).orderBy(F.desc("ts")))
    stream = bins.counted(rows, F.window("ts", "1 hour"))
    return bins.run_to_end(stream, f"rotahash_{uuid.uuid4().hex}", "append", f"{home}/state", partitions)


add("stream_late", late)


ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def state_bins(spark: SparkSession, d: str) -> DataFrame:
    """Bin minima from arbitrary state: the least of what each user's state reported."""
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key, None)
    spark.conf.set(key, ROCKS)
    try:
        out = settled(streamed(lambda e: bins.stateful(e, STREAM_P), "update")(spark, d).groupBy("user_id", "bin").agg(F.min("v").alias("v")))
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)
    return out


add("stream_state_bins", state_bins, SQL["stream_bin_minima"])
