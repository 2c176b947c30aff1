"""Tables and the sets made of them: postings (set_id, elem), distinct, elements from 0 on."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SHINGLE_BITS = 40


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_sets(df: DataFrame, set_id: str, elem: str) -> DataFrame:
    """Postings of any two columns: nulls are no elements, repeats count once."""
    return df.select(F.col(set_id).alias("set_id"), F.col(elem).alias("elem")).where("set_id is not null and elem is not null").distinct()


def read_sets(spark: SparkSession, path: str, kind: str, set_id: str, elem: str, schema: str | None = None) -> DataFrame:
    """Postings from files of any kind Spark reads: parquet, orc, csv, json."""
    reader = spark.read.format(kind)
    reader = reader.schema(schema) if schema else reader
    return load_sets((reader.option("header", True) if kind == "csv" else reader).load(path), set_id, elem)


def tokens(text: Column) -> Column:
    """Lower-case runs of a-z and 0-9."""
    return F.filter(F.split(F.lower(text), "[^a-z0-9]+"), lambda w: w != "")


def token_id(text: Column, bits: int = SHINGLE_BITS) -> Column:
    """An id of any text from its md5: the first 40 bits, folded."""
    return F.pmod(F.conv(F.substring(F.md5(text), 1, 10), 16, 10).cast("long"), F.lit(1 << bits))


def word_postings(docs: DataFrame, distinct: bool = True) -> DataFrame:
    """Sets: words; elements: the documents that hold them. Without ``distinct`` rows of equal doc_id repeat their postings, which minima don't mind; that saves an exchange."""
    rows = docs.where("doc_id is not null").select(F.col("doc_id").alias("elem"), F.explode(F.array_distinct(tokens(F.col("text")))).alias("set_id")).select("set_id", "elem")
    return rows.distinct() if distinct else rows


def document_words(docs: DataFrame) -> DataFrame:
    """Sets: documents; elements: md5 ids of their words."""
    return docs.select(F.col("doc_id").alias("set_id"), F.explode(F.array_distinct(tokens(F.col("text")))).alias("w")).select("set_id", token_id(F.col("w")).alias("elem")).distinct()


def shingles(words: Column, k: int = 5) -> Column:
    """Distinct runs of k words of an array, joined by blanks; none if there are fewer."""
    runs = F.transform(F.sequence(F.lit(1), F.size(words) - k + 1), lambda i: F.array_join(F.slice(words, i, k), " "))
    return F.when(F.size(words) >= k, F.array_distinct(runs)).otherwise(F.array().cast("array<string>"))


def shingle_postings(rows: DataFrame, set_id: str, text: Column, k: int = 5, bits: int = SHINGLE_BITS) -> DataFrame:
    """Sets: rows; elements: md5 ids of their k-word shingles. The words are a column of their own, so they are split once and not for every run."""
    words = rows.select(F.col(set_id).alias("set_id"), tokens(text).alias("w"))
    return words.select("set_id", F.explode(shingles(F.col("w"), k)).alias("s")).select("set_id", token_id(F.col("s"), bits).alias("elem")).distinct()


def ngram_postings(rows: DataFrame, set_id: str, text: Column, n: int = 4, bits: int = SHINGLE_BITS) -> DataFrame:
    """Sets: rows; elements: md5 ids of their character n-grams."""
    grams = F.when(F.length(text) >= n, F.transform(F.sequence(F.lit(1), F.length(text) - n + 1), lambda i: F.substr(text, i, F.lit(n))))
    return rows.select(F.col(set_id).alias("set_id"), F.explode(F.array_distinct(grams)).alias("s")).select("set_id", token_id(F.col("s"), bits).alias("elem")).distinct()


def basket_postings(lineitem: DataFrame) -> DataFrame:
    """Sets: orders; elements: their parts."""
    return load_sets(lineitem, "l_orderkey", "l_partkey")


def supplier_postings(lineitem: DataFrame) -> DataFrame:
    """Sets: suppliers; elements: the parts they deliver."""
    return load_sets(lineitem, "l_suppkey", "l_partkey")


def user_activity(events: DataFrame) -> DataFrame:
    """Sets: users; elements: (type of event, hour of the day) as md5 ids."""
    key = F.concat_ws(":", "event_type", F.hour("ts").cast("string"))
    return events.select(F.col("user_id").alias("set_id"), token_id(key).alias("elem")).where("set_id is not null and elem is not null").distinct()


def strip_html(html: Column) -> Column:
    """Text without scripts, styles, tags and entities."""
    out = F.regexp_replace(html, "(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    out = F.regexp_replace(out, "<[^>]*>", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(out, "&[a-zA-Z#0-9]+;", " "), "[ \\t\\r\\n]+", " "))


def frequent(postings: DataFrame, n: int, most: int | None = None, least: int = 1) -> DataFrame:
    """The postings of the n largest sets with at least ``least`` and, if given, at most ``most`` elements, ties by id: a choice of pairs for experiments."""
    sizes = postings.groupBy("set_id").agg(F.count("*").alias("n")).where(F.col("n") >= least)
    top = (sizes if most is None else sizes.where(F.col("n") <= most)).orderBy(F.desc("n"), "set_id").limit(n)
    return postings.join(F.broadcast(top.select("set_id")), "set_id")


def synthetic_pairs(spark: SparkSession, f: int, tenths: tuple[int, ...]) -> DataFrame:
    """For each j of ``tenths`` two sets, ids 2j and 2j+1, with f elements in their union and a = j*f/10 (rounded down) in common."""
    rows = spark.range(f).select(F.col("id").alias("elem")).crossJoin(F.broadcast(spark.createDataFrame([(j,) for j in tenths], "j long")))
    a = F.floor(F.col("j") * f / 10)
    first = F.col("elem") < a + F.floor((F.lit(f) - a) / 2)
    side = F.when(F.col("elem") < a, F.array(F.lit(0), F.lit(1))).when(first, F.array(F.lit(0))).otherwise(F.array(F.lit(1)))
    return rows.select("j", "elem", F.explode(side).alias("side")).select((F.col("j") * 2 + F.col("side")).alias("set_id"), "elem")


def nearest_per_decile(exact: DataFrame) -> DataFrame:
    """(decile, id1, id2): of each tenth of similarity the pair closest to it, ties by ids."""
    spark = exact.sparkSession
    deciles = spark.createDataFrame([(d,) for d in range(1, 10)], "decile int")
    gap = F.abs(F.col("inter").cast("double") / F.col("uni") - F.col("decile") / F.lit(10.0))
    # the best of each partition first: min over (gap, ids) needs no sort of all pairs
    best = exact.crossJoin(F.broadcast(deciles)).groupBy("decile").agg(F.min(F.struct(gap.alias("gap"), "id1", "id2")).alias("b"))
    return best.select("decile", "b.id1", "b.id2")
