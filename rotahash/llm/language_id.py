"""Language of whole texts by prediction by partial matching.

One byte-context trie a language is learned from labelled texts and frozen; a text gets the language under
which its code is shortest. Learning counts strings per task and language and adds them up by bucket, so
a language with most of the rows is no hot key. The models are bounded as in ``lm_scoring``: ``limit``
strings per order and language; the number of languages is that of the distinct labels.

Defined results: a null text or one without a letter is ``und`` with score 0; so is every text if no labelled
text was learned. Score is the posterior of the predicted language with equal priors; ties go to the label
that sorts first. Language, source and doc_id play no part in a prediction.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rotahash.llm import ppm
from rotahash.llm.bytesops import U, lean, mix, pack, slices
from rotahash.llm.durable import durable, partitions
from rotahash.llm.lm_scoring import GRAMS, ROWS, STRING, _row, models_of, train

ORDER, LIMIT = 3, 1 << 17


def learn(docs: DataFrame, order: int = ORDER, limit: int = LIMIT) -> tuple[list[str], dict]:
    """Labels in order, and the packed models by their number, from the rows of docs (text, lang) that have both."""
    spark = docs.sparkSession
    rows = docs.where("lang is not null and text is not null").select("text", "lang")
    labels = sorted(r[0] for r in rows.select("lang").distinct().collect())  # one row per language
    number = {x: i for i, x in enumerate(labels)}
    buckets = partitions(spark)

    def count(batches):
        seen = {}
        for b in batches:
            own = b.column("lang").to_pylist()
            for label in set(own):
                text = b.column("text").filter(pa.array([x == label for x in own]))
                strings = seen.setdefault(number[label], ppm.Grams(order))
                for _, _, data, at in slices(text, lower=True):
                    strings.add(data, at)
        for label, strings in sorted(seen.items()):
            keys, counts = strings.fold()
            bucket = (mix(keys & U(0xFFFFFF)) % U(buckets)).astype(np.int64)
            for k in np.unique(bucket).tolist():
                yield _row(GRAMS, k, label, pack([keys[bucket == k], counts[bucket == k]], STRING))

    return labels, train(durable(rows.mapInArrow(lean(count), ROWS)), order, limit)


def predict(docs: DataFrame, labels: list[str], models: dict, order: int = ORDER) -> DataFrame:
    """doc_id, lang_pred and score of every document."""
    shared = docs.sparkSession.sparkContext.broadcast((uuid.uuid4().hex, order, models))

    def choose(batches):
        own = models_of(shared)
        known = sorted(own)
        for b in batches:
            best, score = np.full(b.num_rows, -1), np.zeros(b.num_rows)
            letters = b.column("letters").to_numpy(zero_copy_only=False)
            if known:
                for lo, hi, data, at in slices(b.column("text"), lower=True):
                    code = np.stack([own[k].score(data, at) for k in known])
                    best[lo:hi] = code.argmax(0)
                    score[lo:hi] = 1 / (10.0 ** np.maximum(code - code.max(0), -300)).sum(0)
            bad = (best < 0) | ~letters.astype(bool)
            names = ["und" if x else labels[known[i]] for x, i in zip(bad.tolist(), best.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(names, pa.string()), pa.array(np.where(bad, 0.0, score))], ["doc_id", "lang_pred", "score"])

    has = F.coalesce(F.col("text").rlike("\\p{L}"), F.lit(False)).alias("letters")
    return docs.select("doc_id", "text", has).mapInArrow(lean(choose), "doc_id long, lang_pred string, score double")


def identify(docs: DataFrame, modulus: int = 5, held: int = 0, order: int = ORDER, limit: int = LIMIT) -> DataFrame:
    """One row per document: doc_id, held_out, lang_pred and score; learned from the rows that are not held out."""
    is_held = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % modulus == held, F.lit(False))
    labels, models = learn(docs.where(~is_held).select("text", "lang"), order, limit)
    return predict(docs, labels, models, order).select("doc_id", is_held.alias("held_out"), "lang_pred", "score")
