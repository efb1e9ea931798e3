"""The language stage learns from every training row."""

import numpy as np
from pyspark.sql import functions as F

from labelroute.llm import langid


def test_counts_together_are_the_sum():
    texts = ["", "a", "Ab", "ÀÉ x" * 7, "z" * 40_000, "one two", "ß"] * 3
    assert (langid.counts_of_all(texts) == np.sum([langid.counts_of(t) for t in texts], axis=0)).all()


def test_a_language_outside_the_sample_is_learned(spark):
    """Of more rows than ``TRAIN_ROWS`` a sample by hash would leave this text out."""
    rare = next(
        t for t in (f"ξψζ λωφ θδγ {i}" for i in range(100))
        if spark.range(1).select(F.pmod(F.xxhash64(F.lit(t)), F.lit(1 << 20))).first()[0] > (1 << 20) * 0.9
    )
    n = langid.TRAIN_ROWS * 3 // 2
    common = spark.range(n).select(F.col("id").alias("doc_id"), F.concat(F.lit("plain words of one kind "), F.col("id") % 97).alias("text"), F.lit("aa").alias("lang"))
    some = spark.range(n, n + 60).select(F.col("id").alias("doc_id"), F.lit(rare).alias("text"), F.lit("zz").alias("lang"))
    got = langid.keep_identified(common.unionByName(some)).groupBy("lang").count().collect()
    assert {r["lang"]: r["count"] for r in got} == {"aa": n, "zz": 60}
