"""The pipeline's stages on planted cases, and its whole run."""

import corpus_pipeline as P
from pyspark.sql import functions as F

from symseek.llm.common import table


def test_stages_keep_columns_and_take_effect(spark, tables):
    docs = table(spark, tables, "documents").withColumn("h", F.lit(7)).withColumn("score", F.lit("x"))
    item = table(spark, tables, "benchmark").first()["text"]
    words = [f"planted{i}" for i in range(80)]
    base = " ".join(words)
    rows = [(10_001, f"alpha beta {base} gamma"), (10_002, f"{base} " + " ".join(f"other{i}" for i in range(60))), (10_003, f"Some words. {item} More."), (10_004, None), (10_005, f"alpha beta {base} gamma")]
    planted = spark.createDataFrame(rows, "doc_id long, text string").select("doc_id", "text", F.lit("en").alias("lang"), F.lit("s").alias("source"), F.coalesce(F.char_length("text"), F.lit(0)).cast("long").alias("n_chars"), F.lit(7).alias("h"), F.lit("x").alias("score"))
    every = docs.unionByName(planted)
    larger = tables.replace("0.001", "0.01")
    whole, labels = table(spark, larger, "documents"), table(spark, larger, "labels")
    good = P.quality_classifier(spark, whole, larger)
    assert good.columns == whole.columns and good.count() < whole.count()
    share = {r["quality"]: r["share"] for r in labels.join(good.select("doc_id", F.lit(1).alias("kept")), "doc_id", "left").groupBy("quality").agg((F.count("kept") / F.count(F.lit(1))).alias("share")).collect()}
    assert share[1] > 0.95 and share[0] < 0.2
    unique = P.near_copies(spark, every, tables)
    ids = {r["doc_id"] for r in unique.select("doc_id").collect()}
    assert unique.columns == every.columns and 10_001 in ids and 10_005 not in ids and {10_002, 10_003, 10_004} <= ids
    cut = P.substring_removal(spark, every, tables)
    after = {r["doc_id"]: r for r in cut.where("doc_id > 10000").collect()}
    assert cut.columns == every.columns and cut.count() == every.count()
    assert after[10_001]["text"] == rows[0][1] and after[10_005]["text"] == "" and after[10_002]["text"] == " ".join(f"other{i}" for i in range(60)) and after[10_004]["text"] is None
    assert after[10_002]["n_chars"] == len(after[10_002]["text"])
    clean = P.decontamination(spark, every, tables)
    assert clean.columns == every.columns and {r["doc_id"] for r in clean.where("doc_id > 10000").collect()} == {10_001, 10_002, 10_004, 10_005}


def test_run(spark, tables):
    out = P.run(spark, tables)
    assert out.count() > 0 and out.where("not restored").count() == 0
    assert out.select("doc_id").distinct().count() < table(spark, tables, "documents").count()


ODD = "doc_id long, text string, lang string, source string, n_chars long, extra_id long, __held string, row int, carried_0 string"


def test_stages_on_odd_rows(spark, tables):
    """Empty tables, null keys, repeated rows and clashing names: each stage keeps the columns and gives the defined result."""
    base = " ".join(f"w{i}" for i in range(70))
    odd = [(1, base, "en", "s", 9, 1, "a", 1, "x"), (1, base, "en", "s", 9, 1, "a", 1, "x"), (2, base, None, None, None, None, None, None, None), (None, base, "en", "s", 9, 1, "a", 1, "x"), (3, None, "en", "s", 0, 1, "a", 1, "x"), (4, "", "en", "s", 0, 1, "a", 1, "x")]
    none, some = spark.createDataFrame([], ODD), spark.createDataFrame(odd, ODD)
    for stage in (P.quality_classifier, P.near_copies, P.substring_removal, P.decontamination):
        got = stage(spark, none, tables)
        assert got.columns == none.columns and got.count() == 0
    assert P.sampled_segmentations(spark, none, tables).count() == 0
    ids = lambda df: sorted((r["doc_id"] is not None, r["doc_id"] or 0) for r in df.collect())
    assert ids(P.near_copies(spark, some, tables)) == [(False, 0), (True, 1), (True, 1), (True, 3), (True, 4)]
    cut = P.substring_removal(spark, some, tables).collect()
    assert sorted((r["doc_id"] or 0, r["text"]) for r in cut if r["text"]) == [(0, base), (1, base), (1, base)] and len(cut) == 6 and [r["__held"] for r in cut if r["doc_id"] == 2] == [None]
    assert len(ids(P.decontamination(spark, some, tables))) == 6
    assert P.sampled_segmentations(spark, some, tables).count() >= 6
    assert P.quality_classifier(spark, some, tables).columns == some.columns
