"""The registered queries: one for each operator, SQL where there is any, and whole results."""

import importlib.util

import pytest

import __spark_entry__ as entry


def test_names():
    names = entry.queries()
    for n in range(1, 11):
        assert len([x for x in names if x.startswith(f"op{n}_")]) == 1
    assert "pipeline" in names and importlib.util.find_spec("corpus_pipeline")


@pytest.mark.parametrize("name", ["op3_sharding", "op8_substring_dedup", "op10_ngram_jaccard_join"])
def test_query_against_sql(spark, tables, name):
    from test_entry import same

    same(spark, tables, name)


@pytest.mark.parametrize(("name", "columns"), [
    ("op1_language_id", "doc_id held_out lang_pred score"), ("op2_quality_classifier", "doc_id held_out score predicted"), ("op6_sentencepiece_sampling", "doc_id draw"), ("op9_media_columns", "doc_id n_bytes payload_bytes payload_sha256 tail_crc32 media_bytes media_sha256 feature"),
])
def test_query_covers_the_table(spark, tables, name, columns):
    df = entry.queries()[name](spark, tables)
    assert df.columns[: len(columns.split())] == columns.split()
    assert df.select("doc_id").distinct().count() == spark.read.parquet(f"{tables}/documents.parquet").count()


def test_extraction_and_counts(spark, tables):
    pages = entry.queries()["op5_html_extraction"](spark, tables)
    assert pages.columns[:4] == ["page_id", "url", "text", "n_chars"] and pages.count() == spark.read.parquet(f"{tables}/pages.parquet").count()
    totals = entry.queries()["op7_token_counts"](spark, tables)
    docs = spark.read.parquet(f"{tables}/documents.parquet")
    assert totals.agg({"docs": "sum"}).first()[0] == docs.select("text").distinct().count()


def test_counts_against_brute_force(spark, tables):
    """op7: the first document of each text counts, with each line once; every group that any document has is there."""
    from symseek.llm import token_counts

    encode = token_counts._pieces(token_counts.VOCABULARY).encode_ordinary
    expected, seen = {}, set()
    for r in sorted(spark.read.parquet(f"{tables}/documents.parquet").collect(), key=lambda r: r["doc_id"]):
        total = expected.setdefault((r["source"], r["lang"]), [0, 0, 0])
        text = r["text"] or ""
        if text not in seen:
            seen.add(text)
            once = "\n".join(dict.fromkeys(text.split("\n")))
            for i, x in enumerate((1, len(encode(once)), len(once.encode()))):
                total[i] += x
    found = entry.queries()["op7_token_counts"](spark, tables).collect()
    assert {(r["source"], r["lang"]): [r["docs"], r["tokens"], r["bytes"]] for r in found} == expected and len(found) == len(expected)
