"""Queries do the whole job: small tables with rows that a cut would lose, against brute force."""

import random
import re
from collections import Counter

import pytest
from pyspark.errors import AnalysisException

import __spark_entry__ as entry
import reference
from symseek.plans.methods import DOC_PATTERNS
from test_entry import same

WORDS = "the and attention interesting therefore therein without interest ring und der nicht bench".split()


def prose(seed, size):
    rng = random.Random(seed)
    text = "interesting and the " + " ".join(rng.choice(WORDS) for _ in range(size // 4))
    return text[: size - 12] + " therefore. "


#: A short English text, a long one, and two in other languages.
DOCS = [(1, prose(1, 150), "en"), (2, prose(2, 1040), "en"), (3, prose(3, 300), "de"), (4, prose(4, 250), "fr")]
PATTERNS = [tuple(p) for p in DOC_PATTERNS]


def fold(text):
    return re.sub("[^a-z ]", "?", text.lower())


@pytest.fixture(scope="module")
def small(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("small"))
    spark.createDataFrame([(i, t, lang, "web", len(t)) for i, t, lang in DOCS], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([(i, i % 2, 0) for i, _, _ in DOCS], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return folder


def got(spark, folder, name, *columns):
    return sorted(tuple(tuple(x) if isinstance(x := r[c], list) else x for c in columns) for r in entry.queries()[name](spark, folder).collect())


def sifted(texts, patterns, **options):
    """(stream, pattern, start, len, dist)"""
    return sorted((i, n, *r) for i, t in texts for n, p, k in patterns for r in reference.sift(p, t, k, **options))


def test_all_documents(spark, small):
    texts = [(i, fold(t)) for i, t, _ in DOCS]
    found = sorted((i, n, *h) for i, t in texts for n, p, k in PATTERNS for h in reference.hits(p, t, k))
    columns = ("stream_id", "pattern_id", "start", "len", "dist")
    assert got(spark, small, "find_hits_docs", *columns) == found
    kept = sifted(texts, PATTERNS)
    assert {r[0] for r in kept} == {1, 2, 3, 4}
    assert got(spark, small, "online_sift_docs", *columns) == kept
    counts = Counter(r[:2] for r in kept)
    assert got(spark, small, "motif_histogram_docs", "stream_id", "vector") == [(i, tuple(counts[i, n] for n in range(3))) for i, _ in texts]


def test_retrieval_labels_and_window(spark, small):
    texts = [(i, fold(t)) for i, t, _ in DOCS]
    kept = sifted(texts, [(0, "interest", 2), (1, "without", 2)])
    count, best = Counter(r[0] for r in kept), {i: min(r[4] for r in kept if r[0] == i) for i, _ in texts}
    assert got(spark, small, "w11_retrieval_topk", "stream_id", "kept", "best") == [(i, count[i], best[i]) for i, _ in texts]
    kept = Counter((r[0] % 2, r[1]) for r in sifted(texts, [(0, "the", 0), (1, "ing", 0), (2, "and the", 2)]))
    assert got(spark, small, "w13_histogram_labels", "quality", "documents", "v0", "v1", "v2") == [(q, 2, *(kept[q, n] for n in range(3))) for q in (0, 1)]
    around = {i: t[max(t.index(" and the ") - 200, 0) : t.index(" and the ") + 209] for i, t in texts if " and the " in t}
    exhaustive = {i: len(reference.hits("therein", t, 2)) for i, t in around.items()}
    online = {i: len(reference.sift("therein", t, 2)) for i, t in around.items()}
    assert got(spark, small, "w1_doc_window", "stream_id", "exhaustive", "online") == [(i, exhaustive[i], online[i]) for i in sorted(around) if exhaustive[i]]
    assert {2, 3, 4} & {i for i in around if exhaustive[i]}


def test_whole_pages(spark, tmp_path):
    """Patterns beyond the first 2,000 symbols of a page."""
    rng = random.Random(5)
    pages = [(i, "<html><article>" + "".join(rng.choice("ab <>/") for _ in range(size)) + "<style>x</style><script></footer></html>") for i, size in ((1, 60), (2, 2100))]
    spark.createDataFrame([(i, f"http://a/{i}", h) for i, h in pages], "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    kept = sifted(pages, [(0, "<article", 1), (1, "</footer", 2)])
    assert any(r[0] == 2 and r[1] == 1 and r[2] > 2000 and r[4] == 0 for r in kept)
    assert got(spark, str(tmp_path), "online_sift_pages", "stream_id", "pattern_id", "start", "len", "dist") == kept
    kept = sifted(pages, [(0, "<script>", 2), (1, "<style>", 2)])
    expected = [(n, sum(r[1] == n for r in kept), sum(r[1] == n and r[4] == 0 for r in kept), len({r[0] for r in kept if r[1] == n})) for n in (0, 1)]
    assert got(spark, str(tmp_path), "w10_signatures_pages", "pattern_id", "kept", "exact", "streams") == expected


def test_bank_over_all_documents(spark, tmp_path):
    """A bank's pattern in a long English text and in a German one."""
    items = [(7, "Sixteen symbols it has"), (8, "another benchmark"), (9, "too short")]
    rng = random.Random(6)
    noise = "".join(rng.choice("abcde ") for _ in range(640))
    texts = [(1, noise + " sixteen symbols it has", "en"), (2, "wir haben another benchmxrk hier", "de"), (3, "sixteen symbol it has", "en")]
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    spark.createDataFrame([(i, t, lang, len(t)) for i, t, lang in texts], "doc_id long, text string, lang string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    bank = [(i, fold(t)[:16], 4) for i, t in items if len(t) >= 16]
    kept = sifted([(i, fold(t)) for i, t, _ in texts], bank)
    assert {r[0] for r in kept} == {1, 2, 3}
    assert got(spark, str(tmp_path), "bank_sift_docs40", "stream_id", "pattern_id", "start", "len", "dist") == kept
    kept = sifted([(i, fold(t)) for i, t, _ in texts], bank, validation="interval")
    assert got(spark, str(tmp_path), "w7_bank40", "pattern_id", "kept", "best") == [(n, sum(r[1] == n for r in kept), min(r[4] for r in kept if r[1] == n)) for n in (7, 8)]


def test_parts_of_one_name(spark, tmp_path):
    """Copies of a name aren't expanded into pairs; every part has its class, and no link between different names is lost."""
    names = ["red bolt", "red bolts", "ed bolt", "red volt", "", "a", "blue nut", "blue nuts!", None]
    parts = [(10 * i + 3, names[i % len(names)]) for i in range(3000)]
    spark.createDataFrame(parts, "p_partkey long, p_name string").write.parquet(f"{tmp_path}/part.parquet")
    first = {}
    for key, name in parts:
        first.setdefault(name, key)
    first.pop(None)
    expected = [("member", first[name], key, 0) for key, name in parts if name is not None]
    expected += [("link", a, b, 1) for x, a in first.items() for y, b in first.items() if a < b and reference.distance(x, y) == 1]
    assert len(expected) == 2667 + 4
    assert got(spark, str(tmp_path), "fuzzy_join_parts", "kind", "left_key", "right_key", "dist") == sorted(expected)


def test_recursion_on_large_tables(spark, tmp_path):
    """A stream with more occurrences than Spark's recursion has levels, and more steps in all than its limit of rows."""
    made = spark.range(1_100_000).selectExpr("id AS event_id", "timestamp_seconds(id) AS ts", "if(id < 500, -1, id div 60) AS user_id", "if(id % 9 = 0, 'view', 'error') AS event_type")
    made.write.parquet(f"{tmp_path}/events.parquet")
    expected = made.where("event_type = 'error'").groupBy("user_id").count()
    assert got(spark, str(tmp_path), "sql_recursive_count", "stream_id", "n") == sorted(tuple(r) for r in expected.collect())


#: Queries that were once made up, and the table that each reads now.
MOVED = {"complexity_grid": "lineitem", "dp_cells": "events", "dp_matrix": "orders", "example_chain": "orders", "example_matrix": "lineitem", "example_sift_earliest": "lineitem", "example_sift_latest": "lineitem", "example_sift_shortest": "lineitem", "pipeline_time_grid": "lineitem", "published_speedups": "lineitem", "resource_linear_fit": "documents"}


@pytest.mark.parametrize("name", MOVED)
def test_moved_to_a_given_table(spark, tables, tmp_path, name):
    """The query follows its table: without it, it fails; with it, it agrees with SQL."""
    with pytest.raises(AnalysisException, match=f"{MOVED[name]}.parquet"):
        entry.queries()[name](spark, str(tmp_path)).collect()
    same(spark, tables, name)


def lineitems(spark, folder, suppliers, count, seed=8):
    """The letters of line items by supplier, for quantities from 0 to 3."""
    rng = random.Random(seed)
    rows = [(order, 1, supplier, 1, rng.randrange(4), order) for supplier in suppliers for order in range(count)]
    made = spark.createDataFrame(rows, "l_orderkey long, l_linenumber int, l_suppkey long, l_partkey long, q int, day int")
    made.selectExpr("l_orderkey", "l_linenumber", "l_suppkey", "l_partkey", "double(q) l_quantity", "date_add(date'1995-01-01', day) l_shipdate").write.parquet(f"{folder}/lineitem.parquet")
    return {s: [r[4] for r in rows if r[2] == s] for s in suppliers}


def test_fold_of_all_streams(spark, tmp_path):
    letters = lineitems(spark, tmp_path, (3, 13, 500), 70)
    kept = sifted([(i, "".join("acgt"[q] for q in own)) for i, own in letters.items()], [(0, "acgta", 3)])
    assert {r[0] for r in kept} == {3, 13, 500}
    assert got(spark, str(tmp_path), "resync_fold", "stream_id", "pattern_id", "start", "len", "dist") == kept


def test_speed_streams(spark, tmp_path):
    """Streams beyond the first four, and trials by 100 numbers."""
    letters = lineitems(spark, tmp_path, (1, 5, 21, 99), 24)
    by = lambda n: {k: "".join("ABCD"[q] for day in range(24) for i in sorted(letters) if i % n == k for q in [letters[i][day]]) for k in {i % n for i in letters}}
    trials = Counter(r[0] for r in sifted(list(by(100).items()), [(0, "ABDCABC", 3)]))
    assert got(spark, str(tmp_path), "w5_trials", "stream_id", "kept") == sorted(trials.items()) and set(trials) == {1, 5, 21, 99}
    for name, sweep in (("w3_lp_sweep", [(n, "ABDCABCCDBADCBA"[:n], 3) for n in (5, 7, 10, 15)]), ("w4_k_sweep", [(10 * n + k, "ABDCABCCDBADCBA"[:n], k) for n in (5, 15) for k in (2, 3, 4, 5)])):
        texts = list(by(16).items())
        expected = []
        for n, p, k in sweep:
            found = [(i, *h) for i, t in texts for h in reference.hits(p, t, k)]
            kept = sifted(texts, [(n, p, k)])
            if kept:
                expected.append((n, len(found), len({(i, s + m) for i, s, m, _ in found}), len(kept)))
        assert got(spark, str(tmp_path), name, "pattern_id", "hits", "ends", "kept") == expected


def common(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        old, row = row, [0]
        for j, y in enumerate(b):
            row.append(old[j] + 1 if x == y else max(row[-1], old[j + 1]))
    return row[-1]


def test_distances_to_whole_streams(spark, tables):
    texts = sorted((r["stream_id"], r["text"]) for r in entry.queries()["build_streams_events"](spark, tables).collect())
    assert max(len(t) for _, t in texts) > 12
    whole = [(i, reference.distance("SVCPE", t)) for i, t in texts]
    assert got(spark, tables, "edit_distance", "stream_id", "dist") == whole
    assert sorted(got(spark, tables, "edit_within", "stream_id", "dist"), key=lambda r: r[0]) == [(i, d if d <= 5 else None) for i, d in whole]
    assert got(spark, tables, "dp_last_row", "stream_id", "m", "dist") == [(i, m, reference.distance("CVPSEC", t[:m])) for i, t in texts for m in range(len(t) + 1)]
    assert got(spark, tables, "indel_distance", "stream_id", "dist") == [(i, 5 + len(t) - 2 * common("SVCPE", t)) for i, t in texts]
    assert got(spark, tables, "array_functions", "stream_id", "more", "total") == [(i, tuple(ord(c) + 1 for c in t), sum(map(ord, t))) for i, t in texts]


@pytest.mark.parametrize("name", ["edit_distance", "edit_within", "dp_last_row", "indel_distance", "array_functions"])
def test_distances_against_sql(spark, tables, name):
    same(spark, tables, name)


def test_all_symbols_and_lines(spark, small, tables):
    assert got(spark, small, "unpack_streams", "stream_id", "pos", "sym") == [(i, at, c) for i, t, _ in DOCS for at, c in enumerate(fold(t))]
    lines = spark.read.parquet(f"{tables}/lineitem.parquet").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate").collect()
    placed = {}
    for r in spark.read.parquet(f"{tables}/orders.parquet").collect():
        placed.setdefault(r["o_custkey"], []).append((r["o_orderdate"], r["o_orderkey"]))
    expected = Counter((*r, max((o for o in placed.get(r["l_suppkey"], ()) if o[0] <= r["l_shipdate"]), default=(None, None))[1]) for r in lines)
    assert len({r["l_linenumber"] for r in lines}) > 1
    assert Counter(tuple(r) for r in entry.queries()["asof_last_event"](spark, tables).collect()) == expected


def test_document_shorter_than_an_item(spark):
    """A whole document that is an item short of its last word; half an item isn't one."""
    pytest.importorskip("symseek.llm.decontaminate")
    from symseek.llm import decontaminate

    words = [f"w{i}" for i in range(20)]
    texts = [(1, " ".join(words[:-1])), (2, " ".join(words[:10])), (3, " ".join(words[1:])), (4, " ".join(words))]
    docs, items = spark.createDataFrame(texts, "doc_id long, text string"), spark.createDataFrame([(5, " ".join(words))], "item_id long, text string")
    found = {r["doc_id"]: (r["similarity"], r["n_words"]) for r in decontaminate.find_items(docs, items).collect()}
    assert found == {1: (15 / 16, 19), 3: (15 / 16, 19), 4: (1.0, 20)}
    assert [r["doc_id"] for r in decontaminate.without_items(docs, items).collect()] == [2]
