"""Queries for the measures and the experiment workloads."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from symseek.functions import costmodel as C
from symseek.operators import baselines, hits, measures, sifter
from symseek.plans import sqltext as Q
from symseek.plans.methods import EV_PATTERNS, EVH, conversations, docs, embeddings, ev_hits, ev_kept, events, lines4, lines16, lines100, lines_abcd, orders_abc, pages, pats
from symseek.plans.registry import Tables, query
from symseek.sources import streams as S
from symseek.sources.scratch import written

EVK = Q.sift(EVH, 2)

# Measures.


def _counts(streams: DataFrame, patterns: DataFrame) -> DataFrame:
    found = written(hits.find_hits(streams, patterns), "hits")
    kept = sifter.sift_hits(found, sifter.most_levels(patterns), number=False)
    return measures.hit_counts({"exhaustive": found, "free_start": baselines.free_start_ends(streams, patterns), "online": kept})


def counts_sql(hits_sql: str, k: int) -> str:
    count = lambda rows, name: f"SELECT stream_id, pattern_id, count(*) AS {name} FROM {rows} GROUP BY ALL"
    return f"""SELECT stream_id, pattern_id, exhaustive, free_start, online FROM ({count(hits_sql, 'exhaustive')})
JOIN ({count(Q.ends(hits_sql), 'free_start')}) USING (stream_id, pattern_id) JOIN ({count(Q.sift(hits_sql, k), 'online')}) USING (stream_id, pattern_id)"""


@query("hit_count_table", counts_sql(EVH, 2))
def _(t):
    return _counts(events(t), pats(t, EV_PATTERNS))


@query("count_ordering", f"SELECT bool_and(online <= free_start AND free_start <= exhaustive) AS holds, count(*) AS rows_seen FROM ({counts_sql(EVH, 2)})")
def _(t):
    return _counts(events(t), pats(t, EV_PATTERNS)).agg(F.bool_and((F.col("online") <= F.col("free_start")) & (F.col("free_start") <= F.col("exhaustive"))).alias("holds"), F.count(F.lit(1)).alias("rows_seen"))


def _coverage_sql(hits_sql: str) -> str:
    return f"SELECT stream_id, pattern_id, pos, count(*) AS n FROM (SELECT stream_id, pattern_id, unnest(range(start, start + len)) AS pos FROM {hits_sql}) GROUP BY ALL"


@query("coverage_by_position", _coverage_sql(EVH))
def _(t):
    return measures.coverage(ev_hits(t))


@query("shadow_ratio", f"SELECT pattern_id, hits, kept, round(hits / kept, 6) AS ratio FROM (SELECT pattern_id, count(*) AS hits FROM {EVH} GROUP BY ALL) JOIN (SELECT pattern_id, count(*) AS kept FROM {EVK} GROUP BY ALL) USING (pattern_id)")
def _(t):
    return measures.shadow_ratio(ev_hits(t), ev_kept(t))


_VIOLATIONS = """SELECT pattern_id, count(*) FILTER (WHERE start <= reach) AS violations FROM (
  SELECT *, max(start + len - 1) OVER (PARTITION BY stream_id, pattern_id ORDER BY start, len ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS reach FROM {}) GROUP BY pattern_id"""


@query("overlap_violations", _VIOLATIONS.format(EVK))
def _(t):
    return measures.overlap_violations(ev_kept(t))


@query("overlap_violations_interval", _VIOLATIONS.format(Q.sift(EVH, 2, validation="interval")))
def _(t):
    return measures.overlap_violations(ev_kept(t, validation="interval"))


@query("decision_delay", f"""SELECT pattern_id, dist, count(*) AS n, max(delay) AS max_delay, round(avg(delay), 6) AS mean_delay, max(greatest(delay - (lp * (weakest + 1) + weakest * (weakest - 1) // 2), 0))::BIGINT AS excess
FROM (SELECT *, decided_at - start + 1 AS delay, max(dist) OVER (PARTITION BY stream_id, pattern_id, decided_at) AS weakest FROM {EVK}) JOIN {Q.patterns(EV_PATTERNS)} p USING (pattern_id) GROUP BY pattern_id, dist""")
def _(t):
    return measures.decision_delay(ev_kept(t), pats(t, EV_PATTERNS))


# Cost models, for streams of the given tables: their lengths, times the lengths and thresholds of patterns.

_LINE_LENGTHS = "(SELECT l_suppkey AS stream_id, count(*) AS n FROM lineitem WHERE l_quantity IS NOT NULL GROUP BY l_suppkey)"
_GRID = "(SELECT lp::INTEGER AS lp, k::INTEGER AS k FROM (VALUES (5), (7), (10), (15), (16), (32)) a(lp), range(1, 6) b(k))"


def _grid(t: Tables) -> DataFrame:
    return t.spark.createDataFrame([(lp, k) for lp in (5, 7, 10, 15, 16, 32) for k in range(1, 6)], "lp int, k int")


def _line_lengths(t: Tables, stream_id: str = "l_suppkey") -> DataFrame:
    return t.lineitem.where("l_quantity is not null").groupBy(F.expr(stream_id).alias("stream_id")).agg(F.count(F.lit(1)).alias("n"))


@query("state_bound_grid", f"SELECT lp, k, 3 * (k + 1) AS numbers, (lp * (k + 1) + k * (k - 1) // 2 * (2 * k + 1))::BIGINT AS bound FROM {_GRID}")
def _(t):
    return _grid(t).select("lp", "k", (3 * (F.col("k") + 1)).alias("numbers"), C.state_bound(F.col("lp"), F.col("k")).cast("long").alias("bound"))


@query("complexity_grid", f"SELECT stream_id, n, lp, k, n::DOUBLE * n * n * n + n::DOUBLE * n AS exhaustive, n::DOUBLE * lp AS free_start, n::DOUBLE * (lp * (k + 1) + k * (k - 1) // 2) AS online FROM {_LINE_LENGTHS}, {_GRID}")
def _(t):
    n = F.col("n").cast("double")
    return _line_lengths(t).join(F.broadcast(_grid(t)), how="cross").select("stream_id", "n", "lp", "k", *[C.op_counts(n, F.col("lp"), F.col("k"), m).cast("double").alias(m) for m in ("exhaustive", "free_start", "online")])


@query("dp_cells", f"SELECT stream_id, n, lp, k, (n * lp * (lp + k))::BIGINT AS prefix, (n * (lp * (lp + k) - (greatest(lp - k, 0) * greatest(lp - k - 1, -1) // 2) - (lp - 1) * lp // 2))::BIGINT AS band, (n * lp * lp * (2 * k + 1))::BIGINT AS separate, (n * lp)::BIGINT AS free_start "
    f"FROM (SELECT user_id AS stream_id, count(*) AS n FROM events WHERE event_type IS NOT NULL GROUP BY user_id), {_GRID} WHERE lp > k")
def _(t):
    n = F.col("n")
    lengths = t.events.where("event_type is not null").groupBy(F.col("user_id").alias("stream_id")).agg(F.count(F.lit(1)).alias("n"))
    return lengths.join(F.broadcast(_grid(t).where("lp > k")), how="cross").select("stream_id", "n", "lp", "k", *[C.dp_cells(n, F.col("lp"), F.col("k"), m).cast("long").alias(m) for m in ("prefix", "band", "separate", "free_start")])


@query("pipeline_time_grid", f"SELECT stream_id, n, lp, k, 2 * lp + k - 1 AS steps, k + 1 AS latency, 2 * k + 1 AS latency_validating, 2 * k + 1 <= 2 * lp + k - 1 AS hidden, round((2 * lp + k - 1) * 1e-8 * n, 9) AS seconds FROM {_LINE_LENGTHS}, {_GRID}")
def _(t):
    lp, k = F.col("lp"), F.col("k")
    return _line_lengths(t).join(F.broadcast(_grid(t)), how="cross").select(
        "stream_id", "n", "lp", "k", C.step_count(lp, k).alias("steps"), C.search_latency(k, False).alias("latency"), C.search_latency(k, True).alias("latency_validating"),
        C.search_is_hidden(lp, k).alias("hidden"), F.round(C.execution_time(lp, k, F.col("n"), 1e-8), 9).alias("seconds"),
    )


_RESOURCES = "(SELECT * FROM (VALUES " + ", ".join(f"({b}, {lp}, {k + 1}, {e})" for (b, lp), row in C.RESOURCES.items() for k, e in enumerate(row)) + ") v(bits, lp, k, elements))"


#: The published units that are wide enough for the symbols of each document, by the narrowest width that is.
_UNITS = f"""(SELECT v.* FROM (SELECT ceil(log2(len(list_distinct(string_split(text, ''))) + 2)) AS need FROM {Q.docs('text IS NOT NULL')}) u
JOIN {_RESOURCES} v ON v.bits = CASE WHEN need <= 4 THEN 4 WHEN need <= 8 THEN 8 WHEN need <= 12 THEN 12 ELSE 16 END)"""


@query("resource_linear_fit", " UNION ALL ".join(f"SELECT '{a}' AS axis, round(regr_slope(elements, {a}), 6) AS slope, round(regr_r2(elements, {a}), 6) AS r2, count(*) AS n, round(max(elements) / 114800.0, 6) AS largest_share FROM {_UNITS}" for a in ("bits", "lp", "k")))
def _(t):
    alphabet = sum((F.contains("text", F.lit(c)).cast("int") for c in "abcdefghijklmnopqrstuvwxyz ?"), F.lit(0))
    need = C.symbol_bits(alphabet)
    width = F.when(need <= 4, 4).when(need <= 8, 8).when(need <= 12, 12).otherwise(16)
    rows = docs(t).select(width.alias("bits")).join(F.broadcast(C.resource_frame(t.spark)), "bits")
    fits = [
        rows.agg(F.lit(a).alias("axis"), F.round(F.regr_slope("elements", a), 6).alias("slope"), F.round(F.regr_r2("elements", a), 6).alias("r2"), F.count(F.lit(1)).alias("n"), F.round(F.max("elements") / C.ELEMENTS_OF_DEVICE, 6).alias("largest_share"))
        for a in ("bits", "lp", "k")
    ]
    return fits[0].unionByName(fits[1]).unionByName(fits[2])


@query("published_speedups", "SELECT stream_id, n, test, lp, k, round(software * n / 3104, 6) AS software_seconds, round(hardware * n / 3104, 9) AS hardware_seconds, round(software / hardware, 3) AS speedup, round(3104 / software, 6) AS software_rate, round((2 * lp + k - 1) * 1e-8 * 3104 / hardware, 6) AS model_share FROM (VALUES "
    + ", ".join(f"({a}, {b}, {c}, {d}::DOUBLE, {f}::DOUBLE)" for a, b, c, d, _, f in C.SPEEDS) + ") v(test, lp, k, software, hardware), (SELECT l_suppkey % 16 AS stream_id, count(*) AS n FROM lineitem WHERE l_quantity IS NOT NULL GROUP BY 1)")
def _(t):
    """What the published rates, measured on 3104 symbols, come to for the streams of the speed tests."""
    return _line_lengths(t, "l_suppkey % 16").join(F.broadcast(C.speed_frame(t.spark)), how="cross").select(
        "stream_id", "n", "test", "lp", "k", F.round(F.col("software") * F.col("n") / 3104, 6).alias("software_seconds"), F.round(F.col("hardware") * F.col("n") / 3104, 9).alias("hardware_seconds"),
        F.round(F.col("software") / F.col("hardware"), 3).alias("speedup"), F.round(3104 / F.col("software"), 6).alias("software_rate"),
        F.round(C.execution_time(F.col("lp"), F.col("k"), F.lit(3104), 1e-8) / F.col("hardware"), 6).alias("model_share"),
    )


@query("symbol_bits", "SELECT a::INTEGER AS alphabet, ceil(log2(a + 2))::INTEGER AS bits FROM (VALUES (2), (3), (4), (5), (6), (14), (28), (128), (254), (255)) v(a)")
def _(t):
    rows = t.spark.createDataFrame([(a,) for a in (2, 3, 4, 5, 6, 14, 28, 128, 254, 255)], "alphabet int")
    return rows.select("alphabet", C.symbol_bits(F.col("alphabet")).alias("bits"))


# The genome study, on letters of line items.

_W1 = [(0, "aaaaaaaa", 2), (1, "gcaacc", 2), (2, "acgttgca", 2), (3, "aaccttgg", 2), (4, "ctcattca", 2)]
_W1_LENGTHS = (510, 483, 485, 481, 485)
_W1_STREAMS = "(SELECT stream_id, least(n, len)::BIGINT AS n, substr(text, 1, len) AS text FROM " + Q.LINES4 + " JOIN (VALUES " + ", ".join(f"({i + 1}, {n})" for i, n in enumerate(_W1_LENGTHS)) + ") v(stream, len) ON stream_id = stream)"


def _w1_streams(t: Tables) -> DataFrame:
    lengths = t.spark.createDataFrame([(i + 1, n) for i, n in enumerate(_W1_LENGTHS)], "stream_id long, len int")
    rows = lines4(t).join(F.broadcast(lengths), "stream_id")
    return rows.select("stream_id", F.least("n", F.col("len").cast("long")).alias("n"), F.substr("text", F.lit(1), F.col("len")).alias("text"))


_W1H = Q.hits(_W1_STREAMS, Q.patterns(_W1))


@query("w1_hit_counts", counts_sql(_W1H, 2))
def _(t):
    return _counts(_w1_streams(t), pats(t, _W1))


@query("w2_coverage", _coverage_sql(_W1H))
def _(t):
    return measures.coverage(hits.find_hits(_w1_streams(t), pats(t, _W1)))


_ANCHORED = f"(SELECT stream_id, length(win)::BIGINT AS n, win AS text FROM (SELECT stream_id, substr(text, greatest(instr(text, 'acgta') - 201, 0) + 1, least(instr(text, 'acgta') - 1, 200) + 205) AS win FROM {Q.LINES4} WHERE instr(text, 'acgta') > 0))"


def around(streams: DataFrame, anchor: str, reach: int) -> DataFrame:
    """The part of each stream from `reach` symbols before an anchor's first exact occurrence to `reach` behind it."""
    at = F.instr("text", F.lit(anchor)) - 1
    rows = streams.where(F.col("text").contains(anchor)).withColumn("low", F.greatest(at - reach, F.lit(0)))
    rows = rows.select("stream_id", F.substr("text", F.col("low") + 1, at - F.col("low") + len(anchor) + reach).alias("text"))
    return rows.select("stream_id", F.char_length("text").cast("long").alias("n"), "text")


@query("w1_anchor_window", counts_sql(Q.hits(_ANCHORED, Q.patterns([(0, "gcaacc", 2)])), 2))
def _(t):
    return _counts(around(lines4(t), "acgta", 200), pats(t, [(0, "gcaacc", 2)]))


_DOC_ANCHORED = f"(SELECT stream_id, length(win)::BIGINT AS n, win AS text FROM (SELECT stream_id, substr(text, greatest(instr(text, ' and the ') - 201, 0) + 1, least(instr(text, ' and the ') - 1, 200) + 209) AS win FROM {Q.docs("true")} WHERE instr(text, ' and the ') > 0))"


@query("w1_doc_window", counts_sql(Q.hits(_DOC_ANCHORED, Q.patterns([(0, "therein", 2)])), 2))
def _(t):
    return _counts(around(docs(t), " and the ", 200), pats(t, [(0, "therein", 2)]))


# Speed tests.

_TEST_TEXT = "ABDCABCCDBADCBA"
SWEEP = [(lp, lp, 3) for lp in (5, 7, 10, 15)]
K_SWEEP = [(10 * lp + k, lp, k) for lp in (5, 15) for k in (2, 3, 4, 5)]
_LIM = Q.cut(Q.LINES16, 3104)


_SEARCHED = f"(SELECT * FROM {_LIM} WHERE stream_id <> 15)"


def test_streams(t: Tables) -> DataFrame:
    """Fifteen streams of the test length; the sixteenth gives the patterns."""
    return S.first_symbols(lines16(t).where("stream_id <> 15"), 3104)


def cut_patterns(t: Tables, wanted) -> DataFrame:
    """Patterns (pattern_id, lp, K) cut from the stream that isn't searched, each at its own place."""
    table = t.spark.createDataFrame([(i, lp, k, 100 + 40 * n) for n, (i, lp, k) in enumerate(wanted)], "pattern_id int, lp int, k_max int, place int")
    given = lines16(t).where("stream_id = 15").select("text")
    return table.join(F.broadcast(given), how="cross").select("pattern_id", F.substr("text", F.col("place") + 1, F.col("lp")).alias("pattern"), "lp", "k_max")


def cut_patterns_sql(wanted) -> str:
    rows = ", ".join(f"({i}, {lp}, {k}, {100 + 40 * n})" for n, (i, lp, k) in enumerate(wanted))
    return f"(SELECT pattern_id, substr(text, place + 1, lp) AS pattern, lp, k_max FROM (VALUES {rows}) v(pattern_id, lp, k_max, place), {Q.LINES16} WHERE stream_id = 15)"


def _summary(found: DataFrame, kept: DataFrame) -> DataFrame:
    raw = found.groupBy("pattern_id").agg(F.count(F.lit(1)).alias("hits"), F.countDistinct("stream_id", F.col("start") + F.col("len")).alias("ends"))
    few = kept.groupBy("pattern_id").agg(F.count(F.lit(1)).alias("kept"), F.max(F.col("decided_at") - F.col("start") + 1).alias("max_delay"))
    return raw.join(few, "pattern_id")


def _summary_sql(hits_sql: str, k: int) -> str:
    return f"""SELECT pattern_id, hits, ends, kept, max_delay FROM (SELECT pattern_id, count(*) AS hits, count(DISTINCT (stream_id, start + len)) AS ends FROM {hits_sql} GROUP BY ALL)
JOIN (SELECT pattern_id, count(*) AS kept, max(decided_at - start + 1) AS max_delay FROM {Q.sift(hits_sql, k)} GROUP BY ALL) USING (pattern_id)"""


def sweep(t: Tables, wanted) -> DataFrame:
    table = S.pattern_frame(t.spark, S.collected(cut_patterns(t, wanted)))
    found = written(hits.find_hits(test_streams(t), table), "hits")
    return _summary(found, sifter.sift_hits(found, max(k for _, _, k in wanted) + 1, number=False))


@query("w3_lp_sweep", _summary_sql(Q.hits(_SEARCHED, cut_patterns_sql(SWEEP)), 3))
def _(t):
    return sweep(t, SWEEP)


@query("w4_k_sweep", _summary_sql(Q.hits(_SEARCHED, cut_patterns_sql(K_SWEEP)), 5))
def _(t):
    return sweep(t, K_SWEEP)


@query("w5_trials", f"SELECT stream_id, count(*) AS kept FROM {Q.sift(Q.hits(Q.cut(Q.LINES100, 3104), Q.patterns([(0, _TEST_TEXT[:7], 3)])), 3)} GROUP BY stream_id")
def _(t):
    kept = sifter.sift(S.first_symbols(lines100(t), 3104), pats(t, [(0, _TEST_TEXT[:7], 3)]), number=False)
    return kept.groupBy("stream_id").agg(F.count(F.lit(1)).alias("kept"))


@query("w6_param_grid", "SELECT bits::INTEGER AS bits, lp::INTEGER AS lp, k::INTEGER AS k, (lp * (lp + k))::BIGINT AS cells_per_symbol, (3 * (k + 1))::INTEGER AS state_numbers, (bits * (lp + k))::BIGINT AS window_bits FROM (VALUES (4), (8), (12), (16)) a(bits), (VALUES (8), (16), (24), (32)) b(lp), range(1, 5) c(k)")
def _(t):
    grid = t.spark.createDataFrame([(b, lp, k) for b in (4, 8, 12, 16) for lp in (8, 16, 24, 32) for k in range(1, 5)], "bits int, lp int, k int")
    lp, k = F.col("lp"), F.col("k")
    return grid.select("bits", "lp", "k", C.dp_cells(F.lit(1), lp, k, "prefix").cast("long").alias("cells_per_symbol"), (3 * (k + 1)).alias("state_numbers"), (F.col("bits") * (lp + k)).cast("long").alias("window_bits"))


# Fields of use.

_SIGNATURES = [(0, "EEEP", 1), (1, "SVCPE", 1)]


@query("w10_signatures_events", f"""SELECT pattern_id, count(*) AS kept, count(*) FILTER (WHERE dist = 0) AS exact, count(DISTINCT stream_id) AS streams FROM {Q.sift(Q.hits(Q.EVENTS, Q.patterns(_SIGNATURES)), 1)} GROUP BY pattern_id""")
def _(t):
    kept = sifter.sift(events(t), pats(t, _SIGNATURES), number=False)
    return kept.groupBy("pattern_id").agg(F.count(F.lit(1)).alias("kept"), F.count_if(F.col("dist") == 0).alias("exact"), F.countDistinct("stream_id").alias("streams"))


_MARKUP = [(0, "<script>", 2), (1, "<style>", 2)]


@query("w10_signatures_pages", f"SELECT pattern_id, count(*) AS kept, count(*) FILTER (WHERE dist = 0) AS exact, count(DISTINCT stream_id) AS streams FROM {Q.sift(Q.hits(Q.pages(), Q.patterns(_MARKUP)), 2)} GROUP BY pattern_id")
def _(t):
    kept = sifter.sift(pages(t), pats(t, _MARKUP), number=False)
    return kept.groupBy("pattern_id").agg(F.count(F.lit(1)).alias("kept"), F.count_if(F.col("dist") == 0).alias("exact"), F.countDistinct("stream_id").alias("streams"))


_KEYWORDS = [(0, "interest", 2), (1, "without", 2)]


@query("w11_retrieval_topk")
def _(t):
    kept = sifter.sift(docs(t), pats(t, _KEYWORDS), number=False)
    return kept.groupBy("stream_id").agg(F.count(F.lit(1)).alias("kept"), F.min("dist").alias("best")).orderBy(F.desc("kept"), "best", "stream_id").limit(10)


_PHRASES = [(0, "please", 2), (1, "thank you", 2)]


_ROLES = "(SELECT role, conv_id AS stream_id, sum(length(text))::BIGINT AS n, string_agg(regexp_replace(lower(text), '[^a-z ]', '?', 'g'), '' ORDER BY turn) AS text FROM conversations GROUP BY role, conv_id)"


def _role_sql() -> str:
    """Each role's turns of a conversation are a stream; its number is the rank of (role, conversation)."""
    named = f"(SELECT *, dense_rank() OVER (ORDER BY role, conv) AS stream_id FROM (SELECT role, stream_id AS conv, n, text FROM {_ROLES}))"
    kept = Q.sift(Q.hits(f"(SELECT stream_id, n, text FROM {named})", Q.patterns(_PHRASES)), 2)
    return f"SELECT role, pattern_id, count(*) AS kept, count(DISTINCT stream_id) AS streams FROM {kept} JOIN (SELECT stream_id, role FROM {named}) USING (stream_id) GROUP BY role, pattern_id"


@query("w12_conversations", _role_sql())
def _(t):
    rows = t.conversations.groupBy("role", "conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "text"))).alias("turns"))
    key = F.xxhash64("role", "conv_id")
    named = rows.select("role", "conv_id", key.alias("key"), S.fold_ascii(F.array_join(F.transform("turns", lambda x: x["text"]), "")).alias("text"))
    kept = sifter.sift(S.text_streams(named, F.col("key"), F.col("text")), pats(t, _PHRASES), number=False)
    return kept.join(named.select("key", "role"), F.col("stream_id") == F.col("key")).groupBy("role", "pattern_id").agg(F.count(F.lit(1)).alias("kept"), F.countDistinct("stream_id").alias("streams"))


_HISTOGRAM = [(0, "the", 0), (1, "ing", 0), (2, "and the", 2)]


@query("w13_histogram_labels")
def _(t):
    vectors = measures.motif_histogram(sifter.sift(docs(t), pats(t, _HISTOGRAM), number=False), pats(t, _HISTOGRAM))
    marked = vectors.join(t.labels, F.col("doc_id") == F.col("stream_id"))
    return marked.groupBy("quality").agg(F.count(F.lit(1)).alias("documents"), *[F.sum(F.col("vector")[i]).alias(f"v{i}") for i in range(3)])


_UPDOWN = "(SELECT user_id AS stream_id, count(*) AS n, string_agg(CASE WHEN value > before THEN 'u' WHEN value < before THEN 'd' ELSE 's' END, '' ORDER BY ts, event_id) AS text FROM (SELECT *, lag(value) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events) WHERE before IS NOT NULL GROUP BY user_id)"


@query("w14_updown_patterns", f"SELECT pattern_id, dist, count(*) AS kept FROM {Q.sift(Q.hits(_UPDOWN, Q.patterns([(0, 'uuuuud', 1), (1, 'udududud', 1)])), 1)} GROUP BY ALL")
def _(t):
    from pyspark.sql.window import Window

    moves = t.events.withColumn("before", F.lag("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))).where("before is not null")
    letter = F.when(F.col("value") > F.col("before"), "u").when(F.col("value") < F.col("before"), "d").otherwise("s")
    kept = sifter.sift(S.build_streams(moves, F.col("user_id"), ("ts", "event_id"), letter), pats(t, [(0, "uuuuud", 1), (1, "udududud", 1)]), number=False)
    return kept.groupBy("pattern_id", "dist").agg(F.count(F.lit(1)).alias("kept"))


@query("w14_embedding_patterns", f"SELECT pattern_id, dist, count(*) AS kept FROM {Q.sift(Q.hits(Q.EMBEDDINGS, Q.patterns([(0, 'abcd', 1), (1, 'ddaadd', 2)])), 2)} GROUP BY ALL")
def _(t):
    kept = sifter.sift(embeddings(t), pats(t, [(0, "abcd", 1), (1, "ddaadd", 2)]), number=False)
    return kept.groupBy("pattern_id", "dist").agg(F.count(F.lit(1)).alias("kept"))


# The patterns of the worked examples, in the letters of line items and orders.

_EXAMPLE = Q.hits(Q.LINES_ABCD, Q.patterns([(0, "ACBDA", 2)]))


@query("example_matrix", Q.all_of(Q.hits(Q.LINES_ABCD, Q.patterns([(0, "ABCD", 1)]))))
def _(t):
    return hits.find_hits(lines_abcd(t), pats(t, [(0, "ABCD", 1)]), kernel="native")


for _tie in sifter.TIES:
    query(f"example_sift_{_tie}", Q.all_of(Q.sift(_EXAMPLE, 2, tie=_tie)))(lambda t, tie=_tie: sifter.sift(lines_abcd(t), pats(t, [(0, "ACBDA", 2)]), tie=tie))


@query("example_chain", Q.all_of(Q.sift(Q.hits(Q.ORDERS_ABC, Q.patterns([(0, "AAAA", 2)])), 2)))
def _(t):
    return sifter.sift(orders_abc(t), pats(t, [(0, "AAAA", 2)]))


