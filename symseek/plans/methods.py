"""Queries for the methods, their variants and the baselines."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from symseek.functions import distance as D
from symseek.functions import kernels
from symseek.operators import baselines, hits, measures, resync, sifter
from symseek.plans import sqltext as Q
from symseek.plans.registry import Tables, query
from symseek.sources import streams as S
from symseek.sources.scratch import written

LINE_ORDER = ("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
EV_PATTERNS = [(0, "SVCPE", 1), (1, "SVCPE", 2), (2, "EEEP", 1), (3, "CVPSEC", 2)]
LI_PATTERNS = [(0, "acgtacgt", 2), (1, "gcaacc", 2)]
MIXED = [(0, "SVC", 0), (1, "EEEP", 1), (2, "CVPSEC", 2), (3, "VVSPECSE", 3)]
DOC_PATTERNS = [(0, "interesting", 2), (1, "therefore", 2), (2, "the and attion", 3)]


# Streams on the given tables.


def events(t: Tables) -> DataFrame:
    return S.build_streams(t.events, F.col("user_id"), ("ts", "event_id"), F.upper(F.substring("event_type", 1, 1)))


def events_all(t: Tables) -> DataFrame:
    return S.build_streams(t.events, F.lit(0), ("ts", "event_id"), F.upper(F.substring("event_type", 1, 1)))


def event_blocks(t: Tables, halo: int, block: int = 1 << 16) -> DataFrame:
    """The one stream of all events, in blocks; it is never in one row."""
    return S.build_blocks(t.events, F.lit(0), ("ts", "event_id"), F.upper(F.substring("event_type", 1, 1)), block=block, halo=halo)


def _letter(letters: str):
    return F.substr(F.lit(letters), F.col("l_quantity").cast("int") % 4 + 1, F.lit(1))


def lines4(t: Tables) -> DataFrame:
    return S.build_streams(t.lineitem, F.col("l_suppkey"), LINE_ORDER, _letter("acgt"))


def lines_abcd(t: Tables) -> DataFrame:
    return S.build_streams(t.lineitem, F.col("l_suppkey"), LINE_ORDER, _letter("ABCD"))


def lines16(t: Tables) -> DataFrame:
    return S.build_streams(t.lineitem, F.col("l_suppkey") % 16, LINE_ORDER, _letter("ABCD"))


def lines100(t: Tables) -> DataFrame:
    return S.build_streams(t.lineitem, F.col("l_suppkey") % 100, LINE_ORDER, _letter("ABCD"))


def lines6(t: Tables) -> DataFrame:
    pair = F.concat("l_returnflag", "l_linestatus")
    return S.build_streams(t.lineitem, F.col("l_partkey"), LINE_ORDER, F.substr(F.lit("ABCDEF"), (F.floor(F.instr(F.lit("AFANRFRNAONO"), pair) / 2) + 1).cast("int"), F.lit(1)))


def orders(t: Tables) -> DataFrame:
    return S.build_streams(t.orders, F.col("o_custkey"), ("o_orderdate", "o_orderkey"), F.col("o_orderstatus"))


def orders_abc(t: Tables) -> DataFrame:
    return S.build_streams(t.orders, F.col("o_custkey"), ("o_orderdate", "o_orderkey"), F.translate("o_orderstatus", "FOP", "ABC"))


def priorities(t: Tables) -> DataFrame:
    return S.build_streams(t.orders, F.col("o_custkey"), ("o_orderdate", "o_orderkey"), F.substring("o_orderpriority", 1, 1))


def docs(t: Tables, where: str = "true") -> DataFrame:
    return S.text_streams(t.documents.where(where), F.col("doc_id"), S.fold_ascii(F.col("text")))


def pages(t: Tables) -> DataFrame:
    return S.text_streams(t.pages, F.col("page_id"), S.fold_printable(F.col("html")))


def conversations(t: Tables) -> DataFrame:
    turns = t.conversations.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "text"))).alias("turns"))
    return S.text_streams(turns, F.col("conv_id"), S.fold_ascii(F.array_join(F.transform("turns", lambda x: x["text"]), "")))


def embeddings(t: Tables) -> DataFrame:
    letter = lambda x: F.when(x < -0.1, "a").when(x < 0, "b").when(x < 0.1, "c").otherwise("d")
    return S.text_streams(t.embeddings, F.col("vec_id"), F.array_join(F.transform("embedding", letter), ""))


def pats(t: Tables, rows) -> DataFrame:
    return S.pattern_frame(t.spark, rows)


EV, LI = Q.EVENTS, Q.LINES4
EVP, LIP = Q.patterns(EV_PATTERNS), Q.patterns(LI_PATTERNS)
EVH, LIH = Q.hits(EV, EVP), Q.hits(LI, LIP)
ONE = Q.patterns([(1, "SVCPE", 2)])


def ev_hits(t: Tables) -> DataFrame:
    return hits.find_hits(events(t), pats(t, EV_PATTERNS))


def ev_kept(t: Tables, **options) -> DataFrame:
    return sifter.sift(events(t), pats(t, EV_PATTERNS), **options)


# Distances.


@query("edit_distance", "SELECT stream_id, levenshtein('SVCPE', text)::INTEGER AS dist FROM " + EV)
def _(t):
    return events(t).select("stream_id", D.edit_distance(F.lit("SVCPE"), F.col("text")).alias("dist"))


@query("edit_within", "SELECT stream_id, CASE WHEN d <= 5 THEN d END AS dist FROM (SELECT stream_id, levenshtein('SVCPE', text)::INTEGER AS d FROM " + EV + ")")
def _(t):
    return events(t).select("stream_id", D.edit_distance_within(F.lit("SVCPE"), F.col("text"), 5).alias("dist"))


@query("dp_last_row", "SELECT stream_id, m::INTEGER AS m, levenshtein('CVPSEC', substr(text, 1, m::BIGINT))::INTEGER AS dist FROM (SELECT *, unnest(range(0, n + 1)) AS m FROM " + EV + ")")
def _(t):
    return events(t).select("stream_id", F.posexplode(D.dp_last_row(F.lit("CVPSEC"), F.col("text"))).alias("m", "dist"))


@query("dp_matrix", f"SELECT stream_id, a.n::INTEGER AS n, m::INTEGER AS m, levenshtein(substr('ABCD', 1, a.n), substr(text, 1, m::BIGINT))::INTEGER AS c FROM (SELECT stream_id, text, unnest(range(0, n + 1)) AS m FROM {Q.ORDERS_ABC}), range(0, 5) a(n)")
def _(t):
    return D.dp_matrix(orders_abc(t).withColumn("pattern", F.lit("ABCD")), "pattern", "text", "stream_id")


_PREFIX_SQL = f"""SELECT stream_id, start, l::INTEGER AS len, levenshtein('SVCPE', substr(text, (start + 1)::BIGINT, l::BIGINT))::INTEGER AS dist
FROM (SELECT *, unnest(range(3, 8)) AS l FROM (SELECT *, unnest(range(0, n - 6)) AS start FROM {EV}))"""


@query("prefix_distances", _PREFIX_SQL)
def _(t):
    rows = events(t).where("n > 6").select("stream_id", "text", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 7)).alias("start"))
    return rows.select("stream_id", "start", F.inline(D.prefix_distances(F.col("text"), F.col("start"), F.lit("SVCPE"), 2)))


def _by_wavefront(t: Tables, kernel: str) -> DataFrame:
    """Distances above the threshold too: with K as large as the pattern's length, no distance of the band is beyond it."""
    found = hits.find_hits(events(t), pats(t, [(0, "SVCPE", 7)]), kernel=kernel).where("len between 3 and 7")
    whole = events(t).select("stream_id", "n")
    return found.join(whole, "stream_id").where("start < n - 6").select("stream_id", "start", "len", "dist")


@query("wavefront", _PREFIX_SQL)
def _(t):
    return _by_wavefront(t, "wavefront")


@query("wavefront_by_counter", _PREFIX_SQL)
def _(t):
    return _by_wavefront(t, "counter")


@query("find_hits_wavefront", Q.all_of(EVH))
def _(t):
    return hits.find_hits(events(t), pats(t, EV_PATTERNS), kernel="wavefront")


@query("find_hits_counter", Q.all_of(EVH))
def _(t):
    return hits.find_hits(events(t), pats(t, EV_PATTERNS), kernel="counter")


@query("slide_windows", f"SELECT stream_id, start, rpad(substr(text, (start + 1)::BIGINT, 7), 7, '') AS win FROM (SELECT *, unnest(range(0, n)) AS start FROM {EV})")
def _(t):
    return S.slide_windows(events(t), 7)


# Hits.


@query("find_hits_events", Q.all_of(EVH))
def _(t):
    return ev_hits(t)


@query("find_hits_native", Q.all_of(EVH))
def _(t):
    return hits.find_hits(events(t), pats(t, EV_PATTERNS), kernel="native")


@query("find_hits_li4", Q.all_of(LIH))
def _(t):
    return hits.find_hits(lines4(t), pats(t, LI_PATTERNS))


@query("find_hits_docs")
def _(t):
    return hits.find_hits(docs(t), pats(t, DOC_PATTERNS))


@query("blocked_hits_equal", Q.all_of(LIH))
def _(t):
    return hits.find_hits(lines4(t), pats(t, LI_PATTERNS), block=64)


def _rule_sql(condition: str) -> str:
    return f"""WITH h AS MATERIALIZED {Q.hits(EV, ONE)}
SELECT a.stream_id, a.start AS start_a, a.len AS len_a, a.dist AS dist_a, b.start AS start_b, b.len AS len_b, b.dist AS dist_b
FROM h a JOIN h b ON a.stream_id = b.stream_id AND a.start <= b.start + b.len - 1 AND b.start <= a.start + a.len - 1 WHERE {condition}"""


def overlapping(found: DataFrame, width: int = 64) -> DataFrame:
    """Pairs of overlapping hits of a stream and pattern: an equi-join on the buckets of positions that both touch, each pair from its first common bucket."""
    last = F.col("start") + F.col("len") - 1
    rows = found.select("stream_id", "pattern_id", "start", "len", "dist", F.explode(F.sequence(F.floor(F.col("start") / width), F.floor(last / width))).alias("bucket"))
    a, b = (rows.select("stream_id", "pattern_id", "bucket", *[F.col(c).alias(f"{c}_{x}") for c in ("start", "len", "dist")]) for x in "ab")
    both = a.join(b, ["stream_id", "pattern_id", "bucket"])
    meet = (F.col("start_a") <= F.col("start_b") + F.col("len_b") - 1) & (F.col("start_b") <= F.col("start_a") + F.col("len_a") - 1)
    return both.where(meet & (F.col("bucket") == F.floor(F.greatest("start_a", "start_b") / width))).drop("bucket", "pattern_id")


def _rule(t: Tables, condition: str) -> DataFrame:
    return overlapping(hits.find_hits(events(t), pats(t, [(1, "SVCPE", 2)]))).where(condition)


@query("rule_r1_pairs", _rule_sql("b.dist < a.dist AND b.start >= a.start"))
def _(t):
    return _rule(t, "dist_b < dist_a and start_b >= start_a")


@query("rule_r2_pairs", _rule_sql("b.dist = a.dist AND b.start > a.start"))
def _(t):
    return _rule(t, "dist_b = dist_a and start_b > start_a")


@query("rule_r3_pairs", _rule_sql("b.dist = a.dist AND b.start = a.start AND b.len > a.len"))
def _(t):
    return _rule(t, "dist_b = dist_a and start_b = start_a and len_b > len_a")


@query("overlap_pairs", _rule_sql("a.start < b.start OR (a.start = b.start AND a.len < b.len)"))
def _(t):
    return _rule(t, "start_a < start_b or (start_a = start_b and len_a < len_b)")


@query("shadow_islands", Q.all_of(Q.islands(EVH)))
def _(t):
    return sifter.split_islands(written(ev_hits(t), "hits"), block=16)


@query("shadow_islands_window", Q.all_of(Q.islands(EVH)))
def _(t):
    return sifter.islands_by_window(ev_hits(t))


# The sifter and its variants.

_OPTIONS = {
    "online_sift_events": {},
    "online_sift_shortest": {"tie": "shortest"},
    "online_sift_latest": {"tie": "latest"},
    "online_sift_lastlen": {"validation": "last_length"},
    "online_sift_interval": {"validation": "interval"},
    "online_sift_touching": {"strict": False},
    "online_sift_interval_touching": {"validation": "interval", "strict": False, "tie": "latest"},
}
for _name, _options in _OPTIONS.items():
    query(_name, Q.all_of(Q.sift(EVH, 2, **_options)))(lambda t, options=_options: ev_kept(t, **options))
for _engine in ("serial", "iterator", "auto", "kernel", "native", "resync"):
    query(f"{_engine}_engine", Q.all_of(Q.sift(EVH, 2)))(lambda t, engine=_engine: ev_kept(t, engine=engine))


@query("online_sift_li4", Q.all_of(Q.sift(LIH, 2)))
def _(t):
    return sifter.sift(lines4(t), pats(t, LI_PATTERNS))


_DENSE = [(0, "acgta", 3)]


@query("resync_fold", "SELECT stream_id, pattern_id, start, len, dist, decided_at FROM " + Q.sift(Q.hits(LI, Q.patterns(_DENSE)), 3))
def _(t):
    return resync.resync_fold(hits.find_hits(lines4(t), pats(t, _DENSE)), 4, width=50)


@query("kernel_engine_blocks", Q.all_of(Q.sift(LIH, 2, tie="shortest", validation="interval")))
def _(t):
    return sifter.sift(lines4(t), pats(t, LI_PATTERNS), engine="kernel", block=40, tie="shortest", validation="interval")


@query("sift_one_stream_blocks", Q.all_of(Q.sift(Q.hits(Q.EVENTS_ALL, Q.patterns([(0, "SVCPE", 2), (1, "EEEP", 1)])), 2, tie="shortest")))
def _(t):
    return sifter.sift(event_blocks(t, 6, block=97), pats(t, [(0, "SVCPE", 2), (1, "EEEP", 1)]), tie="shortest", giant=20)


@query("online_sift_orders", Q.all_of(Q.sift(Q.hits(Q.ORDERS, Q.patterns([(0, "FOF", 1), (1, "OOPF", 1)])), 1)))
def _(t):
    return sifter.sift(orders(t), pats(t, [(0, "FOF", 1), (1, "OOPF", 1)]))


@query("online_sift_priorities", Q.all_of(Q.sift(Q.hits(Q.PRIORITIES, Q.patterns([(0, "1234", 1)])), 1)))
def _(t):
    return sifter.sift(priorities(t), pats(t, [(0, "1234", 1)]))


@query("online_sift_docs")
def _(t):
    return sifter.sift(docs(t), pats(t, DOC_PATTERNS))


@query("online_sift_parts", Q.all_of(Q.sift(Q.hits(Q.LINES6, Q.patterns([(0, "BCFA", 1)])), 1)))
def _(t):
    return sifter.sift(lines6(t), pats(t, [(0, "BCFA", 1)]))


_PAGE_PATTERNS = [(0, "<article", 1), (1, "</footer", 2)]


@query("online_sift_pages", Q.all_of(Q.sift(Q.hits(Q.pages(), Q.patterns(_PAGE_PATTERNS)), 2)))
def _(t):
    return sifter.sift(pages(t), pats(t, _PAGE_PATTERNS))


@query("bank_sift_events", Q.all_of(Q.sift(Q.hits(Q.EVENTS_ALL, Q.patterns([(i, p, 1) for i, p in enumerate(("SVCPE", "EEEP", "CVPSEC", "PPPP"))])), 1)))
def _(t):
    return sifter.sift_bank(event_blocks(t, 8), pats(t, [(i, p, 1) for i, p in enumerate(("SVCPE", "EEEP", "CVPSEC", "PPPP"))]))


@query("bank_mixed_k", Q.all_of(Q.sift(Q.hits(EV, Q.patterns(MIXED)), 3)))
def _(t):
    return sifter.sift_bank(events(t), pats(t, MIXED))


def _bank(t: Tables) -> DataFrame:
    return S.pattern_bank(t.benchmark, F.col("item_id"), S.fold_ascii(F.col("text")), 16, 4)


@query("bank_sift_docs40")
def _(t):
    return sifter.sift_bank(docs(t), _bank(t))


@query("w7_bank40")
def _(t):
    kept = sifter.sift_bank(docs(t), _bank(t), validation="interval")
    return kept.groupBy("pattern_id").agg(F.count(F.lit(1)).alias("kept"), F.min("dist").alias("best"))


@query("pack_results", "SELECT stream_id, pattern_id, start * 256 + dist * 32 + len AS packed, start, len, dist FROM " + Q.sift(EVH, 2))
def _(t):
    packed = ev_kept(t).select("stream_id", "pattern_id", measures.pack_result(F.col("start"), F.col("len"), F.col("dist")).alias("packed"))
    return packed.select("*", measures.unpack_result(F.col("packed")).alias("r")).select("stream_id", "pattern_id", "packed", "r.start", "r.len", "r.dist")


def _histogram_sql(kept: str, ids) -> str:
    return f"SELECT stream_id, [{', '.join(f'count(*) FILTER (WHERE pattern_id = {i})' for i in ids)}] AS vector FROM {kept} GROUP BY stream_id"


@query("motif_histogram_events", _histogram_sql(Q.sift(EVH, 2), range(4)))
def _(t):
    return measures.motif_histogram(ev_kept(t), pats(t, EV_PATTERNS))


@query("motif_histogram_docs")
def _(t):
    return measures.motif_histogram(sifter.sift(docs(t), pats(t, DOC_PATTERNS)), pats(t, DOC_PATTERNS))


# Other distances and classes of search.


@query("hamming_hits", f"SELECT * FROM (SELECT stream_id, 1 AS pattern_id, start, 5 AS len, hamming('SVCPE', substr(text, (start + 1)::BIGINT, 5))::INTEGER AS dist FROM (SELECT *, unnest(range(0, n - 4)) AS start FROM {EV})) WHERE dist <= 2")
def _(t):
    return hits.hamming_hits(events(t), pats(t, [(1, "SVCPE", 2)]))


@query("indel_distance", f"""WITH RECURSIVE s AS (SELECT stream_id, n, text FROM {EV}),
sub AS (SELECT bits, array_to_string(list_transform(list_filter(range(0, 5), lambda i: (bits >> i) & 1 = 1), lambda i: substr('SVCPE', i + 1, 1)), '') AS part FROM range(32) b(bits)),
best AS (SELECT stream_id, n, max(length(part)) AS common FROM s, sub WHERE regexp_matches(text, array_to_string(list_transform(string_split(part, ''), lambda c: c), '.*')) GROUP BY stream_id, n)
SELECT stream_id, (5 + n - 2 * common)::INTEGER AS dist FROM best""")
def _(t):
    return events(t).select("stream_id", D.indel_distance(F.lit("SVCPE"), F.col("text")).cast("int").alias("dist"))


@query("episode_hits", f"""SELECT stream_id, 1 AS pattern_id, start, len::INTEGER AS len, (len - 4)::INTEGER AS dist FROM (
  SELECT *, substr(text, (start + 1)::BIGINT, len::BIGINT) AS sub FROM (SELECT *, unnest(range(4, least(7, n - start + 1))) AS len FROM (SELECT *, unnest(range(0, n - 3)) AS start FROM {EV})))
WHERE regexp_full_match(sub, 'S.*V.*C.*P')""")
def _(t):
    return hits.episode_hits(events(t), pats(t, [(1, "SVCP", 2)]))


@query("ends_automaton", Q.all_of(Q.ends(EVH)))
def _(t):
    return baselines.free_start_ends(events(t), pats(t, EV_PATTERNS), kernel="automaton", block=32)


@query("ends_bitparallel", Q.all_of(Q.ends(EVH)))
def _(t):
    return baselines.free_start_ends(events(t), pats(t, EV_PATTERNS), kernel="bits", block=32)


@query("hits_prefiltered", Q.all_of(LIH))
def _(t):
    return hits.hits_prefiltered(lines4(t), pats(t, LI_PATTERNS), block=128)


@query("hits_qgram_index", Q.all_of(LIH))
def _(t):
    streams = lines4(t)
    return hits.hits_qgram_index(streams, pats(t, LI_PATTERNS), hits.qgram_index(streams, 2), 2)


@query("exact_hits", f"SELECT stream_id, 0 AS pattern_id, start, 3 AS len, 0 AS dist FROM (SELECT *, unnest(range(0, n)) AS start FROM {EV}) WHERE substr(text, (start + 1)::BIGINT, 3) = 'SVC'")
def _(t):
    return hits.exact_hits(events(t), pats(t, [(0, "SVC", 2)]))


# Baselines.

_TEN = "(SELECT * FROM " + EV + " WHERE stream_id < 10)"
_ALL_SUBS = f"""SELECT stream_id, 1 AS pattern_id, start, len::INTEGER AS len, dist FROM (
  SELECT *, levenshtein('SVCPE', substr(text, (start + 1)::BIGINT, len::BIGINT))::INTEGER AS dist FROM (
    SELECT *, unnest(range(1, n - start + 1)) AS len FROM (SELECT *, unnest(range(0, n)) AS start FROM {EV}))) WHERE dist <= 2"""


@query("exhaustive_small", _ALL_SUBS)
def _(t):
    return hits.exhaustive_hits(events(t), pats(t, [(1, "SVCPE", 2)]), materialize=True)


@query("exhaustive_fused", _ALL_SUBS)
def _(t):
    return hits.exhaustive_hits(events(t), pats(t, [(1, "SVCPE", 2)]))


@query("free_start_ends_events", Q.all_of(Q.ends(EVH)))
def _(t):
    return baselines.free_start_ends(events(t), pats(t, EV_PATTERNS))


@query("free_start_ends_native", Q.all_of(Q.ends(EVH)))
def _(t):
    return baselines.free_start_ends(events(t), pats(t, EV_PATTERNS), kernel="native")


@query("free_start_ends_li4", Q.all_of(Q.ends(LIH)))
def _(t):
    return baselines.free_start_ends(lines4(t), pats(t, LI_PATTERNS))


@query("free_start_intervals", f"SELECT stream_id, pattern_id, start, len, dist FROM (SELECT *, row_number() OVER (PARTITION BY stream_id, pattern_id, start + len ORDER BY dist, len) AS nth FROM {EVH}) WHERE nth = 1")
def _(t):
    return baselines.baseline_counts(events(t), pats(t, EV_PATTERNS))


@query("offline_island_best", f"SELECT stream_id, pattern_id, start, len, dist FROM (SELECT *, row_number() OVER (PARTITION BY stream_id, pattern_id, island ORDER BY dist, start, len) AS nth FROM {Q.islands(EVH)}) WHERE nth = 1")
def _(t):
    return baselines.offline_filter(ev_hits(t), "island_best")


def _pick_sql(order: str) -> str:
    """Take hits in an order, one a step; each drops the later ones that it overlaps."""
    return f"""WITH RECURSIVE h AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY stream_id, pattern_id ORDER BY {order}) AS r FROM {EVH}),
x AS (
  SELECT stream_id, pattern_id, 0::BIGINT AS r, []::STRUCT(s BIGINT, e BIGINT)[] AS kept, NULL::BIGINT AS start, NULL::INTEGER AS len, NULL::INTEGER AS dist FROM (SELECT DISTINCT stream_id, pattern_id FROM h)
  UNION ALL
  SELECT stream_id, pattern_id, r, CASE WHEN good THEN list_append(kept, struct_pack(s := hs, e := he)) ELSE kept END, CASE WHEN good THEN hs END, hl, hd FROM (
    SELECT *, len(list_filter(kept, lambda k: k.s <= he AND hs <= k.e)) = 0 AS good FROM (
      SELECT x.stream_id, x.pattern_id, h.r, x.kept, h.start AS hs, h.start + h.len - 1 AS he, h.len AS hl, h.dist AS hd FROM x JOIN h ON h.stream_id = x.stream_id AND h.pattern_id = x.pattern_id AND h.r = x.r + 1))
)
SELECT stream_id, pattern_id, start, len, dist FROM x WHERE start IS NOT NULL"""


@query("offline_greedy", _pick_sql("dist, start, len"))
def _(t):
    return baselines.offline_filter(ev_hits(t), "greedy")


@query("offline_max_disjoint", _pick_sql("start + len, start, len"))
def _(t):
    return baselines.offline_filter(ev_hits(t), "max_disjoint")
