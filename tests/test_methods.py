"""Worked examples, option matrix, invariants and edges of the methods."""

import itertools
import random
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import reference
from symseek.functions import distance as D
from symseek.functions import kernels
from symseek.functions.costmodel import resource_fit
from symseek.operators import baselines, fold, hits, measures, resync, sifter
from symseek.sources import scratch
from symseek.sources import streams as S


def streams(spark, *texts):
    return spark.createDataFrame([(i, None if x is None else len(x), x) for i, x in enumerate(texts)], "stream_id long, n long, text string")


def rows(df, *columns):
    return sorted(tuple(r[c] for c in columns) for r in df.collect())


def kept(df):
    return rows(df, "start", "len", "dist")


def random_texts(seed, count, size, letters="AB"):
    rng = random.Random(seed)
    return ["".join(rng.choice(letters) for _ in range(rng.randint(1, size))) for _ in range(count)]


def test_matrix_example(spark):
    pairs = spark.createDataFrame([("ABCD", s) for s in ("ABB", "ABBD", "ABBDA")], "p string, s string")
    assert rows(pairs.select("s", D.edit_distance(F.col("p"), F.col("s")).alias("d")), "s", "d") == [("ABB", 2), ("ABBD", 1), ("ABBDA", 2)]
    last = pairs.where("s = 'ABBDA'").select(D.dp_last_row(F.col("p"), F.col("s")).alias("r")).first()[0]
    assert last == [4, 3, 2, 2, 1, 2]
    for kernel in ("native", "arrow"):
        found = hits.find_hits(streams(spark, "ABBDABCDACDB"), S.pattern_frame(spark, [(0, "ABCD", 1)]), kernel=kernel)
        assert kept(found) == [(0, 4, 1), (3, 5, 1), (4, 3, 1), (4, 4, 0), (4, 5, 1), (5, 3, 1), (8, 3, 1)]


@pytest.mark.parametrize(("tie", "strict", "expected"), [("shortest", True, [(3, 3, 2), (10, 5, 0)]), ("earliest", True, [(1, 5, 2), (10, 5, 0)]), ("latest", True, [(10, 5, 0)]), ("latest", False, [(5, 5, 2), (10, 5, 0)])])
def test_online_example(spark, tie, strict, expected):
    table = S.pattern_frame(spark, [(0, "ACBDA", 2)])
    for validation in sifter.VALIDATIONS:
        assert kept(sifter.sift(streams(spark, "CCCCDACCBDACBDAA"), table, tie=tie, strict=strict, validation=validation)) == expected


def test_online_example_ends(spark):
    one, table = streams(spark, "CCCCDACCBDACBDAA"), S.pattern_frame(spark, [(0, "ACBDA", 2)])
    assert hits.find_hits(one, table).count() == 26
    for kernel in ("native", "columns", "bits", "automaton"):
        ends = baselines.free_start_ends(one, table, kernel=kernel, block=7)
        assert rows(ends, "end", "dist") == [(5, 2), (9, 2), (10, 1), (11, 2), (12, 2), (13, 1), (14, 0), (15, 1)]


def test_chain_and_validation_examples(spark):
    def run(p, text, k, **options):
        return kept(sifter.sift(streams(spark, text), S.pattern_frame(spark, [(0, p, k)]), **options))

    assert run("AAAA", "BABABAAAAB", 2) == [(0, 4, 2), (5, 4, 0)]
    assert run("ABAA", "AABABAABBA", 3) == [(0, 2, 2), (3, 4, 0), (7, 3, 2)]
    assert run("ABAA", "AABABAABBA", 3, validation="last_length") == [(0, 1, 3), (0, 2, 2), (3, 4, 0), (7, 3, 2)]
    assert run("BBAB", "ABAABBABAA", 3) == [(0, 1, 3), (0, 2, 2), (4, 4, 0), (8, 1, 3), (9, 1, 3)]
    assert run("BBAB", "ABAABBABAA", 3, validation="interval") == [(0, 2, 2), (4, 4, 0), (8, 1, 3), (9, 1, 3)]
    assert run("BAAB", "BBBAABAABA", 2, validation="interval") == [(2, 4, 0), (6, 3, 1)]
    assert run("BAAB", "BBBAABAABA", 2, validation="interval", strict=False) == [(0, 2, 2), (2, 4, 0), (6, 3, 1)]


@pytest.mark.parametrize(("p", "text", "k", "count", "expected"), [("AB", "XYZ", 2, 5, [(0, 1, 2), (1, 1, 2), (2, 1, 2)]), ("ABA", "ABABABA", 0, 3, [(0, 3, 0), (4, 3, 0)]), ("AAA", "AAAAAAA", 1, 15, [(0, 3, 0), (3, 3, 0)])])
def test_edges(spark, p, text, k, count, expected):
    one, table = streams(spark, text), S.pattern_frame(spark, [(0, p, k)])
    assert hits.find_hits(one, table).count() == hits.find_hits(one, table, kernel="native").count() == count
    assert kept(sifter.sift(one, table)) == expected


def test_empty_null_and_reserved(spark):
    table = S.pattern_frame(spark, [(0, "AB", 1)])
    assert sifter.sift(streams(spark, ""), table).count() == 0
    texts = spark.createDataFrame([(1, None), (2, "AB")], "id long, t string")
    assert S.text_streams(texts, F.col("id"), F.col("t")).count() == 1
    with pytest.raises(Exception, match="reserved"):
        S.checked(streams(spark, "A" + S.FILLER)).collect()
    for bad in ([(0, "", 1)], [(0, "A", -1)], [(0, S.STOP, 1)]):
        with pytest.raises(ValueError):
            S.pattern_frame(spark, bad)
    with pytest.raises(ValueError):
        sifter.Rules(tie="none")
    twice = spark.createDataFrame([(1, 1, "A"), (1, 1, "B")], "s long, at long, sym string")
    with pytest.raises(Exception, match="same order key"):
        S.build_streams(twice, F.col("s"), ("at",), F.col("sym"), unique_order=True).collect()


def test_option_matrix(spark):
    """All ties, validations and strictness, thresholds 0 to 3, against the symbol-by-symbol reference; array, iterator and serial folds."""
    texts = random_texts(7, 60, 24)
    all_streams = streams(spark, *texts)
    for k, p in ((0, "ABA"), (1, "ABBA"), (2, "AABB"), (3, "ABAA")):
        found = hits.find_hits(all_streams, S.pattern_frame(spark, [(0, p, k)])).persist()
        for tie, validation, strict in itertools.product(sifter.TIES, sifter.VALIDATIONS, (True, False)):
            expected = sorted((i, *r) for i, t in enumerate(texts) for r in reference.sift(p, t, k, tie, validation, strict))
            engine = {"earliest": "native", "shortest": "iterator", "latest": "serial"}[tie] if strict else {"earliest": "resync", "shortest": "auto", "latest": "auto"}[tie]
            got = sifter.sift_hits(found, k + 1, tie=tie, validation=validation, strict=strict, engine=engine, number=False, giant=9)
            assert rows(got, "stream_id", "start", "len", "dist") == expected, (k, tie, validation, strict)
            if strict:
                block = {"accumulated": 9, "last_length": 14, "interval": 1 << 16}[validation]
                got = sifter.sift(all_streams, S.pattern_frame(spark, [(0, p, k)]), tie=tie, validation=validation, engine="kernel", block=block, number=False, giant=9)
                assert rows(got, "stream_id", "start", "len", "dist") == expected, (k, tie, validation, block)
        found.unpersist()


def test_giant_islands(spark):
    """Whole streams as one island, folded in blocks that repair each other."""
    texts = random_texts(21, 6, 160)
    found = hits.find_hits(streams(spark, *texts), S.pattern_frame(spark, [(0, "ABA", 3)]))
    for tie, width in (("earliest", 11), ("shortest", 30)):
        expected = sorted((i, *r) for i, t in enumerate(texts) for r in reference.sift("ABA", t, 3, tie))
        assert rows(resync.resync_fold(found, 4, width=width, tie=tie), "stream_id", "start", "len", "dist") == expected


def test_kernels_agree():
    rng = random.Random(3)
    for _ in range(200):
        p, s = ("".join(rng.choice("ABC") for _ in range(rng.randint(1, 9))) for _ in range(2))
        a, b = kernels.encode(p), kernels.encode(s)
        exact = [reference.distance(p, s[:m]) for m in range(len(s) + 1)]
        assert kernels.wavefront_last_row(a, b).tolist() == exact
        assert kernels.wavefront_last_row(a, b, by_counter=True).tolist() == exact
        k = rng.randint(0, 4)
        ends = [min(reference.distance(p, s[i : m + 1]) for i in range(m + 2)) for m in range(len(s))]
        assert kernels.free_start_row(a, b[None])[0].tolist() == ends
        assert kernels.bit_parallel_row(a, b[None])[0].tolist() == ends
        assert kernels.automaton_row(a, b[None], k)[0].tolist() == [min(e, k + 1) for e in ends]
        codes, at, size = kernels.joined([s], len(p) + k)
        lengths, dist = kernels.band_distances(codes, at[0] + np.arange(size[0]), a, k)
        for by_counter in (False, True):
            assert kernels.wavefront_distances(codes, at[0] + np.arange(size[0]), a, k, by_counter=by_counter)[1].tolist() == dist.tolist()
        for start in range(len(s)):
            for length, d in zip(lengths, dist[:, start], strict=True):
                if start + length <= len(s):
                    assert d == min(reference.distance(p, s[start : start + length]), k + 1)


def test_bank_fills_matrices_at_hits_only(monkeypatch):
    """The starts that are found for many patterns together are those of the banded matrices, and no other matrix is filled."""
    rng = random.Random(3)
    text = "".join(rng.choice("abc") for _ in range(3000))
    filled, original = [], kernels.band_distances
    for lp, k in ((3, 1), (8, 2), (9, 0), (16, 4), (40, 6), (64, 3)):
        bank = [text[at : at + lp // 2] + "d" + text[at + lp // 2 + 1 : at + lp] for at in range(0, 2900, 700)] + ["d" * lp]
        codes, _, _ = kernels.joined([text], lp + k)
        near = {}
        for p in bank:
            _, dist = original(codes, np.arange(len(text)), kernels.encode(p), k)
            near[p] = np.flatnonzero((dist <= k).any(0)).tolist()
        monkeypatch.setattr(kernels, "band_distances", lambda codes, starts, pattern, k: (filled.append(len(starts)), original(codes, starts, pattern, k))[1])
        filled.clear()
        batch = pa.RecordBatch.from_arrays([pa.array([5]), pa.array([0]), pa.array([len(text)], pa.int32()), pa.array([text])], names=["stream_id", "base", "own", "text"])
        found = list(hits._kernel_arrays(iter([batch]), {(lp, k): [(i, kernels.encode(p)) for i, p in enumerate(bank)]}, 1, kernels.band_distances))
        starts = {i: sorted(set(start.tolist())) for _, _, i, start, _, _ in found}
        assert all(set(starts.get(i, [])) <= set(near[p]) and {s for s in near[p] if s + lp + k <= len(text)} <= set(starts.get(i, [])) for i, p in enumerate(bank))
        assert sum(filled) == sum(len(near[p]) for p in bank) and sum(filled) < len(bank) * len(text)
        monkeypatch.setattr(kernels, "band_distances", original)


def test_bank_takes_its_patterns_together(monkeypatch):
    """A bank's matrices are filled in one call for all patterns of a chunk, and the pass over each symbol and pattern isn't needed where grams leave few starts."""
    rng = random.Random(4)
    text = "".join(rng.choice("abcdefghijklmnop ") for _ in range(4000))
    bank = [(i, kernels.encode(text[90 * i : 90 * i + 16]), 4) for i in range(40)]
    calls, original = Counter(), (kernels.band_distances, kernels.hit_starts)
    monkeypatch.setattr(kernels, "band_distances", lambda *a: (calls.update(["matrices"]), original[0](*a))[1])
    monkeypatch.setattr(kernels, "hit_starts", lambda *a: (calls.update(["pass"]), original[1](*a))[1])
    batch = pa.RecordBatch.from_arrays([pa.array([5, 6]), pa.array([0, 0]), pa.array([4000, 700], pa.int32()), pa.array([text, text[1000:1700]])], names=["stream_id", "base", "own", "text"])
    found = hits._kernel_arrays(iter([batch]), {(16, 4): [(i, p) for i, p, _ in bank]}, 1, kernels.band_distances)
    found = [(ids[int(r)].as_py(), i, *h) for ids, of, i, *columns in found for r, *h in zip(of, *[c.tolist() for c in columns], strict=True)]
    assert calls == {"matrices": 1}
    for n, t in ((5, text), (6, text[1000:1700])):
        codes, _, _ = kernels.joined([t], 20)
        for i, p, k in bank:
            lengths, dist = original[0](codes, np.arange(len(t)), p, k)
            expected = [(n, i, s, length, d) for s in range(len(t)) for length, d in zip(lengths, dist[:, s].tolist(), strict=True) if d <= k and s + length <= len(t)]
            assert [h for h in found if h[:2] == (n, i)] == expected and (n == 6 or expected)


def test_bank_starts_agree(monkeypatch):
    """Grams leave no start of a hit out: short and long patterns, thresholds beyond the tables, symbols that no pattern has, and texts full of hits."""
    rng, by_grams = random.Random(5), Counter()
    for lp, k, letters, count in ((16, 4, "abcdefghijkl ", 200), (16, 4, "ab", 17), (5, 1, "abc", 4), (8, 0, "abcd", 5), (9, 2, "abcd", 33), (33, 7, "abcdef", 16), (64, 7, "abcdefgh", 5), (20, 9, "abc", 4), (12, 5, "ab\U0001f600", 6)):
        text = "".join(rng.choice(letters + "?") for _ in range(3000))
        bank = [kernels.encode("".join(rng.choice(letters) if rng.random() < 0.1 else c for c in text[a : a + lp])) for a in (rng.randrange(2900) for _ in range(count))]
        for t in (text, "", "?", text[:lp], text[7 : 7 + lp] * 40):
            codes, _, _ = kernels.joined([t, t[1:]], lp + k)
            expected = [s.tolist() for s in kernels.hit_starts(codes, bank, k)]
            for most in (1 << 15, 16):
                monkeypatch.setattr(kernels, "DECIDED", most)
                assert [s.tolist() for s in kernels.bank_starts(codes, bank, k)] == expected
                grams = kernels.GramFilter(np.array(bank), k)
                by_grams[grams.useful and grams.starts(codes) is not None] += 1
    assert by_grams[True] > 20 and by_grams[False] > 10


def test_bank_folds_patterns_apart(spark):
    """Islands of many patterns that are folded together: several rows a chunk, blocks with edges, and two patterns of one number."""
    texts = random_texts(7, 12, 150, "ABC")
    bank = [(i, p, 2) for i, p in enumerate(("ABBAC", "BBABA", "AACBA", "BABAA", "CCABC", "ABBAB"))]
    expected = sorted((n, i, *o) for n, t in enumerate(texts) for i, p, k in bank for o in reference.sift(p, t, k))
    for block in (1 << 16, 40):
        assert rows(sifter.sift_bank(streams(spark, *texts), S.pattern_frame(spark, bank), block=block, number=False), "stream_id", "pattern_id", "start", "len", "dist") == expected
    twice = [(0, p, k) for _, p, k in bank]
    assert rows(sifter.sift_bank(streams(spark, *texts), S.pattern_frame(spark, twice), number=False), "stream_id", "start", "len", "dist") == sorted((n, *rest) for n, _, *rest in expected)


def test_search_plans_agree(spark):
    texts = random_texts(11, 40, 90, "ABC")
    all_streams, table = streams(spark, *texts), S.pattern_frame(spark, [(0, "ABCAB", 1), (1, "CCBA", 2)])
    columns = ("stream_id", "pattern_id", "start", "len", "dist")
    expected = sorted((i, pid, *h) for i, t in enumerate(texts) for pid, p, k in ((0, "ABCAB", 1), (1, "CCBA", 2)) for h in reference.hits(p, t, k))
    for found in (
        hits.find_hits(all_streams, table, kernel="native"), hits.find_hits(all_streams, table, block=13), hits.exhaustive_hits(all_streams, table), hits.hits_prefiltered(all_streams, table, block=20),
        hits.hits_qgram_index(all_streams, table, hits.qgram_index(all_streams, 2), 2),
    ):
        assert rows(found, *columns) == expected
    with pytest.raises(Exception, match="up to 10 symbols"):
        hits.exhaustive_hits(all_streams, table, max_len=10).collect()
    a = rows(sifter.split_islands(hits.find_hits(all_streams, table), block=8), *columns, "island")
    assert a == rows(sifter.islands_by_window(hits.find_hits(all_streams, table)), *columns, "island")


def test_fold_of_many_islands(monkeypatch):
    """Steps over many islands at once against the hit-by-hit fold, with every number of islands left to the latter."""
    rng = random.Random(2)
    for few in (0, 3, 12):
        monkeypatch.setattr(fold, "FEW", few)
        for _ in range(150):
            rules, levels = fold.Rules(rng.choice(fold.TIES), rng.choice(fold.VALIDATIONS), rng.random() < 0.5), rng.randint(1, 4)
            found, begin, expected = [], [], []
            for island in range(rng.randint(0, 25)):
                at, own = 0, set()
                for _ in range(rng.randint(1, 12)):
                    at += rng.randint(0, 3)
                    own.add((at, rng.randint(1, 5)))
                own = [(*x, rng.randrange(levels)) for x in sorted(own)]
                begin.append(len(found))
                found += own
                serial = fold.SerialSifter(levels, rules)
                expected += [(island, *o) for h in own for o in serial.add(*h)] + [(island, *o) for o in serial.close()]
            columns = np.array(found, np.int64).reshape(-1, 3).T
            got = fold.fold_islands(np.array(begin, np.int64), *columns, levels, rules)
            assert sorted(zip(*(g.tolist() for g in got), strict=True)) == sorted(expected)


def test_one_long_stream(spark):
    """A stream far above a block, built from symbol rows and never in one row: blocks, hits and occurrences as of the whole text."""
    rng = random.Random(31)
    text = "".join(rng.choice("ABCD") for _ in range(30_000))
    symbols = [(5, i, c) for i, c in enumerate(text)] + [(6, i, c) for i, c in enumerate("ABCABC")] + [(6, 9, None)]
    rng.shuffle(symbols)
    df = spark.createDataFrame(symbols, "s long, at long, sym string").repartition(7)
    built = S.build_blocks(df, F.col("s"), ("at",), F.col("sym"), block=64, halo=8).persist()
    got = sorted((r["stream_id"], r["base"], r["own"], r["text"], r["final"]) for r in built.collect())
    expected = [(5, b, min(64, 30_000 - b), text[b : b + 72], b + 72 >= 30_000) for b in range(0, 30_000, 64)] + [(6, 0, 6, "ABCABC", True)]
    assert got == expected
    table = S.pattern_frame(spark, [(0, "ABCAB", 1), (1, "DDDDDD", 3)])
    whole = [(5, p, *o) for p, (q, k) in enumerate((("ABCAB", 1), ("DDDDDD", 3))) for o in reference.sift(q, text, k)] + [(6, p, *o) for p, (q, k) in enumerate((("ABCAB", 1), ("DDDDDD", 3))) for o in reference.sift(q, "ABCABC", k)]
    for giant in (1 << 20, 30):
        assert rows(sifter.sift(built, table, number=False, giant=giant), "stream_id", "pattern_id", "start", "len", "dist") == sorted(whole)
    with pytest.raises(Exception, match="halo is shorter"):
        sifter.sift(built, S.pattern_frame(spark, [(0, "ABCABCDABC", 1)])).collect()
    kept = sifter.sift(built, table)
    plain = sifter.numbered(kept.drop("group_no"), block=11)
    assert rows(kept, "stream_id", "pattern_id", "start", "group_no") == rows(plain, "stream_id", "pattern_id", "start", "group_no")


def test_detection_runs_once(spark, tables, monkeypatch):
    """For each engine: one pass of the kernel over the streams, at most two shuffles of hits in what is left of the plan, and no scan of a source."""
    passes = []
    original = sifter._kernel_arrays
    monkeypatch.setattr(sifter, "written", lambda df, name: (passes.append((name, df._jdf.queryExecution().executedPlan().toString())), scratch.written(df, name))[1])
    all_streams, table = streams(spark, *random_texts(5, 20, 60)), S.pattern_frame(spark, [(0, "ABBAB", 2)])
    assert original is hits._kernel_arrays
    for engine in ("kernel", "auto", "native", "iterator"):
        passes.clear()
        plan = sifter.sift(all_streams, table, engine=engine, number=False)._jdf.queryExecution().executedPlan().toString()
        made = [p for name, p in passes if name in ("hits", "detected")]
        assert len(made) == 1 and made[0].count("MapInArrow") == 1 and "Exchange" not in made[0]
        assert "Scan ExistingRDD" not in plan and "LocalTableScan" not in plan
        # rows by block of positions, their summary by block and then by stream, and rows by island; equal ones are one
        shuffled = [line for line in plan.splitlines() if "Exchange hashpartitioning" in line and "len" not in line]
        assert len(shuffled) <= (0 if engine == "kernel" else 5)


def test_bank_deals_its_blocks_out(spark, monkeypatch):
    """A file of one row group is one task: a bank's blocks are dealt out before the search, with the same result."""
    passes = []
    monkeypatch.setattr(sifter, "written", lambda df, name: (passes.append(df._jdf.queryExecution().executedPlan().toString()), scratch.written(df, name))[1])
    texts = random_texts(5, 20, 60)
    all_streams, table = streams(spark, *texts).coalesce(1), S.pattern_frame(spark, [(i, p, 2) for i, p in enumerate(("ABBAB", "BBABA", "AABBA", "BABAA"))])
    got = {tuple(r) for r in sifter.sift_bank(all_streams, table, validation="interval", number=False).collect()}
    assert "Exchange hashpartitioning(stream_id" in passes[0].split("MapInArrow")[1]
    assert got == {tuple(r) for r in sifter.sift(all_streams, table, validation="interval", number=False).collect()} and got


def test_invariants(spark):
    texts = random_texts(5, 120, 60)
    all_streams, table = streams(spark, *texts), S.pattern_frame(spark, [(0, "ABBAB", 2)])
    found = hits.find_hits(all_streams, table)
    occurrences = sifter.sift_hits(found, 3, validation="interval")
    assert measures.overlap_violations(occurrences).first()["violations"] == 0
    assert {r["excess"] for r in measures.decision_delay(sifter.sift_hits(found, 3), table).collect()} == {0}
    assert occurrences.select("stream_id", "start", "len", "dist").subtract(found.select("stream_id", "start", "len", "dist")).count() == 0
    assert occurrences.where("abs(len - 5) > dist").count() == 0
    ends = baselines.free_start_ends(all_streams, table).count()
    assert occurrences.count() <= ends <= found.count()


def test_offline_policies(spark):
    texts = random_texts(9, 40, 40)
    found = hits.find_hits(streams(spark, *texts), S.pattern_frame(spark, [(0, "ABA", 1)]))
    by_stream = {}
    for r in found.collect():
        by_stream.setdefault(r["stream_id"], []).append((r["dist"], r["start"], r["len"]))
    for policy, order in (("greedy", lambda h: h), ("max_disjoint", lambda h: (h[1] + h[2], h[1], h[2]))):
        expected = []
        for i, own in by_stream.items():
            taken = []
            for d, s, n in sorted(own, key=order):
                if all(s + n <= a or a + m <= s for _, a, m in taken):
                    taken.append((d, s, n))
            expected += [(i, s, n, d) for d, s, n in taken]
        assert rows(baselines.offline_filter(found, policy), "stream_id", "start", "len", "dist") == sorted(expected)


def test_other_distances(spark):
    pairs = spark.createDataFrame([("ABC", "AXBYC"), ("ABC", "ACB"), ("AB", "AB"), ("", "AB"), ("ABCD", "DCBA")], "a string, b string")
    got = {(r["a"], r["b"]): (r["h"], r["i"], r["e"]) for r in pairs.select("a", "b", D.hamming(F.col("a"), F.col("b")).alias("h"), D.indel_distance(F.col("a"), F.col("b")).alias("i"), D.episode_distance(F.col("a"), F.col("b")).alias("e")).collect()}
    assert got == {("ABC", "AXBYC"): (None, 2, 2), ("ABC", "ACB"): (2, 2, None), ("AB", "AB"): (0, 0, 0), ("", "AB"): (None, 2, 2), ("ABCD", "DCBA"): (4, 6, None)}


def test_resource_plane(spark):
    fit = resource_fit(spark)
    assert round(fit["r2"], 3) == 0.98 and round(fit["bits"], 1) == 45.1 and round(fit["lp"], 1) == 87.7 and round(fit["k"], 1) == 120.8


@pytest.mark.parametrize(("p", "k", "counts"), [("SVCPE", 1, (20, 17, 15)), ("SVCPE", 2, (244, 167, 92)), ("EEEP", 1, (43, 33, 22)), ("CVPSEC", 2, (87, 53, 27))])
def test_event_counts(spark, tables, p, k, counts):
    from symseek.plans.methods import events
    from symseek.plans.registry import Tables

    traffic, table = events(Tables(spark, tables)), S.pattern_frame(spark, [(0, p, k)])
    found = hits.find_hits(traffic, table)
    assert (found.count(), baselines.free_start_ends(traffic, table).count(), sifter.sift_hits(found, k + 1).count()) == counts


def test_plan_shape(spark, tables):
    """Patterns reach the scan's stage without a shuffle, only needed columns are read, and filters are pushed down."""
    from symseek.plans.methods import events
    from symseek.plans.registry import Tables

    t = Tables(spark, tables)
    plan = hits.find_hits(events(t), S.pattern_frame(spark, [(0, "SVCPE", 1)]))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "ReadSchema: struct<event_id:bigint,ts:timestamp_ntz,user_id:bigint,event_type:string>" in plan
    text = S.text_streams(t.documents.where("lang = 'en'"), F.col("doc_id"), F.col("text"))
    plan = hits.find_hits(text, S.pattern_frame(spark, [(0, "the", 1)]))._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "EqualTo(lang,en)" in plan
