"""The training-data operators against brute force, round trips and held-out rows, with the defined edge cases."""

import collections
import hashlib
import itertools
import math
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from symseek.llm import connected, decontaminate, html_extract, langid, media_ts, ngram_join, quality, sharding, sp_sampling, substring_dedup, token_counts
from symseek.llm.common import LOWER_ASCII, PLAIN_WORD, crc_bucket, table, words_of

WORD = re.compile(rb"[^\x20\x09-\x0D]+")
ODD_TEXTS = [None, "", " \n\t", "one", "é x", "no\x1cbreak\x85here \xa0", "Straße ÄÖ ß 😀 漢字", "x" * 50_000, "a b " * 8_000]


def docs(spark, texts, **columns):
    rows = [(i, t, *(v[i] for v in columns.values())) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string" + "".join(f", {c} string" for c in columns))


def clashing(df):
    """The same table with extra columns whose names the operators use inside."""
    for name in ("k", "id", "h", "body", "score", "gone", "n", "rep", "seed", "held", "extra_id", "__held", "row", "bucket", "packed", "around"):
        df = df.withColumn(name, F.lit("x"))
    return df


def by_id(df, *columns):
    return {r[0]: tuple(r[c] for c in columns) if len(columns) > 1 else r[columns[0]] for r in df.collect()}


def test_words_and_hashes():
    w = words_of(pa.array(ODD_TEXTS, pa.string()), PLAIN_WORD, LOWER_ASCII)
    for i, t in enumerate(ODD_TEXTS):
        expected = WORD.findall((t or "").encode().lower() if (t or "").isascii() else bytes(LOWER_ASCII[np.frombuffer((t or "").encode(), np.uint8)]))
        assert [w.data[a:b].tobytes() for a, b in zip(w.starts[w.first[i] : w.first[i + 1]], w.ends[w.first[i] : w.first[i + 1]], strict=True)] == expected
    same = words_of(pa.array(["the cat", "a cat the"]))
    assert same.hashes[0] == same.hashes[4] and same.hashes[1] == same.hashes[3] and len(set(same.hashes.tolist())) == 3


# 1, 2: learned models


def test_language_held_out(spark, tables):
    d = table(spark, tables, "documents")
    held = crc_bucket(F.col("doc_id"), 3) == 1
    got = langid.identify(d, langid.train(d, ~held), keep={"held_out": held}).join(d.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert sum(r["lang_pred"] == r["lang"] for r in got) / len(got) > 0.95
    assert all(0 <= r["score"] <= 1 for r in got)


def test_language_edges(spark):
    texts = ["the cat and the dog went"] * 3 + ["der Hund und die Katze gehen"] * 3
    d = docs(spark, texts, lang=["en"] * 3 + ["de"] * 3)
    model = langid.train(d, F.lit(True))
    odd = clashing(docs(spark, ODD_TEXTS))
    got = by_id(langid.identify(odd, model), "lang_pred", "score")
    assert got[0] == got[1] == got[2] == ("und", 0.0) and {x[0] for x in got.values()} <= {"en", "de", "und"} and got[3][0] != "und"
    assert {r["lang_pred"] for r in langid.identify(odd, None).collect()} == {"und"}
    assert langid.train(d.limit(0), F.lit(True)) is None
    assert langid.identify(odd.limit(0), model).count() == 0


def test_quality_held_out(spark, tables):
    d, labels = table(spark, tables, "documents"), table(spark, tables, "labels")
    held = crc_bucket(F.col("doc_id"), 5) == 0
    got = quality.score(d, quality.train(d, labels, ~held), keep={"held_out": held}).join(labels, "doc_id").where("held_out").collect()
    good = [r["score"] for r in got if r["quality"] == 1]
    assert sum(s >= quality.ACCEPT for s in good) / len(good) > 0.9
    bad = [r["score"] for r in got if r["quality"] == 0]
    assert not bad or np.mean(bad) < np.mean(good)


def test_quality_edges(spark):
    odd = clashing(docs(spark, ODD_TEXTS))
    none = spark.createDataFrame([], "doc_id long, quality int")
    assert set(by_id(quality.score(odd, quality.train(odd, none, F.lit(True))), "score").values()) == {0.5}
    one = spark.createDataFrame([(3, 1), (4, 1), (5, None)], "doc_id long, quality int")
    assert all(s > 0.9 for s in by_id(quality.score(odd, quality.train(odd, one, F.lit(True))), "score").values())
    x = quality.statistics(pa.array(ODD_TEXTS, pa.string()))
    assert x.shape == (len(ODD_TEXTS), len(quality.STATISTICS)) and np.isfinite(x).all() and not x[:2].any()


def test_trees_match_plain_walk():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(800, 5)).astype(np.float32)
    y = ((x[:, 0] > 0.3) ^ (x[:, 1] < 0)).astype(float)
    model = quality.fit(x, y, trees=25, depth=3)
    assert ((model.score(x) > 0.5) == y).mean() > 0.97
    for row, s in zip(x[:50], model.score(x[:50]), strict=True):
        raw = model.base
        for t in range(25):
            node = 0
            while node < 7:
                node = 2 * node + 1 + bool(row[model.feature[t, node]] > model.threshold[t, node])
            raw += model.leaf[t, node - 7]
        assert math.isclose(s, 1 / (1 + math.exp(-raw)), rel_tol=1e-9)


# 3: sharding


def test_shards(spark):
    d = clashing(docs(spark, ODD_TEXTS * 40)).unionByName(clashing(spark.createDataFrame([(None, "n"), (3, "again")], "doc_id long, text string")))
    got = sharding.assign_shards(d, [1.0] * 8, groups=4).collect()
    assert len(got) == d.count()
    for s in range(8):
        assert sorted(r["slot"] for r in got if r["shard"] == s) == list(range(sum(r["shard"] == s for r in got)))
    assert all(r["grown_shard"] in (r["shard"], 8) for r in got)
    assert {r["size"] for r in got if r["doc_id"] == 0} == {1} and {r["text_crc32"] for r in got if r["doc_id"] == 6} == {zlib.crc32(ODD_TEXTS[6].encode())}
    assert len({r["shard"] for r in got if r["doc_id"] == 3}) == 1
    assert sharding.assign_shards(d.limit(0), [1.0] * 8).count() == 0
    with pytest.raises(ValueError):
        sharding.shard_of(F.col("doc_id"), [1.0, 0.0])


def test_shard_weights(spark):
    got = spark.range(20_000).select(sharding.shard_of(F.col("id"), [1.0, 2.0, 1.0]).alias("s")).groupBy("s").count().collect()
    share = {r["s"]: r["count"] / 20_000 for r in got}
    assert abs(share[1] - 0.5) < 0.02 and abs(share[0] - 0.25) < 0.02


# 4: decontamination


def test_items_against_brute_force(spark):
    rng = random.Random(2)
    vocabulary = [f"w{i}" for i in range(40)]
    items = [" ".join(rng.choices(vocabulary, k=rng.randint(3, 40))) for _ in range(25)]
    texts = list(ODD_TEXTS)
    for _ in range(60):
        item = rng.choice(items).split()
        for _ in range(rng.randint(0, 2)):
            item[rng.choice((0, -1))] = rng.choice(vocabulary)
        texts.append(" ".join(rng.choices(vocabulary, k=rng.randint(0, 30)) + item + rng.choices(vocabulary, k=rng.randint(0, 30))).upper())
    bench = spark.createDataFrame([*enumerate(items), (99, None), (98, "")], "item_id long, text string")
    d = clashing(docs(spark, texts))
    shingles = lambda w: collections.Counter(tuple(w[i : i + min(5, len(w))]) for i in range(len(w) - min(5, len(w)) + 1))
    expected = {}
    for i, text in enumerate(texts):
        words = re.findall(r"[^\x00-\x2f\x3a-\x40\x5b-\x60\x7b-\x7f]+", (text or "").lower())
        for j, item in enumerate(items):
            n, own = len(item.split()), shingles(item.split())
            for at in range(len(words) - n + 1 if len(words) < 5000 else 0):
                other = shingles(words[at : at + n])
                s = sum((own & other).values()) / sum((own | other).values())
                if s >= 0.8:
                    expected[i, j] = max(expected.get((i, j), 0), s)
    for block in (8 << 20, 300):
        got = {(r["doc_id"], r["item_id"]): r["similarity"] for r in decontaminate.find_items(d, bench, block_bytes=block).collect()}
        assert got.keys() == expected.keys() and all(math.isclose(got[k], expected[k]) for k in got)
    clean = decontaminate.without_items(d, bench)
    assert clean.columns == d.columns and {r["doc_id"] for r in clean.collect()} == set(range(len(texts))) - {i for i, _ in expected}
    assert decontaminate.find_items(d, bench.limit(0)).count() == 0


def test_block_radii_cover():
    for radius in (0, 7, 15, 16, 40, 128):
        radii = decontaminate.block_radii(radius)
        assert sum(r + 1 for r in radii) == radius + 1  # so the bits can't all be over their byte's share


def test_near_fingerprints_are_complete():
    """Every pair within the radius passes the blocks, whatever bits differ; radius 128 lets all pairs pass."""
    rng = np.random.default_rng(5)
    index = decontaminate.ItemIndex([0], ["one two three four five six seven"])
    for radius in (40, 128):
        index.radius, index.radii = radius, np.array(decontaminate.block_radii(radius))
        for flips in range(0, 129, 4):
            bits = np.unpackbits(np.repeat(index.prints, 50, 0), axis=1)
            for row in bits:
                row[rng.permutation(128)[:flips]] ^= 1
            near, apart = index.near(np.packbits(bits, axis=1), np.zeros(50, int))
            assert len(near) == (50 if flips <= radius else 0) and set(apart.tolist()) <= {flips}
    assert decontaminate.windows(np.array([1, 2, 9]), np.array([4, 5, 9])).tolist() == [1, 2, 3, 4, 5, 9]


def test_items_in_blocks_and_other_keys(spark, tables):
    """Blocks of items one after another, the largest radius, and keys of another type give the same rows."""
    d, items = table(spark, tables, "documents"), table(spark, tables, "benchmark")
    rows = lambda df: sorted((int(r["doc_id"]), int(r["item_id"]), r["similarity"], r["first_word"]) for r in df.collect())
    plain = rows(decontaminate.find_items(d, items))
    assert plain and plain == rows(decontaminate.find_items(d, items, block_bytes=2_000)) == rows(decontaminate.find_items(d, items, radius=128))
    odd = [df.withColumn(c, F.col(c).cast("decimal(20,0)")) for df, c in ((d, "doc_id"), (items, "item_id"))]
    assert plain == rows(decontaminate.find_items(*odd))
    near = ngram_join.near_copies(odd[0]).collect()
    assert {int(r["doc_id"]): int(r["component_id"]) for r in near} == {r["doc_id"]: r["component_id"] for r in ngram_join.near_copies(d).collect()}


# 5: extraction

PAGE = """<!DOCTYPE html><html><head><title>t &amp; t</title><style>p{{}}</style><script>if (a < b) document.write("<p>no</p>")</script></head><body>
<nav><ul><li><a href="/">Home</a></li></ul></nav><div id="cookie-notice">We use cookies</div>{main}<aside>More</aside><form><p>Sign up</p></form><div class="comments"><p>First!</p></div><footer>&copy; x</footer></body></html>"""


def pages(spark, *rows):
    return spark.createDataFrame([(i, u, h) for i, (u, h) in enumerate(rows)], "page_id long, url string, html string")


def test_marked_content(spark):
    main = "<article><h1>A&nbsp;&lt;title&gt;</h1><p>One\n  two<br>three <b>bo</b>ld</p><div class='ad'>Buy</div><ul><li>x</li><li>y&#233;</ul><p>cut <a hre"
    rows = [("http://h/a/1", PAGE.format(main="<article><p>Shared.</p><p>Own 1</p></article>")), ("http://h/a/2", PAGE.format(main="<article><p>Shared.</p><p>Own 2</p></article>")), (None, main), ("http://h/b", None), ("bad url", "")]
    got = by_id(html_extract.extract(clashing(pages(spark, *rows))), "text")
    assert got == {0: "Shared.\nOwn 1", 1: "Shared.\nOwn 2", 2: "A <title>\nOne two three bold\nx\nyé\ncut", 3: "", 4: ""}


def test_differencing(spark):
    body = lambda own: f"<body><p>Site name</p><div><p>{own} first</p><p>{own} second</p></div><p>Imprint</p></body>"
    rows = [(f"http://h/x/{i}", body(f"page {i}")) for i in range(5)] + [("http://other/x/1", "<p>Site name</p>"), ("http://h/x/0?copy", body("page 0"))]
    for near in (1, 2):
        got = by_id(html_extract.extract(pages(spark, *rows).repartition(3), near=near), "text")
        own = {i: f"page {i} first\npage {i} second" for i in range(5)} | {6: "page 0 first\npage 0 second"}
        if near == 1:  # of the two copies, one has only the other beside it, which says nothing
            whole = [i for i in (0, 6) if got[i] != own[i]]
            assert len(whole) == 1 and got[whole[0]] == f"Site name\n{own[whole[0]]}\nImprint"
            own[whole[0]] = got[whole[0]]
        assert got == {**own, 5: "Site name"}
    assert html_extract.extract(pages(spark, *rows).limit(0)).count() == 0


def test_nothing_of_an_article_is_lost(spark):
    """Names of classes that articles use, formulas, embedded and hidden content stay; a suspicious class needs neighbours that share its slot."""
    inner = (
        "<section class='discussion related'><p>A <math><mi>x</mi></math> and <svg><text>label</text></svg>.</p></section><p class='legal-note'>Law</p><p hidden>More</p>"
        "<object>fallback</object> <noscript>plain</noscript><div class='search-result reply notice'>Found</div>"
    )
    page = lambda i, more="": f"<nav><a>n{i}</a></nav><article><h1>T{i}</h1>{inner}{more}</article><div class='foot'>f{i}</div>"
    ad = "<div class='ad'>Buy {}</div>"
    rows = [(f"http://h/{i}", page(i, ad.format(i) if i in (1, 2) else "")) for i in range(3)] + [("http://lone/1", page(9, ad.format(9))), ("http://pair/1", page(7, ad.format(7))), ("http://pair/2", page(8))]
    got = by_id(html_extract.extract(pages(spark, *rows)), "text", "n_differenced", "n_by_markup")
    kept = "T{}\nA x and label.\nLaw\nMore\nfallback plain\nFound"
    assert got[0] == (kept.format(0), 2, 0) and got[1] == (kept.format(1), 3, 0) and got[2] == (kept.format(2), 3, 0)
    assert got[3] == (kept.format(9), 0, 3)  # nobody to ask
    assert got[4] == (kept.format(7) + "\nBuy 7", 2, 0)  # a neighbour, which has no such slot


def test_neighbours_and_deletion_against_brute_force(spark, tables):
    df = table(spark, tables, "pages")
    rows = sorted((r for r in df.collect()), key=lambda r: r["page_id"])
    host = lambda u: re.match(r"\w+://([^/?#]*)", u)[1].lower()
    path = lambda u: re.match(r"\w+://[^/?#]*([^?#]*)", u)[1]
    ids = {r["page_id"]: r["row"] for r in df.select("page_id", F.xxhash64("page_id", "url", "html").alias("row")).collect()}
    order = sorted(rows, key=lambda r: (host(r["url"]), path(r["url"]), ids[r["page_id"]]))
    got = by_id(html_extract.extract(df), "text", "n_differenced", "n_by_markup")
    parsed = {r["page_id"]: html_extract.lines_of(r["html"]) for r in rows}
    for i, r in enumerate(order):
        around = [order[j] for j in (i - 2, i - 1, i + 1, i + 2) if 0 <= j < len(order) and host(order[j]["url"]) == host(r["url"])]
        lines = parsed[r["page_id"]]
        open_lines = [k for k, x in enumerate(lines) if not x.main]  # every page of these tables marks an article
        gone = set()
        for other in around:
            theirs = [x.slot for x in parsed[other["page_id"]] if not x.main]
            mine = [lines[k].slot for k in open_lines]
            common = max((c for n in range(len(mine) + 1) for c in itertools.combinations(range(len(mine)), n) if _subsequence([mine[x] for x in c], theirs)), key=len)
            gone |= {open_lines[k] for k in common}
        assert got[r["page_id"]][1] == len(gone) and got[r["page_id"]][2] == len(open_lines) - len(gone)
        assert got[r["page_id"]][0] == "\n".join(x.text for x in lines if x.main)
    assert sum(x[1] for x in got.values()) > 0


def test_longest_common_subsequence(monkeypatch):
    rng = random.Random(4)
    for pairs in (html_extract.PAIRS, 3, 0):
        monkeypatch.setattr(html_extract, "PAIRS", pairs)
        for _ in range(200):
            a, b = ([rng.randint(0, 4) for _ in range(rng.randint(0, 9))] for _ in range(2))
            best = max((n for n in range(len(a) + 1) for c in itertools.combinations(range(len(a)), n) if _subsequence([a[i] for i in c], b)), default=0)
            found = sorted(html_extract.shared_lines(a, b))
            assert len(found) == best and _subsequence([a[i] for i in found], b)


def _subsequence(x, y):
    rest = iter(y)
    return all(v in rest for v in x)


# 6: segmentations


def test_segmentations(spark):
    d = clashing(docs(spark, ODD_TEXTS + ["▁ odd  spaces \n\n lines", "the the"]))
    rows = sp_sampling.sample(d, k=3).collect()
    again = sp_sampling.sample(d.repartition(5), k=3).collect()
    assert sorted(map(repr, rows)) == sorted(map(repr, again))
    own = collections.defaultdict(list)
    for r in rows:
        own[r["doc_id"]].append(r)
    assert len(own) == len(ODD_TEXTS) + 2
    for i, found in own.items():
        assert len({tuple(r["token_ids"]) for r in found}) == len(found) and all(0 < r["inclusion"] <= 1 or r["log_prob"] < -20 for r in found)
        assert [r["perturbed"] for r in sorted(found, key=lambda r: r["draw"])] == sorted((r["perturbed"] for r in found), reverse=True)
        assert all(r["restored"] for r in found if i != len(ODD_TEXTS))  # a space mark in the text is a space
    assert [(r["draw"], list(r["token_ids"]), r["inclusion"]) for r in own[0]] == [(0, [], 1.0)]
    decoded = by_id(sp_sampling.decode(sp_sampling.encode(d).withColumn("decoded", F.lit(1))), "decoded")
    assert all(decoded[i] == (t or "") for i, t in enumerate(ODD_TEXTS))
    assert sp_sampling.sample(d.limit(0)).count() == 0


def test_sampling_without_replacement_has_the_right_law():
    v = sp_sampling.vocabulary(sp_sampling.MODEL, 0.5)
    lattices = sp_sampling.Lattices(sp_sampling.units_of("the the"), v)

    def paths(node):
        if lattices.left[node] == 0:
            return [((), 0.0)]
        return [((int(lattices.piece[e]), *rest), float(lattices.logp[e]) + q) for e in range(lattices.first[node], lattices.first[node + 1]) for rest, q in paths(int(lattices.target[e]))]

    every = {a + b: math.exp(p + q) for a, p in paths(int(lattices.start[0])) for b, q in paths(int(lattices.start[1]))}
    assert math.isclose(sum(every.values()), 1, rel_tol=1e-6)
    first, second, n = collections.Counter(), collections.Counter(), 4000
    for a, b in sp_sampling.segment(["the the"] * n, sp_sampling.mix64(np.arange(n, dtype=np.uint64)), 2, v):
        first[tuple(a[0].tolist())] += 1
        second[tuple(b[0].tolist())] += 1
    expected = collections.Counter()
    for a, p in every.items():
        for b, q in every.items():
            if a != b:
                expected[b] += p * q / (1 - p)
    for ids in sorted(every, key=every.get)[-4:]:
        assert abs(first[ids] / n - every[ids]) < 0.03 and abs(second[ids] / n - expected[ids]) < 0.03


# 7: token counts


def test_rollup(spark, monkeypatch):
    monkeypatch.setattr(token_counts, "KEPT", 2)  # more commits than manifests that stay
    counted = token_counts.with_counts(clashing(docs(spark, ODD_TEXTS, source=["a", None] * 4 + ["a"], lang=["en"] * 9)))
    encode = token_counts._pieces(token_counts.VOCABULARY).encode_ordinary
    assert by_id(counted, "n_tokens", "n_bytes") == {i: (len(encode(t or "")), len((t or "").encode())) for i, t in enumerate(ODD_TEXTS)}
    rollup = token_counts.new_rollup(spark)
    assert rollup.totals().count() == 0
    total = lambda: {(r["source"], r["lang"]): (r["docs"], r["tokens"], r["bytes"]) for r in rollup.totals().collect()}
    assert rollup.commit("b1", token_counts.changes(counted, +1))
    before = total()
    assert before["a", "en"][0] == 5 and before[None, "en"][0] == 4
    assert not rollup.commit("b1", token_counts.changes(counted, +1)) and total() == before
    old, new = counted.where("doc_id = 8"), counted.where("doc_id = 8").withColumn("n_tokens", F.lit(1).cast("long"))
    assert rollup.commit("b2", token_counts.revisions(old, new))
    revised = total()
    assert revised["a", "en"][:2] == (5, before["a", "en"][1] - len(encode(ODD_TEXTS[8])) + 1)
    assert rollup.commit("empty", token_counts.changes(counted.limit(0), +1)) and total() == revised
    assert rollup.commit("b3", token_counts.changes(counted.where("source is null"), -1))
    assert total()[None, "en"] == (0, 0, 0)
    fs, folder = rollup._at("manifests")
    assert sorted(int(x.getPath().getName()) for x in fs.listStatus(folder)) == [3, 4]
    rollup.compact()
    assert (None, "en") not in total() and rollup.committed() == ["b1", "b2", "empty", "b3"] and not rollup.commit("b2", token_counts.changes(counted, +1))


# 8: repeated passages


def test_repeats_against_brute_force(spark):
    rng = random.Random(8)
    vocabulary = [f"w{i}" for i in range(30)]
    passages = [rng.choices(vocabulary, k=rng.randint(6, 20)) for _ in range(4)] + [["tick", "tock"] * 12]
    texts = list(ODD_TEXTS[:7])
    for _ in range(60):
        parts = [rng.choices(vocabulary, k=rng.randint(0, 15)) for _ in range(3)]
        texts.append(rng.choice((" ", "\n", "\t ")).join(itertools.chain(parts[0], rng.choice(passages), parts[1], rng.choice(passages), parts[2])))
    texts += texts[10:14]
    width = 8
    d = clashing(docs(spark, texts)).unionByName(clashing(spark.createDataFrame([(12, texts[12]), (None, texts[20])], "doc_id long, text string")))
    words = {i: WORD.findall((t or "").encode()) for i, t in enumerate(texts)}
    firsts = {}
    for i, w in words.items():
        for at in range(len(w) - width + 1):
            firsts.setdefault(tuple(w[at : at + width]), i)
    expected = {None: (len(words[20]), 0, b" ".join(words[20]).decode())}
    for i, w in words.items():
        gone = {p for at in range(len(w) - width + 1) if firsts[tuple(w[at : at + width])] < i for p in range(at, at + width)}
        expected[i] = (len(w), len(gone), b" ".join(x for p, x in enumerate(w) if p not in gone).decode())
    for crowd in (2_000, 3, 1):
        got = substring_dedup.remove_repeats(d, width=width, seed=4, crowd=crowd).collect()
        assert len(got) == len(texts) + 2
        for r in got:
            assert (r["n_words"], r["n_removed"], r["kept"]) == expected[r["doc_id"]], r["doc_id"]
    assert substring_dedup.remove_repeats(d.limit(0)).count() == 0


def test_common_passage_in_many_documents(spark):
    """One passage between words of their own: each document adds a few rows to the last join, and not one for each window."""
    rng = random.Random(3)
    passage = [f"p{i}" for i in range(90)]
    word = lambda: f"w{rng.randrange(10**6)}"
    n = 400
    texts = [" ".join([word() for _ in range(40)] + passage + [word() for _ in range(40)]) for _ in range(n)]
    d = docs(spark, texts)
    for crowd in (2_000, 50):
        out = substring_dedup.remove_repeats(d, crowd=crowd)
        got = out.collect()
        assert all(r["n_words"] == 170 and r["n_removed"] == (90 if r["doc_id"] else 0) and (r["doc_id"] == 0 or "p" not in r["kept"]) for r in got)
    w = words_of(pa.array(texts[:1]))
    inner = substring_dedup.super_kmers(w, 50, 16)
    assert len(inner[0]) < 20  # super-k-mers of a whole document of 121 windows
    line = substring_dedup.super_kmers(words_of(pa.array(["same line. " * 400])), 50, 16)
    assert line[2].tolist() == [751]


def test_cut_runs_keep_equal_windows_together():
    """Whatever windows take part, equal windows of two texts get equal minimisers."""
    rng = random.Random(9)
    vocabulary = [f"v{i}" for i in range(6)]
    texts = [" ".join(rng.choices(vocabulary, k=60)) for _ in range(30)]
    w = words_of(pa.array(texts))
    wanted = np.array([rng.random() < 0.7 for _ in w.hashes])
    text, start, n, mini = substring_dedup.super_kmers(w, 8, 5, wanted)
    of = {}
    for t, s, c, m in zip(text.tolist(), start.tolist(), n.tolist(), mini.tolist(), strict=True):
        for i in range(s, s + c):
            assert wanted[w.first[t] + i] and of.setdefault(tuple(texts[t].split()[i : i + 8]), m) == m
    assert sum(n) == sum(bool(wanted[w.first[t] + i]) for t in range(30) for i in range(53))
    assert substring_dedup.wider_seeds(50, 16) == [38, 50] and substring_dedup.wider_seeds(8, 8) == []


# 9: media


@pytest.mark.parametrize("size", [0, 1, 575, 576, 577, 18_432, 18_433, 60_000])
def test_transport_stream_round_trip(size):
    payload = media_ts.padded(random.Random(size).randbytes(size))
    read = media_ts.demux(stream := media_ts.mux(payload))
    assert read.payload == payload and read.continuity_errors == 0 and len(payload) % 576 == 0
    units = len(payload) // 576
    assert read.timestamps == [u * 3600 for u in range(0, units, 32)] and len(read.random_access) == len(read.timestamps)
    assert all(stream[at] == 0x47 for at in read.random_access)
    if read.packets > 6:
        assert media_ts.demux(stream[: 188 * 4] + stream[188 * 5 :]).continuity_errors == 1
    for bad in (b"", stream[:-1], b"\0" + stream[1:], stream[:20] + b"\xee" + stream[21:]):
        with pytest.raises(ValueError):
            media_ts.demux(bad)


def test_media_columns(spark):
    texts = [*ODD_TEXTS, "one"]
    got = by_id(media_ts.read_media(media_ts.store_texts(clashing(docs(spark, texts)))), "n_bytes", "payload", "tail_crc32", "media_sha256", "media_bytes")
    for i, t in enumerate(texts):
        payload = media_ts.padded((t or "").encode())
        assert got[i] == (len((t or "").encode()), payload, zlib.crc32(payload[-32:]), hashlib.sha256(media_ts.mux(payload)).hexdigest(), len(media_ts.mux(payload)))
    assert got[3] == got[len(texts) - 1]


# 10: near copies


def test_near_copies_against_brute_force(spark):
    rng = random.Random(10)
    vocabulary = [f"W{i}" for i in range(200)]
    texts = list(ODD_TEXTS)
    for size in (5, 12, 30, 80):
        base = rng.choices(vocabulary, k=size)
        for _ in range(14):
            copy = list(base)
            for _ in range(rng.randint(0, max(1, size // 20))):
                copy[rng.randrange(size)] = rng.choice(vocabulary)
            texts.append(" ".join(copy).lower() if rng.random() < 0.5 else "\n".join(copy))
    texts += texts[12:15]
    d = clashing(docs(spark, texts)).unionByName(clashing(spark.createDataFrame([(12, texts[12]), (None, texts[12])], "doc_id long, text string")))
    for n, percent, block, small in ((3, 90, 600, 48), (2, 60, 5, 3)):
        sets = []
        for t in texts:
            w = WORD.findall(bytes(LOWER_ASCII[np.frombuffer((t or "").encode(), np.uint8)]))
            sets.append({tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else {tuple(w)} if w else set())
        root = list(range(len(texts)))
        for i, j in itertools.combinations(range(len(texts)), 2):
            both = len(sets[i] & sets[j])
            if both and 100 * both >= percent * len(sets[i] | sets[j]):
                a, b = sorted((root[i], root[j]))
                root = [a if r == b else r for r in root]
        got = ngram_join.near_copies(d, n=n, percent=percent, block=block, small=small).collect()
        assert len(got) == len(texts) + 2
        for r in got:
            if r["doc_id"] is None:
                assert r["component_id"] is None and r["n_shingles"] == len(sets[12])
            else:
                assert (r["n_shingles"], r["component_id"]) == (len(sets[r["doc_id"]]), root[r["doc_id"]]), r["doc_id"]
    assert ngram_join.near_copies(d.limit(0)).count() == 0


def test_frequent_ngram_glues_nothing(spark):
    """Documents of words of their own that all hold one phrase don't become a cluster; documents made of frequent phrases only still link."""
    rng = random.Random(77)
    phrase = "the same few words in every text"
    texts = [" ".join(f"w{rng.randrange(10**7)}" for _ in range(30)) + f" {phrase}" for _ in range(200)]
    short = [f"{phrase} {phrase} {x}" for x in ("once", "once", "twice")] + [phrase]
    d = docs(spark, texts + short)
    shared = spark.createDataFrame([(g, i, 30, 200) for i in range(200) for g in (1, 2)] + [(g, 500 + i, 30, 200) for i in range(60) for g in (3, 4, 5, 6)], "gram long, id long, n int, size long")
    left = ngram_join._rarest(shared, 90)
    assert left.where("id < 500").count() == 0 and left.where("id >= 500").groupBy("id").count().where("count <> 2").count() == 0
    got = by_id(ngram_join.near_copies(d, small=8), "component_id")
    assert got == {**{i: i for i in range(200)}, 200: 200, 201: 200, 202: got[202], 203: 203}


def test_components(spark):
    edges = [(i, i + 1) for i in range(90)] + [(200, 150), (150, 170), (300, 300)]
    got = by_id(connected.components(spark.createDataFrame(edges, "a long, b long")), "root")
    assert got == {**{i: 0 for i in range(91)}, 150: 150, 170: 150, 200: 150}


def test_least_shared_is_a_bound(spark):
    """Linked sets share at least so many prefix n-grams, whatever the order."""
    rng = random.Random(6)
    for _ in range(300):
        percent, size = rng.choice((60, 80, 90)), rng.randint(1, 60)
        a = set(range(size))
        b = (a - set(rng.sample(range(size), min(size, rng.randint(0, size // 8 + 1))))) | set(range(100, 100 + rng.randint(0, size // 8 + 1)))
        if not b or 100 * len(a & b) < percent * len(a | b):
            continue
        order = {x: rng.random() for x in a | b}
        heads = [set(sorted(s, key=order.get)[: ngram_join.prefix_length(len(s), percent)]) for s in (a, b)]
        behind = lambda n, t=percent: max(0, -(-n * t // 100) - ngram_join.SHARED)
        least = max(1, -(-(len(a) + len(b)) * percent // (100 + percent)) - max(behind(len(a)), behind(len(b))))
        assert len(heads[0] & heads[1]) >= least >= min(ngram_join.SHARED, -(-max(len(a), len(b)) * percent // 100))
        assert spark is not None


# More edges: brute force for the learned models, an independent reader, long texts, many draws


def test_kernel_and_ridge_against_brute_force():
    """The kernel's values from sets of n-grams, and the solution from plain normal equations."""
    texts = ["the cat sat on the mat", "a dog and the cat", "der Hund und die Katze", "die Katze sitzt", "le chat et le chien", "the the the"]
    names = ["en", "en", "de", "de", "fr", "en"]
    model = langid.fit(texts, names, landmarks=6, ridge=1e-2)
    folded = [bytes(langid._FOLD[np.frombuffer(t.lower().encode(), np.uint8)]) for t in texts]
    grams = [{t[i : i + n] for n in (2, 3, 4, 5) for i in range(len(t) - n + 1)} for t in folded]
    order = [i for c in sorted(set(names)) for i in [j for j, x in enumerate(names) if x == c][: max(1, 6 // 3)]]
    exact = np.array([[len(a & grams[j]) / math.sqrt(max(len(a), 1) * max(len(grams[j]), 1)) for j in order] for a in grams])
    got = model.kernel(pa.array(texts))
    assert got.shape == exact.shape and np.allclose(got, exact, atol=0.02)  # buckets may be shared
    square = exact[order]
    value, vector = np.linalg.eigh(square)
    mapped = exact @ (vector / np.sqrt(np.maximum(value, 1e-6 * value.max())) @ vector.T)
    target = np.array([[1.0 if x == c else -1.0 for c in sorted(set(names))] for x in names])
    weigh = np.diag([1 / names.count(x) for x in names])
    solved = mapped @ np.linalg.solve(mapped.T @ weigh @ mapped + 1e-2 * np.eye(len(order)), mapped.T @ weigh @ target)
    assert np.allclose(got @ model.weights, solved, atol=0.05)
    best, _ = model.predict(pa.array(["cat"] * 3 + [""]))
    assert len(set(best[:3].tolist())) == 1
    tied = langid.KernelModel(["de", "en"], model.feature_of, model.landmarks, np.zeros((len(model.landmarks), 2), np.float32))
    assert tied.predict(pa.array(["anything"]))[0].tolist() == [0] and tied.predict(pa.array(["x"]))[1].tolist() == [0.5]


def test_statistics_against_brute_force():
    rng = random.Random(8)
    texts = ["".join(rng.choice("aB3 .!#\n\té") for _ in range(rng.randint(1, 80))) for _ in range(60)]
    got = quality.statistics(pa.array(texts))
    column = {name: i for i, name in enumerate(quality.STATISTICS)}
    for t, x in zip(texts, got, strict=True):
        data, words = t.encode(), WORD.findall(t.encode())
        lines = [line for line in data.split(b"\n") if line]
        pairs = list(itertools.pairwise(words))
        n = max(len(words), 1)
        expected = {
            "log_bytes": math.log1p(len(data)), "lower": data.count(b"a") / len(data), "upper": data.count(b"B") / len(data), "digit": data.count(b"3") / len(data), "beyond_ascii": sum(b > 127 for b in data) / len(data),
            "log_words": math.log1p(len(words)), "word_length": sum(map(len, words)) / n, "word_spread": float(np.std([len(w) for w in words])) if words else 0, "distinct_words": len(set(words)) / n,
            "log_lines": math.log1p(len(lines)), "repeated_lines": 1 - len(set(lines)) / len(lines) if lines else 0.0, "symbol_words": sum(b"#" in w or b"!" in w for w in words) / n, "short_words": sum(len(w) <= 2 for w in words) / n,
            "long_words": sum(len(w) >= 12 for w in words) / n, "full_stops": sum(w[-1:] in (b".", b"!", b"?") for w in words) / n, "repeated_pairs": 1 - len(set(pairs)) / len(pairs) if pairs else 0.0,
        }
        for name, value in expected.items():
            if lines and (pairs or name != "repeated_pairs"):
                assert math.isclose(x[column[name]], value, rel_tol=1e-4, abs_tol=1e-5), name


def test_learned_models_on_empty_and_repeated_rows(spark):
    d = docs(spark, ["one two three"] * 3 + ["x # y"], lang=["en"] * 4)
    labels = spark.createDataFrame([(0, 1), (0, 1), (3, 0)], "doc_id long, quality int")
    model = quality.train(d, labels, F.lit(True))
    assert len(set(by_id(quality.score(d, model).where("doc_id < 3"), "score").values())) == 1
    assert quality.score(d.limit(0), model).count() == 0 and quality.score(d, quality.train(d.limit(0), labels, F.lit(True))).count() == 4


def test_transport_stream_by_an_independent_reader():
    """A plain reader, packet by packet from the standard's layout: tables, adaptation fields, counters, elementary packets."""
    payload = media_ts.padded(random.Random(3).randbytes(70_000))
    stream, out, last, pid, map_pid = media_ts.mux(payload), [], None, None, None
    for at in range(0, len(stream), 188):
        p = stream[at : at + 188]
        assert p[0] == 0x47
        number, begins, has_field, has_body = (p[1] & 31) << 8 | p[2], p[1] >> 6 & 1, p[3] >> 5 & 1, p[3] >> 4 & 1
        body = p[4 + (1 + p[4] if has_field else 0) :] if has_body else b""
        if number == 0 and map_pid is None:
            section = body[1 + body[0] :]
            assert section[0] == 0
            map_pid = (section[10] & 31) << 8 | section[11]
        elif number == map_pid and pid is None:
            section = body[1 + body[0] :]
            assert section[0] == 2
            skip = (section[10] & 15) << 8 | section[11]
            pid = (section[13 + skip] & 31) << 8 | section[14 + skip]
        elif number == pid and pid is not None:
            assert last is None or p[3] & 15 == (last + 1) % 16
            last = p[3] & 15
            if begins:
                assert body[:3] == b"\0\0\1"
                out.append(b"")
            out[-1] += body
    assert b"".join(x[9 + x[8] :] for x in out) == payload
    for x in out:
        size = x[4] << 8 | x[5]
        assert size in (0, len(x) - 6)


def test_media_without_rows_and_null(spark):
    empty = media_ts.store_texts(docs(spark, ["a"]).limit(0))
    assert media_ts.read_media(empty).count() == 0
    null = spark.createDataFrame([(1, 0, None)], "doc_id long, n_bytes long, media binary")
    row = media_ts.read_media(null).first()
    assert row["payload"] is None and row["media_sha256"] is None and row["timestamps"] is None


def test_many_draws(spark):
    """More draws than 64, all different, and no unit's draws repeat another's."""
    rows = sp_sampling.sample(docs(spark, ["several words that can be cut in many ways"]), k=70).collect()
    assert len({tuple(r["token_ids"]) for r in rows}) == 70 and [r["perturbed"] for r in sorted(rows, key=lambda r: r["draw"])] == sorted((r["perturbed"] for r in rows), reverse=True)


def test_texts_over_one_slice(spark):
    """A text of several slices' size, whole, beside short ones."""
    rng = random.Random(6)
    long = " ".join(f"w{rng.randrange(50_000)}" for _ in range(60_000))
    assert len(long) > 256 * 1024
    texts = [long, "short one", long + " tail", None]
    d = docs(spark, texts, source=["s"] * 4, lang=["en"] * 4)
    assert by_id(substring_dedup.remove_repeats(d), "n_words", "n_removed") == {0: (60_000, 0), 1: (2, 0), 2: (60_001, 60_000), 3: (0, 0)}
    assert by_id(ngram_join.near_copies(d), "component_id") == {0: 0, 1: 1, 2: 0, 3: 3}
    items = spark.createDataFrame([(7, " ".join(long.split()[59_900:59_960])), (8, "nothing of this is there at all in the text")], "item_id long, text string")
    assert sorted((r["doc_id"], r["item_id"], r["first_word"]) for r in decontaminate.find_items(d, items).collect()) == [(0, 7, 59_900), (2, 7, 59_900)]
    assert by_id(media_ts.read_media(media_ts.store_texts(d)), "n_bytes")[2] == len(texts[2])
    assert by_id(token_counts.with_counts(d), "n_bytes") == {i: len(t or "") for i, t in enumerate(texts)}
    assert by_id(sp_sampling.decode(sp_sampling.encode(d)), "decoded")[0] == long
