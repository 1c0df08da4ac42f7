"""The streaming sifter gives what the batch sifter gives."""

import os
import random

import pytest
from pyspark.sql import functions as F

import reference
from symseek.operators.fold import Rules
from symseek.sources import files, sinks
from symseek.streaming.online import OnlineState, StreamState, sift_stream, use_rocksdb


def test_pieces_equal_whole():
    rng = random.Random(1)
    for _ in range(200):
        text = "".join(rng.choice("AB") for _ in range(rng.randint(0, 40)))
        p, k, tie = "".join(rng.choice("AB") for _ in range(rng.randint(1, 5))), rng.randint(0, 2), rng.choice(("earliest", "shortest", "latest"))
        online, out, at = OnlineState(p, k, Rules(tie=tie)), [], 0
        while at < len(text):
            step = rng.randint(1, 7)
            online = OnlineState(p, k, Rules(tie=tie), online.saved())
            out += online.feed(text[at : at + step])
            at += step
        out += online.flush()
        assert sorted(o[:3] for o in out) == reference.sift(p, text, k, tie)


@pytest.mark.parametrize("files", [1, 6])
def test_stream_equals_batch(spark, tmp_path, files):
    use_rocksdb(spark)
    rng = random.Random(files)
    rows = [(i, f"2024-01-01 00:{i // 60:02d}:{i % 60:02d}", i % 2, rng.choice("ABC")) for i in range(240)]
    texts = {u: "".join(s for _, _, v, s in rows if v == u) for u in (0, 1)}
    source, order = tmp_path / "in", list(range(240))
    chunk = 240 // files
    for f in range(files):
        part = order[f * chunk : (f + 1) * chunk]
        rng.shuffle(part)  # out of order inside the watermark
        spark.createDataFrame([rows[i] for i in part], "id long, ts string, user long, sym string").withColumn("ts", F.to_timestamp("ts")).coalesce(1).write.mode("append").parquet(str(source))
    # rows far ahead move the watermark, and let the idle timers run out
    for at in ("2024-01-02", "2024-01-03", "2024-01-04"):
        spark.createDataFrame([(1000, at, 9, "Z")], "id long, ts string, user long, sym string").withColumn("ts", F.to_timestamp("ts")).coalesce(1).write.mode("append").parquet(str(source))
    stream = spark.readStream.schema("id long, ts timestamp, user long, sym string").option("maxFilesPerTrigger", 1).parquet(str(source))
    kept = sift_stream(stream, [(0, "ABC", 1), (1, "CAB", 0)], stream_id=F.col("user"), ts="ts", order="id", symbol=F.col("sym"), watermark="10 minutes", idle_ms=60_000)
    query = kept.writeStream.format("memory").queryName(f"kept{files}").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
    query.awaitTermination(180)
    got = sorted((r["stream_id"], r["pattern_id"], r["start"], r["len"], r["dist"]) for r in spark.table(f"kept{files}").where("stream_id < 9").collect())
    expected = sorted((u, i, *o) for u, text in texts.items() for i, (p, k) in enumerate((("ABC", 1), ("CAB", 0))) for o in reference.sift(p, text, k))
    assert got == expected


def symbols(spark, rows, folder):
    """Rows (id, seconds, user, symbol) as one more file of a folder."""
    df = spark.createDataFrame(rows, "id long, at long, user long, sym string").select("id", F.timestamp_seconds("at").alias("ts"), "user", "sym")
    df.coalesce(1).write.mode("append").parquet(str(folder))


SCHEMA = "id long, ts timestamp, user long, sym string"


def test_bank_in_one_state():
    rng = random.Random(4)
    bank = {0: ("ABC", 1), 1: ("CABBA", 2), 7: ("B", 0)}
    for _ in range(60):
        text = "".join(rng.choice("ABC") for _ in range(rng.randint(0, 60)))
        state, out, at = StreamState(bank, Rules()), [], 0
        while at < len(text):
            step = rng.randint(1, 9)
            state = StreamState(bank, Rules(), state.saved())
            out += state.feed(text[at : at + step])
            at += step
            # space: the symbols of one window, and a slot for each level
            saved = state.saved()
            assert len(saved["tail"]) <= max(len(p) + k - 1 for p, k in bank.values())
            assert all(sum(x is not None for x in slots or ()) <= bank[int(i)][1] + 1 for i, (_, _, slots) in saved["own"].items())
        out += state.flush()
        assert sorted(o[:4] for o in out) == sorted((i, *r) for i, (p, k) in bank.items() for r in reference.sift(p, text, k))


@pytest.mark.parametrize(("tie", "validation"), [("shortest", "interval"), ("latest", "last_length")])
def test_rig(spark, tmp_path, tie, validation):
    """Files to micro-batches, the sifter, packed records by pattern, and a batch read; every pattern shares a stream's state, and options reach it."""
    use_rocksdb(spark)
    rng = random.Random(12)
    text = "".join(rng.choice("AB") for _ in range(150))
    for part in range(3):
        rows = [(i, 1000 + i // 2, 1, text[i]) for i in range(50 * part, 50 * part + 50)]  # two symbols a second: ties of time by id
        rng.shuffle(rows)
        symbols(spark, rows, tmp_path / "in")
    for far in (10_000, 20_000, 30_000):
        symbols(spark, [(far, far * 10, 9, "Z")], tmp_path / "in")
    stream = files.file_stream(spark, str(tmp_path / "in"), SCHEMA)
    bank = [(0, "ABBA", 1), (1, "BB", 0), (2, "BABAB", 2)]
    kept = sift_stream(stream, bank, stream_id=F.col("user"), ts="ts", order="id", symbol=F.col("sym"), watermark="5 minutes", idle_ms=60_000, tie=tie, validation=validation)
    sinks.stream_to_parquet(kept, str(tmp_path / "out"), str(tmp_path / "state"), as_records=True).awaitTermination(180)
    got = sinks.unpacked(sinks.read_by_pattern(spark, str(tmp_path / "out"))).where("stream_id = 1").collect()
    expected = sorted((i, *r) for i, p, k in bank for r in reference.sift(p, text, k, tie, validation))
    assert sorted((r["pattern_id"], r["start"], r["len"], r["dist"]) for r in got) == expected
    one = sinks.read_by_pattern(spark, str(tmp_path / "out"), 1)
    assert "PartitionFilters: [isnotnull(pattern_id" in one._jdf.queryExecution().executedPlan().toString() and one.count() == sum(r["pattern_id"] == 1 for r in got)


@pytest.mark.parametrize("late", ["drop", "side_output"])
def test_late_and_repeated_rows(spark, tmp_path, late):
    use_rocksdb(spark)
    source = tmp_path / "in"
    text = "ABCABCABC"
    symbols(spark, [(i, 1000 + i, 1, c) for i, c in enumerate(text[:6])], source)
    symbols(spark, [(100, 5000, 2, "Z"), (3, 1003, 1, text[3])], source)  # moves the watermark; one row comes again
    symbols(spark, [(50, 1004, 1, "X"), (101, 5001, 2, "Z")], source)  # far behind the watermark
    symbols(spark, [(i, 5000 + i, 1, c) for i, c in enumerate(text) if i >= 6], source)
    for far in (10_000, 20_000, 30_000):
        symbols(spark, [(far, far * 10, 9, "Z")], source)
    stream = files.file_stream(spark, str(source), SCHEMA)
    kept = sift_stream(stream, [(0, "ABC", 0)], stream_id=F.col("user"), ts="ts", order="id", symbol=F.col("sym"), watermark="10 minutes", idle_ms=100_000_000, late=late, deduplicate=True)
    sinks.stream_by_batch(kept, str(tmp_path / "out"), str(tmp_path / "state")).awaitTermination(180)
    got = spark.read.parquet(str(tmp_path / "out")).where("stream_id = 1").collect()
    assert sorted((r["start"], r["len"]) for r in got if not r["late"]) == [(0, 3), (3, 3), (6, 3)]  # the last by the idle timer
    assert [(r["decided_at"], r["dist"], r["pattern_id"]) for r in got if r["late"]] == ([(1_004_000, -1, None)] if late == "side_output" else [])


def test_files_and_sinks(spark, tmp_path):
    (tmp_path / "a.fa").write_text(">one first\nACGT\nAC\n>two\n\n>three\nGG")
    fasta = {r["name"]: (r["n"], r["text"]) for r in files.read_fasta(spark, str(tmp_path / "a.fa")).collect()}
    assert fasta == {"one first": (6, "ACGTAC"), "two": (0, ""), "three": (2, "GG")}
    (tmp_path / "t.txt").write_text("ab\ncd")
    assert [(r["n"], r["text"]) for r in files.read_texts(spark, str(tmp_path / "t.txt")).collect()] == [(5, "ab\ncd")]
    (tmp_path / "x.json").write_text('{"s": 1, "sym": "A"}\n{"s": 2}\n')
    assert [tuple(r) for r in files.read_json(spark, str(tmp_path / "x.json"), "s long, sym string").collect()] == [(1, "A"), (2, None)]
    (tmp_path / "bad.json").write_text("{")
    (tmp_path / "x.csv").write_text("s,sym\n1,A\n2,\n")
    assert [tuple(r) for r in files.read_csv(spark, str(tmp_path / "x.csv"), "s long, sym string").collect()] == [(1, "A"), (2, None)]
    for bad in (lambda: files.read_json(spark, str(tmp_path / "bad.json"), "s long"), lambda: files.read_csv(spark, str(tmp_path / "x.csv"), "other long, sym string")):
        with pytest.raises(Exception, match="(?i)malformed|header"):
            bad().collect()
    kept = spark.createDataFrame([(1, 0, 5, 3, 0), (1, 1, 70_000, 31, 7), (2, 0, 9, 2, 1)], "stream_id long, pattern_id int, start long, len int, dist int")
    out = str(tmp_path / "kept")
    sinks.write_by_pattern(kept, out)
    sinks.write_by_pattern(kept.where("stream_id = 2"), out)
    assert sinks.read_by_pattern(spark, out).count() == 4 and sinks.read_by_pattern(spark, out, 1).count() == 1
    assert sorted(map(tuple, sinks.unpacked(sinks.packed(kept)).collect())) == sorted(map(tuple, kept.collect()))
    for wrong in ((32, 0), (3, 8)):
        with pytest.raises(Exception, match="packed record"):
            sinks.packed(spark.createDataFrame([(1, 0, 5, *wrong)], kept.schema)).collect()
    assert files.read_table(spark, out, "start long, len int").columns == ["start", "len"]
    for schema in ("start int", "nothing long"):
        with pytest.raises(ValueError):
            files.read_table(spark, out, schema)
    rate = files.rate_stream(spark, "ACGT", streams=3, rows_per_second=5)
    assert rate.isStreaming and rate.columns == ["id", "ts", "stream", "sym"]
    letters = {r[0] for r in spark.range(200).select(files.letter_of(F.col("id"), "ACGT")).collect()}
    assert letters == set("ACGT")


def test_scratch_tables(spark, monkeypatch):
    from symseek.sources import scratch

    before = list(scratch._paths)
    scratch._paths.clear()
    table = scratch.written(spark.range(3), "three")
    path = scratch._paths[0]
    assert path.startswith(spark.conf.get("spark.checkpoint.dir")) and table.count() == 3 and os.path.isdir(path.removeprefix("file:"))
    assert scratch.clear(spark) == 1 and not os.path.exists(path.removeprefix("file:"))
    scratch._paths.extend(before)

    class Remote:
        sparkContext = type("Context", (), {"master": "yarn"})
        conf = type("Conf", (), {"get": staticmethod(lambda name, default=None: default)})

    with pytest.raises(ValueError, match="checkpoint"):
        scratch.shared_folder(Remote())
