"""The online sifter on endless streams, in Structured Streaming.

One state per stream serves all patterns: rows that the watermark hasn't passed yet, in buckets of time; the last symbols, as many as the longest window needs; and for each pattern
the position of the next undecided start and the sifter's slots. A start is decided once lp + K symbols from it are there, and a group closes
once the next undecided start lies behind its leader. One event-time timer per stream stands at the earliest thing to do: the first waiting row, or the
end of an idle time, when the last starts are decided with the symbols that there are and pending groups close.
"""

from __future__ import annotations

import json
from collections.abc import Iterator, Sequence

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.stateful_processor import StatefulProcessor

from symseek.functions.udfs import hits_of
from symseek.operators.fold import Rules, SerialSifter
from symseek.sources.streams import MOST_PATTERNS, pattern_frame

OUTPUT = T.StructType([
    T.StructField("stream_id", T.LongType()), T.StructField("pattern_id", T.IntegerType()), T.StructField("start", T.LongType()), T.StructField("len", T.IntegerType()),
    T.StructField("dist", T.IntegerType()), T.StructField("decided_at", T.LongType()), T.StructField("late", T.BooleanType()),
])


class OnlineState:
    """The sifter over a stream that comes in pieces."""

    def __init__(self, pattern: str, k: int, rules: Rules, saved: dict | None = None):
        self.pattern, self.k = pattern, k
        saved = saved or {"tail": "", "at": 0, "leader": -1, "slots": None}
        self.tail, self.at = saved["tail"], saved["at"]
        slots = [tuple(s) if s else None for s in saved["slots"]] if saved["slots"] else []
        self.sifter = SerialSifter(k + 1, rules, saved["leader"], slots)

    def saved(self) -> dict:
        return {"tail": self.tail, "at": self.at, "leader": self.sifter.leader, "slots": self.sifter.slots}

    def feed(self, symbols: str) -> list[tuple[int, int, int, int]]:
        """Take more symbols; what is decided now."""
        self.tail += symbols
        ready = len(self.tail) - (len(self.pattern) + self.k) + 1
        return self._decide(ready) if ready > 0 else []

    def flush(self) -> list[tuple[int, int, int, int]]:
        """No more symbols for the time being: decide with what is there."""
        return self._decide(len(self.tail)) + self.sifter.close()

    def _decide(self, starts: int) -> list[tuple[int, int, int, int]]:
        out = []
        for start, length, dist in hits_of(self.tail, self.pattern, self.k):
            if start < starts:
                out += self.sifter.add(self.at + start, length, dist)
        self.tail, self.at = self.tail[starts:], self.at + starts
        if self.sifter.leader >= 0 and self.at > self.sifter.last():
            out += self.sifter.close()
        return out


class StreamState:
    """All patterns of a bank over one stream that comes in pieces. Symbols are kept once, for the pattern that is furthest behind."""

    def __init__(self, bank: dict[int, tuple[str, int]], rules: Rules, saved: dict | None = None):
        saved = saved or {"tail": "", "end": 0, "own": {}}
        self.end, tail = saved["end"], saved["tail"]
        self.online = {}
        for i, (pattern, k) in bank.items():
            at, leader, slots = saved["own"].get(str(i), (0, -1, None))
            self.online[i] = OnlineState(pattern, k, rules, {"tail": tail[len(tail) - (self.end - at) :], "at": at, "leader": leader, "slots": slots})

    def saved(self) -> dict:
        tail = max((o.tail for o in self.online.values()), key=len, default="")
        return {"tail": tail, "end": self.end, "own": {str(i): (o.at, o.sifter.leader, o.sifter.slots if o.sifter.leader >= 0 else None) for i, o in self.online.items()}}

    def feed(self, symbols: str) -> list[tuple]:
        """(pattern, start, length, distance, decided at) of what is decided now."""
        self.end += len(symbols)
        return [(i, *o) for i, online in self.online.items() for o in online.feed(symbols)]

    def flush(self) -> list[tuple]:
        return [(i, *o) for i, online in self.online.items() for o in online.flush()]


class SifterProcessor(StatefulProcessor):
    """Keyed by stream_id. Rows wait in buckets of time until the watermark has passed them, then count in the order of (time, order, symbol)."""

    def __init__(self, patterns: dict[int, tuple[str, int]], rules: Rules, idle_ms: int, late: str, bucket_ms: int = 60_000):
        self.patterns, self.rules, self.idle_ms, self.late, self.bucket_ms = patterns, rules, idle_ms, late, bucket_ms

    def init(self, handle) -> None:
        self.handle = handle
        long, string = T.StructType([T.StructField("bucket", T.LongType())]), T.StructType([T.StructField("json", T.StringType())])
        self.waiting = handle.getMapState("waiting", long, string)
        self.state = handle.getValueState("state", string)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        watermark = timerValues.getCurrentWatermarkInMs()
        new: dict[int, list] = {}
        late = []
        for part in rows:
            for row in zip(part["ms"].tolist(), part["ord"].tolist(), part["sym"].tolist(), strict=True):
                if row[0] < watermark:
                    late.append(row[0])
                else:
                    new.setdefault(row[0] // self.bucket_ms, []).append(row)
        for bucket, more in new.items():
            old = json.loads(self.waiting.getValue((bucket,))[0]) if self.waiting.containsKey((bucket,)) else []
            self.waiting.updateValue((bucket,), (json.dumps(old + more),))
        out = [(*o, False) for o in self._advance(watermark)]
        if self.late == "side_output":
            out += [(None, None, None, -1, ms, True) for ms in late]
        yield self._frame(key, out)

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        yield self._frame(key, [(*o, False) for o in self._advance(timerValues.getCurrentWatermarkInMs(), expiredTimerInfo.getExpiryTimeInMs())])

    def _advance(self, watermark: int, fired: int | None = None) -> list[tuple]:
        """Take the rows that the watermark has passed, flush if the stream is idle, and set the one timer anew."""
        saved = json.loads(self.state.get()[0]) if self.state.exists() else {"stream": None, "last": None, "timer": None}
        online, out, due = StreamState(self.patterns, self.rules, saved["stream"]), [], []
        first = None  # the earliest row that still waits
        for bucket in sorted(int(k[0]) for k in self.waiting.keys()):
            if bucket * self.bucket_ms >= watermark and first is not None:
                break
            rows = [tuple(r) for r in json.loads(self.waiting.getValue((bucket,))[0])]
            if bucket * self.bucket_ms < watermark:
                passed = [r for r in rows if r[0] < watermark]
                rest = [r for r in rows if r[0] >= watermark]
                due += passed
                if not rest:
                    self.waiting.removeKey((bucket,))
                elif passed:
                    self.waiting.updateValue((bucket,), (json.dumps(rest),))
                rows = rest
            if rows and first is None:
                first = min(r[0] for r in rows)
        if due:
            out += online.feed("".join(sym for _, _, sym in sorted(due)))
            saved["last"] = max(r[0] for r in due)
        idle_at = saved["last"] + self.idle_ms if saved["last"] is not None else None
        if idle_at is not None and idle_at <= watermark and first is None:
            out += online.flush()
            idle_at = None
        wanted = first + 1 if first is not None else idle_at
        if wanted != saved["timer"] or fired is not None:
            if saved["timer"] is not None and saved["timer"] != fired and saved["timer"] != wanted:
                self.handle.deleteTimer(saved["timer"])
            if wanted is not None:
                self.handle.registerTimer(wanted)
        self.state.update((json.dumps({"stream": online.saved(), "last": saved["last"] if idle_at is not None or first is not None else None, "timer": wanted}),))
        return out

    def _frame(self, key, out: list[tuple]) -> pd.DataFrame:
        frame = pd.DataFrame(out, columns=["pattern_id", "start", "len", "dist", "decided_at", "late"]).astype({"pattern_id": "Int32", "start": "Int64", "len": "Int32", "dist": "Int32", "decided_at": "Int64", "late": bool})
        frame.insert(0, "stream_id", int(key[0]))
        return frame

    def close(self) -> None:
        pass


def use_rocksdb(spark: SparkSession) -> None:
    """The state store that this operator needs; a setting of the running session."""
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")


def sift_stream(
    stream: DataFrame, patterns: Sequence[tuple[int, str, int]], *, stream_id: Column, ts: str, order: str, symbol: Column, watermark: str = "10 minutes", idle_ms: int = 3_600_000, late: str = "drop",
    tie: str = "earliest", validation: str = "accumulated", strict: bool = True, deduplicate: bool = False,
) -> DataFrame:
    """Occurrences in a streaming DataFrame of symbols. All patterns share a stream's state and shuffle. late: `drop` rows behind the watermark, or give them as `side_output` rows (late is true, no pattern, dist -1, decided_at
    their time in ms). deduplicate: drop rows with an `order` value that came before, inside the watermark."""
    if late not in ("drop", "side_output"):
        raise ValueError("late is 'drop' or 'side_output'")
    rows = stream.withColumn("__ts", F.col(ts).cast("timestamp")).withWatermark("__ts", watermark)
    if deduplicate:
        rows = rows.dropDuplicatesWithinWatermark([order])
    named = rows.select(stream_id.cast("long").alias("stream_id"), F.unix_millis("__ts").alias("ms"), F.col(order).cast("long").alias("ord"), symbol.alias("sym"), "__ts").where("sym is not null")
    pattern_frame(stream.sparkSession, patterns)  # checks them
    if len(patterns) > MOST_PATTERNS:
        raise ValueError(f"more than {MOST_PATTERNS} patterns")
    processor = SifterProcessor({i: (p, k) for i, p, k in patterns}, Rules(tie, validation, strict), idle_ms, late)
    return named.groupBy("stream_id").transformWithStateInPandas(processor, OUTPUT, "Append", "EventTime")
