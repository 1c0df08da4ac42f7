"""Files as tables and streams of symbols, with schemas that are stated and checked, never guessed."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from symseek.sources.streams import text_streams


def _schema(schema: str | T.StructType) -> T.StructType:
    return T._parse_datatype_string(schema) if isinstance(schema, str) else schema


def read_table(spark: SparkSession, path: str, schema: str | T.StructType) -> DataFrame:
    """A Parquet table that must have these columns with these types; other columns aren't read."""
    df = spark.read.parquet(path)
    have = {f.name: f.dataType for f in df.schema}
    for want in _schema(schema):
        if want.name not in have:
            raise ValueError(f"{path} has no column {want.name}")
        if have[want.name] != want.dataType:
            raise ValueError(f"column {want.name} of {path} is {have[want.name].simpleString()}, not {want.dataType.simpleString()}")
    return df.select(*[f"`{f.name}`" for f in _schema(schema)])


def read_texts(spark: SparkSession, path: str) -> DataFrame:
    """Each file as one stream, its path's hash the stream_id: (stream_id, n, text). For files that fit into memory."""
    rows = spark.read.text(path, wholetext=True).withColumn("file", F.input_file_name())
    return text_streams(rows, F.xxhash64("file"), F.col("value"))


def read_fasta(spark: SparkSession, path: str) -> DataFrame:
    """Records of a header line with > and lines of symbols: name, stream_id (the name's hash), n, text. Large files are split between records."""
    rows = spark.read.option("lineSep", "\n>").text(path).where(F.trim("value") != "")
    record = F.regexp_replace("value", r"^>", "")
    name = F.trim(F.regexp_extract(record, r"^([^\r\n]*)", 1))
    text = F.regexp_replace(F.regexp_replace(record, r"^[^\n]*(\n|$)", ""), r"\s", "")
    return rows.select(name.alias("name"), F.xxhash64(name).alias("stream_id"), text.alias("text")).select("name", "stream_id", F.char_length("text").cast("long").alias("n"), "text")


def read_json(spark: SparkSession, path: str, schema: str) -> DataFrame:
    """One JSON object a line. A line that isn't one raises."""
    return spark.read.schema(schema).option("mode", "FAILFAST").json(path)


def read_csv(spark: SparkSession, path: str, schema: str, *, header: bool = True) -> DataFrame:
    """CSV rows. A row that doesn't fit, or another header, raises."""
    return spark.read.schema(schema).option("mode", "FAILFAST").option("header", header).option("enforceSchema", not header).csv(path)


def file_stream(spark: SparkSession, path: str, schema: str, *, files_per_trigger: int = 1) -> DataFrame:
    """A folder of Parquet files as they come."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def rate_stream(spark: SparkSession, alphabet: str, *, streams: int = 1, rows_per_second: int = 1_000) -> DataFrame:
    """A load of symbols for tests of endurance: id, ts, stream, sym; the symbol and the stream follow from the row's number."""
    if not alphabet:
        raise ValueError("an alphabet has at least one symbol")
    rows = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return rows.select(F.col("value").alias("id"), F.col("timestamp").alias("ts"), F.pmod("value", F.lit(streams)).alias("stream"), letter_of(F.col("value"), alphabet).alias("sym"))


def letter_of(number: Column, alphabet: str) -> Column:
    """A letter that a number draws from an alphabet."""
    return F.substr(F.lit(alphabet), (F.pmod(F.xxhash64(number), F.lit(len(alphabet))) + 1).cast("int"), F.lit(1))
