"""Token counts as delta-maintained rollups.

A change is a signed row: +1 for an inserted document, -1 for a deleted one, and for a revised one both, with
the old and the new token counts. A batch of changes is summed to one row per (source, lang, tokenizer version)
and committed under the batch's id; totals are sums over the committed batches.

A commit is idempotent: the batch's sums go to a file set of their own, and then a new manifest names it with the
batch's id. The last KEPT manifests stay, for readers that are a little behind. Repeating a commit of a batch that is already there changes nothing; a commit that broke off before its
manifest isn't counted, and repeating it counts once. Compaction replaces all file sets by one in the same way.

Tokens are those of a byte-level BPE vocabulary file. The version names file and pattern, so totals of two
tokenizers don't mix.

Defined results: a null or empty text has 0 tokens but counts as a document; null source or lang is a group of
its own; repeated rows count once each; groups whose documents are all deleted stay with zeros until compaction drops
them; an empty batch commits only its id.
"""

from __future__ import annotations

import base64
import json
import posixpath
import uuid
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from symseek.llm.common import column_of, map_texts, records, shared_folder

VOCABULARY = "/opt/tokenizers/byte_bpe_50k.tiktoken"
VERSION = "byte_bpe_50k/1"
# Fixed value: the vocabulary's splitting pattern.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
GROUP = ("source", "lang", "version")
#: Manifests that stay.
KEPT = 32
_SUMS = "source string, lang string, version string, docs long, tokens long, bytes long"


@lru_cache(maxsize=4)
def _pieces(vocabulary: str):
    """The vocabulary's encoder. A private copy per worker process, read from the given path."""
    import tiktoken

    with open(vocabulary, "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    return tiktoken.Encoding(posixpath.basename(vocabulary), pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})


def with_counts(df: DataFrame, *, text: str = "text", vocabulary: str = VOCABULARY, keep: tuple[str, ...] = ("doc_id", "source", "lang")) -> DataFrame:
    """The columns of `keep`, n_tokens and n_bytes of each whole text."""
    rows = df.select(*[F.col(c) for c in keep], F.col(text).alias("body"))

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        encode = _pieces(vocabulary).encode_ordinary
        texts = [x or "" for x in column_of(batch, "body").to_pylist()]
        return records(**{c: column_of(batch, c) for c in keep}, n_tokens=pa.array([len(encode(x)) for x in texts], pa.int64()), n_bytes=pa.array([len(x.encode()) for x in texts], pa.int64()))

    kinds = dict(rows.dtypes)
    return map_texts(rows, step, ", ".join([f"`{c}` {kinds[c]}" for c in keep]) + ", n_tokens long, n_bytes long", text="body")


def changes(counted: DataFrame, sign: int | Column, version: str = VERSION) -> DataFrame:
    """Insertions (+1) or deletions (-1) of counted documents. A column says how many documents with these counts a row stands for."""
    return counted.select("source", "lang", F.lit(version).alias("version"), F.lit(sign).cast("long").alias("sign"), "n_tokens", "n_bytes")


def revisions(old: DataFrame, new: DataFrame, version: str = VERSION) -> DataFrame:
    """Documents whose counts are revised: the old ones leave, the new ones come."""
    return changes(old, -1, version).unionByName(changes(new, +1, version))


class TokenRollup:
    """Additive totals under one folder that driver and executors share.

    The state is the manifest with the highest number: the batches that count and the file sets that hold their sums.
    """

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")

    def _at(self, path: str):
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{path}")
        return path.getFileSystem(self.spark._jsc.hadoopConfiguration()), path

    def _state(self) -> tuple[int, dict]:
        fs, folder = self._at("manifests")
        numbers = [int(x.getPath().getName()) for x in fs.listStatus(folder)] if fs.exists(folder) else []
        if not numbers:
            return 0, {"batches": [], "sets": []}
        stream = fs.open(self._at(f"manifests/{max(numbers)}")[1])
        try:
            return max(numbers), json.loads(self.spark._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        finally:
            stream.close()

    def _advance(self, number: int, state: dict) -> None:
        """Publish the next manifest whole: it is written aside, then renamed. Fails if another writer was first."""
        fs, aside = self._at(f"pending/{uuid.uuid4().hex}")
        out = fs.create(aside, True)
        out.write(json.dumps(state).encode())
        out.close()
        _, target = self._at(f"manifests/{number}")
        fs.mkdirs(target.getParent())
        if fs.exists(target) or not fs.rename(aside, target):
            raise RuntimeError("another writer committed first; read the totals again and repeat the commit")
        if number > KEPT:
            fs.delete(self._at(f"manifests/{number - KEPT}")[1], False)

    def _write(self, sums: DataFrame, name: str) -> None:
        sums.write.mode("overwrite").parquet(f"{self.root}/sums/{name}")

    def committed(self) -> list[str]:
        return self._state()[1]["batches"]

    def commit(self, batch_id: str, signed: DataFrame) -> bool:
        """Add a batch of signed changes. False, and nothing done, if the batch is already there."""
        number, state = self._state()
        if batch_id in state["batches"]:
            return False
        name = uuid.uuid4().hex
        self._write(
            signed.groupBy(*GROUP).agg(
                F.sum("sign").cast("long").alias("docs"), F.sum(F.col("sign") * F.col("n_tokens")).cast("long").alias("tokens"), F.sum(F.col("sign") * F.col("n_bytes")).cast("long").alias("bytes")
            ),
            name,
        )
        self._advance(number + 1, {"batches": [*state["batches"], batch_id], "sets": [*state["sets"], name]})
        return True

    def totals(self) -> DataFrame:
        """source, lang, version, docs, tokens, bytes over all committed batches."""
        sets = self._state()[1]["sets"]
        parts = self.spark.read.schema(_SUMS).parquet(*[f"{self.root}/sums/{n}" for n in sets]) if sets else self.spark.createDataFrame([], _SUMS)
        return parts.groupBy(*GROUP).agg(*[F.sum(c).cast("long").alias(c) for c in ("docs", "tokens", "bytes")])

    def compact(self) -> None:
        """Fold all file sets into one, without groups that are all zero. Readers see the state before or after."""
        number, state = self._state()
        if len(state["sets"]) > 1:
            name = uuid.uuid4().hex
            self._write(self.totals().where("docs <> 0 or tokens <> 0 or bytes <> 0"), name)
            self._advance(number + 1, {"batches": state["batches"], "sets": [name]})


def new_rollup(spark: SparkSession) -> TokenRollup:
    return TokenRollup(spark, posixpath.join(shared_folder(spark), f"token-rollup-{uuid.uuid4().hex}"))
