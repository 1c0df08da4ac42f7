"""Language identification with string kernels.

Two texts' kernel is the number of byte n-grams of 2 to 5 bytes (a blended spectrum) that both contain,
counted once however often they occur, over the square root of the product of their own counts. N-grams
are folded into 2**18 buckets, of which the `features` most frequent of the training sample are kept.
Landmark texts give the Nyström features K_xm (K_mm)^(-1/2); on these, one ridge regression per language
learns +1 against -1. Scoring is two matrix products for each slice of texts.

Training looks at a bounded sample: `per_language` rows of each language in expectation, picked by a hash of
the key; its size doesn't grow with the corpus. Scoring covers every row's whole text.

Defined results: a null text, or one without any letter, is `und` with score 0; ties go to the alphabetically
first language; repeated rows get equal predictions; without any training row, everything is `und`.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from symseek.llm.common import column_of, map_texts, records, text_bytes, uniform

UNDETERMINED = "und"
_BUCKET_BITS = 18
_LENGTHS = (2, 3, 4, 5)
#: ASCII letters in lower case, the bytes of other characters as they are, anything else a space.
_FOLD = np.full(256, 0x20, np.uint8)
_FOLD[0x80:] = np.arange(0x80, 256)
_FOLD[0x61:0x7B] = np.arange(0x61, 0x7B)
_FOLD[0x41:0x5B] = np.arange(0x61, 0x7B)


def _buckets(data: np.ndarray, offsets: np.ndarray, length: int) -> np.ndarray:
    """The bucket of the n-gram at each byte; -1 where it would leave its text."""
    n = len(data)
    out = np.full(n, -1, np.int64)
    if n < length:
        return out
    code = np.full(n - length + 1, length, np.uint32)
    for k in range(length):
        code *= np.uint32(0x01000193)
        code += data[k : n - length + 1 + k]
    code *= np.uint32(0x9E3779B1)
    out[: n - length + 1] = code >> np.uint32(32 - _BUCKET_BITS)
    for back in range(1, length):
        at = offsets[1:] - back
        out[at[at >= offsets[:-1]]] = -1
    return out


def presence(column: pa.Array, feature_of: np.ndarray, features: int) -> np.ndarray:
    """One row per text with 1 for each kept n-gram that it contains; feature_of maps a bucket to its feature or -1."""
    data, offsets = text_bytes(pc.utf8_lower(column))
    data = _FOLD[data]
    row = np.repeat(np.arange(len(column)), np.diff(offsets))
    out = np.zeros((len(column), features), np.float32)
    for length in _LENGTHS:
        at = _buckets(data, offsets, length)
        feature = np.where(at >= 0, feature_of[at], -1)
        hit = np.flatnonzero(feature >= 0)
        out[row[hit], feature[hit]] = 1
    return out


@dataclass
class KernelModel:
    languages: list[str]
    feature_of: np.ndarray  # bucket -> feature
    landmarks: np.ndarray  # landmark x feature, divided by the root of its count
    weights: np.ndarray  # landmark x language

    def kernel(self, texts: pa.Array) -> np.ndarray:
        present = presence(texts, self.feature_of, self.landmarks.shape[1])
        own = np.sqrt(np.maximum(present.sum(1), 1))
        return present @ self.landmarks.T / own[:, None]

    def predict(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Index of the best language and its share of a softmax over the one-versus-rest outputs."""
        out = (self.kernel(texts) @ self.weights).astype(np.float64)
        best = out.argmax(1)
        share = np.exp(4 * (out - out.max(1, keepdims=True)))
        return best, share[np.arange(len(best)), best] / share.sum(1)


def fit(texts: list[str], languages: list[str], *, features: int = 8192, landmarks: int = 192, ridge: float = 1e-3) -> KernelModel:
    """Nyström kernel ridge regression, one versus rest. The order of the rows decides the landmarks: each language gives its first ones."""
    names = sorted(set(languages))
    y = np.array([names.index(x) for x in languages])
    column = pa.array(texts, pa.string())
    slices = [column.slice(i, 64) for i in range(0, len(column), 64)]
    seen = np.zeros(1 << _BUCKET_BITS, np.int64)
    for part in slices:
        data, offsets = text_bytes(pc.utf8_lower(part))
        row = np.repeat(np.arange(len(part)), np.diff(offsets))
        for length in _LENGTHS:
            at = _buckets(_FOLD[data], offsets, length)
            pair = np.unique(row[at >= 0] << _BUCKET_BITS | at[at >= 0])
            seen += np.bincount(pair & (1 << _BUCKET_BITS) - 1, minlength=len(seen))
    kept = np.argsort(-seen, kind="stable")[:features]
    kept = kept[seen[kept] > 0]
    feature_of = np.full(len(seen), -1, np.int32)
    feature_of[kept] = np.arange(len(kept))

    chosen = np.concatenate([np.flatnonzero(y == c)[: max(1, landmarks // len(names))] for c in range(len(names))])
    marks = presence(column.take(pa.array(chosen)), feature_of, len(kept))
    marks /= np.sqrt(np.maximum(marks.sum(1, keepdims=True), 1))
    model = KernelModel(names, feature_of, marks, np.zeros((len(chosen), len(names)), np.float32))

    value, vector = np.linalg.eigh((marks @ marks.T).astype(np.float64))
    value = np.maximum(value, 1e-6 * max(value.max(), 1e-6))
    root = vector / np.sqrt(value) @ vector.T
    mapped = np.concatenate([model.kernel(part) for part in slices]) @ root
    target = np.where(y[:, None] == np.arange(len(names)), 1.0, -1.0)
    share = 1 / np.bincount(y)[y]  # rows count so that each language weighs the same
    gram = (mapped * share[:, None]).T @ mapped + ridge * np.eye(len(chosen))
    model.weights = (root @ np.linalg.solve(gram, (mapped * share[:, None]).T @ target)).astype(np.float32)
    return model


def train(df: DataFrame, usable: Column, *, key: str = "doc_id", text: str = "text", lang: str = "lang", per_language: int = 400, **options) -> KernelModel | None:
    """Fit on rows where `usable` holds and text and language are there; two narrow or filtered scans, a bounded sample to the driver."""
    rows = df.where(usable & F.col(lang).isNotNull() & F.col(text).isNotNull() & F.col(text).rlike("\\p{L}")).select(key, text, lang)
    counts = {r[0]: r[1] for r in df.where(usable & F.col(lang).isNotNull()).groupBy(lang).count().collect()}  # one row per language
    if not counts:
        return None
    draw = uniform(F.col(key), 1)
    share = F.coalesce(*[F.when(F.col(lang) == name, F.lit(min(1.0, 1.3 * per_language / n))) for name, n in sorted(counts.items())])
    sample = sorted(rows.where(draw < share).select(draw.alias("draw"), text, lang).collect(), key=lambda r: (r[0], r[1]))
    return fit([r[1] for r in sample], [r[2] for r in sample], **options) if sample else None


def identify(df: DataFrame, model: KernelModel | None, *, key: str = "doc_id", text: str = "text", keep: dict[str, Column] | None = None) -> DataFrame:
    """key, the columns of `keep`, lang_pred and score for every row."""
    keep = keep or {}
    names_kept = list(keep)
    has_letter = F.coalesce(F.col(text).rlike("\\p{L}"), F.lit(False))
    rows = df.select(F.col(key).alias("k"), *[c.alias(n) for n, c in keep.items()], has_letter.alias("lettered"), F.col(text).alias("body"))
    if model is None:
        return rows.select(F.col("k").alias(key), *keep, F.lit(UNDETERMINED).alias("lang_pred"), F.lit(0.0).alias("score"))
    shared = df.sparkSession.sparkContext.broadcast(model)

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        m = shared.value
        best, score = m.predict(column_of(batch, "body"))
        lettered = column_of(batch, "lettered").to_numpy(zero_copy_only=False).astype(bool)
        names = np.array([*m.languages, UNDETERMINED], dtype=object)[np.where(lettered, best, len(m.languages))]
        return records(k=column_of(batch, "k"), **{n: column_of(batch, n) for n in names_kept}, lang_pred=pa.array(names, pa.string()), score=np.where(lettered, score, 0.0))

    kinds = dict(rows.dtypes)
    schema = ", ".join([f"k {kinds['k']}", *[f"`{n}` {kinds[n]}" for n in keep], "lang_pred string", "score double"])
    return map_texts(rows, step, schema, text="body").withColumnRenamed("k", key)
