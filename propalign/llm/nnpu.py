"""Positive-unlabelled quality classifier with the non-negative risk.

A linear model over counts of a text (bytes, words, lines) is fitted to trusted positives and unlabelled web text. With
the class prior p, the risk is ``p * E+[loss(+)] + max(0, Eu[loss(-)] - p * E+[loss(-)])``; where the second part would fall
below zero, its gradient is stepped up instead, which keeps the model from fitting the unlabelled sample. Labels
``quality = 1`` are the positives; the corpus as it is, whatever its labels, is the unlabelled text; the prior is the share of
positives among labels of the training folds.

The fit sees at most ``POSITIVES`` and ``UNLABELLED`` documents of the training folds, those with the smallest hashes of their
ids: a bounded, documented sample. Every document is scored, by its whole text.

Edge cases: a null or empty text scores by its (zero) counts; a null id is never held out. Without positives or other
documents in the training folds every score is the prior (0.5 without labels). Rows and ids may repeat; of an id with many rows
the fit sees one. No documents give no rows. Columns may have any name; one that is called like the score is replaced.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from propalign.llm.bytes_np import give_back, slices
from propalign.llm.tables import kept_columns, schema_with

POSITIVES = 6_000
UNLABELLED = 12_000
#: Learning labels from this share of folds: crc32 of the id as text, modulo FOLDS; HELD is the fold never learned from.
FOLDS, HELD = 3, 1
_BYTES = 256
_MORE = 14


def held_out(key: Column) -> Column:
    return F.coalesce(F.pmod(F.crc32(key.cast("string").cast("binary")), F.lit(FOLDS)) == HELD, F.lit(False))


def text_features(text: str | None) -> np.ndarray:
    """Roots of byte shares, and shares and logarithms of words, repeats and lines, of the whole text."""
    out = np.zeros(_BYTES + _MORE, dtype=np.float32)
    raw = (text or "").encode("utf-8", "surrogatepass")
    n = len(raw)
    if not n:
        return out
    counts = np.bincount(np.frombuffer(raw, dtype=np.uint8), minlength=_BYTES)
    out[:_BYTES] = np.sqrt(counts / n)
    words = raw.split()
    distinct = set(words)
    lines = [x for x in raw.split(b"\n") if x.strip()]
    w, k = max(1, len(words)), max(1, len(lines))
    chars = n - int(counts[[32, 9, 10, 11, 12, 13]].sum())
    upper, lower, digits = int(counts[65:91].sum()), int(counts[97:123].sum()), int(counts[48:58].sum())
    high = int(counts[128:].sum())
    marks = max(0, chars - upper - lower - digits - high)
    common = int(counts[[44, 46]].sum())
    out[_BYTES:] = (
        np.log1p(w) / 5, np.log1p(k) / 5, chars / w / 10, len(distinct) / w, len(set(lines)) / k, upper / max(1, chars), digits / max(1, chars),
        marks / w, (marks - common) / w, min(1.0, w / 50), np.log1p(w / k) / 5, high / max(1, chars), sum(map(len, distinct)) / max(1, len(distinct)) / 10, 1.0,
    )
    return out


def features(rows: DataFrame) -> DataFrame:
    """(row, features as float32 bytes) of (row, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (s for whole in batches for s in slices(whole, 1)):
            found = [text_features(x).tobytes() for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(found, pa.binary())], names=["row", "features"])
        give_back()

    return rows.mapInArrow(run, schema_with([rows.schema["row"]], "features binary"))


def fit_nnpu(positive: np.ndarray, unlabelled: np.ndarray, prior: float, steps: int = 1500, rate: float = 0.02, decay: float = 1e-4) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(weights with the intercept last, mean, scale) that minimise the non-negative unbiased risk of the logistic loss."""
    every = np.concatenate([positive, unlabelled])
    mean, scale = every.mean(0), every.std(0) + 1e-3
    p = np.c_[np.clip((positive - mean) / scale, -8, 8), np.ones(len(positive))]
    u = np.c_[np.clip((unlabelled - mean) / scale, -8, 8), np.ones(len(unlabelled))]
    w = np.zeros(p.shape[1])
    w[-1] = np.log(prior / (1 - prior))
    first, second = np.zeros_like(w), np.zeros_like(w)
    sigmoid = lambda z: 1 / (1 + np.exp(-np.clip(z, -35, 35)))
    for t in range(1, steps + 1):
        zp, zu = p @ w, u @ w
        gain = -prior * ((1 - sigmoid(zp)) @ p) / len(p)  # of p * E+[loss(+)]
        rest = np.logaddexp(0, zu).mean() - prior * np.logaddexp(0, zp).mean()
        slope = sigmoid(zu) @ u / len(u) - prior * (sigmoid(zp) @ p) / len(p)
        grad = gain + slope if rest >= 0 else -slope
        grad[:-1] += decay * w[:-1]
        first, second = 0.9 * first + 0.1 * grad, 0.999 * second + 0.001 * grad**2
        w -= rate * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-8)
    return w, mean, scale


def train(docs: DataFrame, labels: DataFrame, text: str = "text", key: str = "doc_id", good: str = "quality", positives: int = POSITIVES, unlabelled: int = UNLABELLED) -> dict:
    known = labels.where(F.col(key).isNotNull() & F.col(good).isNotNull() & ~held_out(F.col(key)))
    n, share = known.agg(F.count("*"), F.avg((F.col(good) == 1).cast("double"))).first()
    # The prior may not be 0 or 1: then one class would have no say.
    prior = float(np.clip(share, 0.02, 0.98)) if n else 0.5
    docs, known = docs.select(F.col(f"`{key}`").alias("id"), F.col(f"`{text}`").alias("text")), known.select(F.col(key).alias("id"), F.col(good).alias("good"))
    small = F.xxhash64("id")
    ids = docs.select("id").where(F.col("id").isNotNull() & ~held_out(F.col("id"))).distinct()
    chosen = {
        1: known.where("good = 1").select("id").distinct().join(ids, "id", "left_semi").orderBy(small, "id").limit(positives),
        0: ids.orderBy(small, "id").limit(unlabelled),
    }
    picked = chosen[1].withColumn("y", F.lit(1)).unionByName(chosen[0].withColumn("y", F.lit(0)))
    # At most positives + unlabelled ids, and a row of each: a fixed bound, so the broadcast and what returns are bounded.
    rows = features(docs.join(F.broadcast(picked.select("id").distinct()), "id").select(F.col("id").alias("row"), "text")).groupBy(F.col("row").alias("id")).agg(F.min("features").alias("features"))
    rows = rows.join(F.broadcast(picked), "id").select("y", "features").collect()
    x = {y: np.array([np.frombuffer(r["features"], dtype=np.float32) for r in rows if r["y"] == y], dtype=float) for y in (0, 1)}
    if not len(x[0]) or not len(x[1]):
        return {"prior": prior, "weights": None}
    w, mean, scale = fit_nnpu(x[1], x[0], prior)
    return {"prior": prior, "weights": w, "mean": mean, "scale": scale}


def score(docs: DataFrame, model: dict, text: str = "text", name: str = "score") -> DataFrame:
    """docs with the chance, by the model, that a text is of good quality."""
    # The text goes to the workers once, inside the row, unless it isn't passed on.
    kept = [f for f in docs.schema.fields if f.name.lower() != name.lower()]
    at = next((i for i, f in enumerate(kept) if f.name.lower() == text.lower() and isinstance(f.dataType, StringType)), None)
    row = F.struct(*kept_columns(docs, docs.columns, [name])).alias("row")
    rows = docs.select(row) if at is not None else docs.select(row, F.col(f"`{text}`").alias("text"))

    def with_text(whole: pa.RecordBatch) -> pa.RecordBatch:
        if whole.num_columns == 2:
            return whole
        return pa.RecordBatch.from_arrays([whole.column(0), whole.column(0).field(at)], names=["row", "text"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (s for whole in batches for s in slices(with_text(whole), 1)):
            if model["weights"] is None:
                s = np.full(b.num_rows, model["prior"])
            else:
                x = np.array([text_features(t) for t in b.column(1).to_pylist()], dtype=float).reshape(b.num_rows, -1)
                z = np.clip((x - model["mean"]) / model["scale"], -8, 8) @ model["weights"][:-1] + model["weights"][-1]
                s = 1 / (1 + np.exp(-np.clip(z, -35, 35)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(s, pa.float64())], names=["row", "found"])
        give_back()

    out = rows.mapInArrow(run, schema_with([rows.schema["row"]], "found double"))
    return out.select("row.*", F.col("found").alias(name))


def quality_classifier(docs: DataFrame, labels: DataFrame, text: str = "text", key: str = "doc_id", good: str = "quality", name: str = "score") -> DataFrame:
    """docs with the score, called name; those of 0.5 or more count as good."""
    return score(docs, train(docs, labels, text, key, good), text, name)
