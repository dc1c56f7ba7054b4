"""Splits of sources into training and test, for the single-domain and the transfer experiments."""

from __future__ import annotations

import hashlib
from itertools import combinations
from math import comb

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

FRACTIONS = (0.2, 0.4, 0.6, 0.8)
RUNS = 25


def training_sources(sources: list[str], fraction: float, runs: int = RUNS, seed: int = 7) -> list[tuple[str, ...]]:
    """Different subsets of sources to train on: the first sources of one shuffle after another, by hashes, until there are as
    many as asked for, or as there can be. Two sources at least make a pair."""
    m = len(sources)
    if m < 2:
        return []
    k = max(2, round(fraction * m))
    out: dict[tuple[str, ...], None] = {}
    i = 0
    while len(out) < min(runs, comb(m, k)):
        order = sorted(sources, key=lambda s: hashlib.md5(f"{seed}|{fraction}|{i}|{s}".encode()).hexdigest())  # noqa: B023
        out[tuple(sorted(order[:k]))] = None
        i += 1
    return list(out)


def splits(spark: SparkSession, dataset: str, sources: list[str], fractions: tuple[float, ...] = FRACTIONS, runs: int = RUNS, seed: int = 7) -> DataFrame:
    """SPLIT rows (dataset, fraction, run, source, in_train): a small constant table."""
    rows = []
    for f in fractions:
        for run, chosen in enumerate(training_sources(sources, f, runs, seed)):
            rows += [(dataset, f, run, s, s in chosen) for s in sorted(sources)]
    return spark.createDataFrame(rows, "dataset string, fraction double, run int, source string, in_train boolean")


def deal(pairs: DataFrame, split: DataFrame) -> DataFrame:
    """pairs for each fraction and run, with in_train: whether both sources are training sources, and seen: whether one is."""
    side = lambda s: F.broadcast(split.select(F.col("dataset").alias("cls"), "fraction", "run", F.col("source").alias(f"source_{s}"), F.col("in_train").alias(f"_{s}")))
    out = pairs.join(side("a"), ["cls", "source_a"]).join(side("b"), ["cls", "fraction", "run", "source_b"]).withColumn("dataset", F.col("cls"))
    return out.withColumns({"in_train": F.col("_a") & F.col("_b"), "seen": F.col("_a") | F.col("_b")}).drop("_a", "_b")


def transfer_combinations(datasets: tuple[str, ...] = ("goods", "party", "order", "event"), most: int = 3) -> list[tuple[str, str]]:
    """(training sets joined by +, target): every one to three other datasets for each target."""
    return [("+".join(c), t) for t in datasets for k in range(1, most + 1) for c in combinations([d for d in datasets if d != t], k)]
