"""Supervised baseline: a catalogue of name similarities and AdaBoost over small decision trees."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from propalign.functions.strings import all_eight, jaro_winkler, normal_py
from propalign.model import PAIR_KEY

CATALOGUE = [
    "levenshtein", "osa", "damerau", "lcs", "trigram", "trigram_cosine", "trigram_jaccard", "jaro_winkler",
    "levenshtein_share", "lcs_share", "prefix", "suffix", "contained", "word_jaccard", "word_overlap", "sound", "monge_elkan", "word_gap", "length_gap", "equal",
]
_SOUND = {c: d for d, cs in {"1": "bfpv", "2": "cgjkqsxz", "3": "dt", "4": "l", "5": "mn", "6": "r"}.items() for c in cs}


def soundex(word: str) -> str:
    out, last = word[:1].upper(), _SOUND.get(word[:1])
    for c in word[1:]:
        code = _SOUND.get(c)
        if code and code != last:
            out += code
        if c not in "hw":
            last = code
    return (out + "000")[:4]


@lru_cache(maxsize=200_000)
def catalogue(a: str, b: str) -> tuple[float, ...]:
    """Similarities of two normal names; features of the properties' place in a schema aren't among them."""
    eight = all_eight(a, b)
    x, y = a.split(), b.split()
    sx, sy = set(x), set(y)
    longest = max(len(a), len(b), 1)
    prefix = next((i for i, (p, q) in enumerate(zip(a, b, strict=False)) if p != q), min(len(a), len(b)))
    suffix = next((i for i, (p, q) in enumerate(zip(a[::-1], b[::-1], strict=False)) if p != q), min(len(a), len(b)))
    best = lambda p, q: sum(max((jaro_winkler(u, v) for v in q), default=0.0) for u in p) / max(1, len(p))
    return (
        *eight, eight[0] / longest, eight[3] / max(1, len(a) + len(b)), prefix / longest, suffix / longest, float(a in b or b in a),
        len(sx & sy) / max(1, len(sx | sy)), len(sx & sy) / max(1, min(len(sx), len(sy))), float(soundex(a) == soundex(b)), (best(x, y) + best(y, x)) / 2,
        float(abs(len(x) - len(y))), float(abs(len(a) - len(b))), float(a == b),
    )


def catalogue_matrix(names_a: list[str], names_b: list[str]) -> np.ndarray:
    return np.array([catalogue(normal_py(a), normal_py(b)) for a, b in zip(names_a, names_b, strict=True)], dtype=float).reshape(-1, len(CATALOGUE))


def _tree(x: np.ndarray, y: np.ndarray, w: np.ndarray, depth: int):
    """A weighted tree as nested tuples (feature, cut, below, above) with votes -1 or 1 at its leaves."""
    total, pos = w.sum(), w[y > 0].sum()
    leaf = 1.0 if 2 * pos >= total else -1.0
    if depth == 0 or pos <= 1e-12 or total - pos <= 1e-12:
        return leaf
    best = (min(pos, total - pos) - 1e-12, None)
    for f in range(x.shape[1]):
        order = np.argsort(x[:, f], kind="stable")
        v, s = x[order, f], np.cumsum(w[order] * y[order])
        cut = np.flatnonzero(v[1:] > v[:-1])
        if not len(cut):
            continue
        # Error with the better vote on each side: (weight - |signed sum|) / 2.
        error = (total - np.abs(s[cut]) - np.abs(s[-1] - s[cut])) / 2
        i = int(error.argmin())
        if error[i] < best[0]:
            best = (error[i], (f, (v[cut[i]] + v[cut[i] + 1]) / 2))
    if best[1] is None:
        return leaf
    f, c = best[1]
    low = x[:, f] <= c
    return f, c, _tree(x[low], y[low], w[low], depth - 1), _tree(x[~low], y[~low], w[~low], depth - 1)


def _vote(tree, x: np.ndarray) -> np.ndarray:
    if not isinstance(tree, tuple):
        return np.full(len(x), tree)
    f, c, below, above = tree
    return np.where(x[:, f] <= c, _vote(below, x), _vote(above, x))


@dataclass
class BoostedModel:
    trees: list
    votes: list[float]

    def score(self, x: np.ndarray) -> np.ndarray:
        """The share of votes for a match."""
        if not self.trees:
            return np.full(len(x), 0.5)
        s = sum(v * (_vote(t, x) > 0) for t, v in zip(self.trees, self.votes, strict=True))
        return s / sum(self.votes)

    def score_pairs(self, pairs: DataFrame, threshold: float = 0.5) -> DataFrame:
        """SIM rows of PAIR rows."""
        model = self

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                s = model.score(catalogue_matrix(b.column(2).to_pylist(), b.column(4).to_pylist()))
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(s), pa.array(s > threshold)], names=[*PAIR_KEY, "score", "is_match"])

        return pairs.select(*PAIR_KEY).mapInArrow(run, "cls string, source_a string, prop_a string, source_b string, prop_b string, score double, is_match boolean")


def fit(x: np.ndarray, y: np.ndarray, rounds: int = 50, depth: int = 2) -> BoostedModel:
    """AdaBoost: each tree is fitted to weights that its predecessors' errors have raised."""
    sign = np.where(y > 0, 1.0, -1.0)
    w = np.full(len(x), 1 / max(1, len(x)))
    trees, votes = [], []
    for _ in range(rounds if len(x) else 0):
        tree = _tree(x, sign, w, depth)
        h = _vote(tree, x)
        e = w[h != sign].sum()
        if e >= 0.5:
            break
        vote = 0.5 * np.log((1 - e) / max(e, 1e-10))
        trees.append(tree)
        votes.append(float(vote))
        if e <= 1e-10:
            break
        w *= np.exp(-vote * sign * h)
        w /= w.sum()
    return BoostedModel(trees, votes)


def fit_pairs(labelled: DataFrame, rounds: int = 50, depth: int = 2, most: int = 2_000_000) -> BoostedModel:
    """labelled: LABELLED rows, at most so many."""
    rows = labelled.select(*PAIR_KEY, "label").limit(most + 1).toPandas().sort_values(PAIR_KEY)
    if len(rows) > most:
        raise ValueError(f"more than {most} labelled pairs; sample them first")
    return fit(catalogue_matrix(rows["prop_a"].tolist(), rows["prop_b"].tolist()), rows["label"].to_numpy(), rounds, depth)
