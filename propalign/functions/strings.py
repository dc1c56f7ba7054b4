"""Eight distances of two property names.

Names are lower-cased and their separators become spaces. Those distances that Spark has or that array functions express
are columns; the others, and all eight for the classifier, are computed once for each pair of different names.
"""

from __future__ import annotations

from collections import Counter
from functools import lru_cache

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

DISTANCES = ["levenshtein", "osa", "damerau", "lcs", "trigram", "trigram_cosine", "trigram_jaccard", "jaro_winkler"]


def normal(name: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(name), r"[^\p{L}\p{N}]+", " "))


def normal_py(name: str) -> str:
    out = []
    for c in name.lower():
        if c.isalnum():
            out.append(c)
        elif out and out[-1] != " ":
            out.append(" ")
    return "".join(out).strip(" ")


def grams(s: Column) -> Column:
    """3-grams as an array, with repeats; a shorter name is its only gram, an empty one has none."""
    many = F.transform(F.sequence(F.lit(1), F.length(s) - 2), lambda i: F.substring(s, i, F.lit(3)))
    return F.when(F.length(s) >= 3, many).when(F.length(s) > 0, F.array(s)).otherwise(F.array().cast("array<string>"))


def _counts(keys: Column, g: Column) -> Column:
    return F.transform(keys, lambda k: F.size(F.filter(g, lambda x: x == k)).cast("double"))


def _dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def trigram(a: Column, b: Column) -> Column:
    keys = F.array_union(grams(a), grams(b))
    gaps = F.zip_with(_counts(keys, grams(a)), _counts(keys, grams(b)), lambda x, y: F.abs(x - y))
    return F.aggregate(gaps, F.lit(0.0), lambda s, x: s + x)


def trigram_cosine(a: Column, b: Column) -> Column:
    keys = F.array_union(grams(a), grams(b))
    x, y = _counts(keys, grams(a)), _counts(keys, grams(b))
    norm = F.sqrt(_dot(x, x) * _dot(y, y))
    return F.when(a == b, F.lit(0.0)).when(norm > 0, 1 - _dot(x, y) / norm).otherwise(F.lit(1.0))


def trigram_jaccard(a: Column, b: Column) -> Column:
    every = F.size(F.array_union(grams(a), grams(b)))
    return F.when(every > 0, 1 - F.size(F.array_intersect(grams(a), grams(b))) / every).otherwise(F.lit(0.0))


def _edits(a: str, b: str, swaps: bool) -> int:
    before, row = [0] * (len(b) + 1), list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, before, row, least = before, row, [i], i
        # Plain comparisons: min() would take most of the time.
        for j, y in enumerate(b, 1):
            other = before[j] if before[j] < least else least
            least = other + 1
            other = before[j - 1] if x == y else before[j - 1] + 1
            if other < least:
                least = other
            if swaps and i > 1 and j > 1 and x == b[j - 2] and y == a[i - 2] and last[j - 2] + 1 < least:
                least = last[j - 2] + 1
            row.append(least)
    return row[-1]


def osa(a: str, b: str) -> int:
    """Edits with swaps of neighbours, where no part is edited twice."""
    return _edits(a, b, True)


def damerau(a: str, b: str) -> int:
    """Edits with swaps of neighbours, without that restriction."""
    top = len(a) + len(b)
    table = [[top] * (len(b) + 2), [top, *range(len(b) + 1)]]
    seen: dict[str, int] = {}
    for i, x in enumerate(a, 1):
        here, last, row, least = 0, table[-1], [top, i], i
        for j, y in enumerate(b, 1):
            k, m = seen.get(y, 0), here
            if x == y:
                here = j
            # The least of four: kept or replaced, added, removed, swapped.
            other = last[j + 1] if last[j + 1] < least else least
            least = other + 1
            other = last[j] if x == y else last[j] + 1
            if other < least:
                least = other
            other = table[k][m] + i - k + j - m - 1
            if other < least:
                least = other
            row.append(least)
        table.append(row)
        seen[x] = i
    return table[-1][-1]


def lcs_distance(a: str, b: str) -> int:
    row = [0] * (len(b) + 1)
    for x in a:
        diagonal = 0
        for j, y in enumerate(b, 1):
            diagonal, row[j] = row[j], diagonal + 1 if x == y else max(row[j], row[j - 1])
    return len(a) + len(b) - 2 * row[-1]


def jaro_winkler(a: str, b: str, scale: float = 0.1) -> float:
    """Similarity in [0, 1]; made symmetric by taking the shorter name first. Equal beginnings count from 0.7 on."""
    if (len(a), a) > (len(b), b):
        a, b = b, a
    if a == b:
        return 1.0
    if not a:
        return 0.0
    reach = max(0, max(len(a), len(b)) // 2 - 1)
    used = [False] * len(b)
    hits = []
    for i, x in enumerate(a):
        for j in range(max(0, i - reach), min(len(b), i + reach + 1)):
            if not used[j] and b[j] == x:
                used[j] = True
                hits.append(x)
                break
    if not hits:
        return 0.0
    other = [b[j] for j in range(len(b)) if used[j]]
    m, swapped = len(hits), sum(x != y for x, y in zip(hits, other, strict=True)) // 2
    jaro = (m / len(a) + m / len(b) + (m - swapped) / m) / 3
    if jaro <= 0.7:
        return jaro
    prefix = 0
    for x, y in zip(a[:4], b[:4], strict=False):
        if x != y:
            break
        prefix += 1
    return jaro + prefix * scale * (1 - jaro)


def _grams_py(s: str) -> Counter:
    return Counter(s[i : i + 3] for i in range(len(s) - 2)) if len(s) >= 3 else Counter([s] if s else [])


@lru_cache(maxsize=200_000)
def all_eight(a: str, b: str) -> tuple[float, ...]:
    """The distances of two normal names, in the order of DISTANCES."""
    x, y = _grams_py(a), _grams_py(b)
    keys = x.keys() | y.keys()
    dot = sum(x[k] * y[k] for k in keys)
    norm = (sum(v * v for v in x.values()) * sum(v * v for v in y.values())) ** 0.5
    cosine = 0.0 if a == b else 1 - dot / norm if norm else 1.0
    jaccard = 1 - len(x.keys() & y.keys()) / len(keys) if keys else 0.0
    return (
        float(_edits(a, b, False)), float(osa(a, b)), float(damerau(a, b)), float(lcs_distance(a, b)),
        float(sum(abs(x[k] - y[k]) for k in keys)), cosine, jaccard, 1 - jaro_winkler(a, b),
    )


def _kernel(f):
    @F.pandas_udf("double")
    def column(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([float(f(x, y)) for x, y in zip(a, b, strict=True)])

    return column


def distance(kind: str, a: Column, b: Column) -> Column:
    """One distance of two normal names as a column."""
    native = {
        "levenshtein": lambda: F.levenshtein(a, b).cast("double"),
        "trigram": lambda: trigram(a, b), "trigram_cosine": lambda: trigram_cosine(a, b), "trigram_jaccard": lambda: trigram_jaccard(a, b),
    }
    if kind in native:
        return native[kind]()
    return _kernel({"osa": osa, "damerau": damerau, "lcs": lcs_distance, "jaro_winkler": lambda x, y: 1 - jaro_winkler(x, y)}[kind])(a, b)


def distances(pairs: DataFrame, kinds: list[str] = DISTANCES, normalise: bool = False) -> DataFrame:
    """pairs (prop_a, prop_b) with a column dist_<kind> for each kind, evaluated once for each pair of different names."""
    names = pairs.select(normal(F.col("prop_a")).alias("_a"), normal(F.col("prop_b")).alias("_b")).distinct()
    longest = F.greatest(F.length("_a"), F.length("_b"), F.lit(1))
    cols = {}
    for k in kinds:
        d = distance(k, F.col("_a"), F.col("_b"))
        cols[f"dist_{k}"] = d / longest if normalise and k in ("levenshtein", "osa", "damerau", "lcs") else d
    names = names.withColumns(cols)
    keyed = pairs.withColumns({"_na": normal(F.col("prop_a")), "_nb": normal(F.col("prop_b"))})
    return keyed.join(names, (F.col("_na") == F.col("_a")) & (F.col("_nb") == F.col("_b"))).drop("_na", "_nb", "_a", "_b")
