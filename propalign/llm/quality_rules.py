"""Quality rules with thresholds whose false rejections are bounded.

A rule rejects a document if one of its measures lies above a cutoff. For every stratum (the language) and measure, a
fixed list of cutoffs is tried from the mildest on, against labelled documents that the list doesn't depend on. A cutoff
is allowed if the labelled good documents show, by the exact binomial tail, that it rejects at most a share ``alpha`` of good
ones: if the true share were above alpha, so few rejections among n good documents had probability at most ``level``.

Two corrections for many tests: each stratum and measure has ``delta / (strata * measures)`` as its level (Bonferroni), and
within one the cutoffs are tested in a fixed order and testing ends at the first that fails (a fixed sequence needs no
further correction). So with probability 1 - delta, all cutoffs allowed hold together; a stratum loses at most the sum of
alpha over the measures of its good documents. Since all of them hold, any choice among them does: the one taken has the
largest lead of the share of bad documents that it rejects over that of good ones (ties: the mildest); a measure whose
cutoffs have no lead gets none.

A stratum with so few good labels that no test can pass, even without a rejection, is pooled with the others of that kind;
if these have too few together, the labels of all strata are the pool's. Who is pooled depends on numbers of labels only, and
the pool is tested in the place of its strata, so no more tests are made than the level is split over. A pool's cutoffs hold
for the pool as a whole: at most the same share of its good documents is lost, but one stratum of it can lose more. Where the
pool has too few labels too, and in strata without a good label, there is no cutoff and none is lost.

Edge cases: a null or empty text has no words and fails the base rule; a null stratum is a stratum; label rows with a null
quality or id, or without a document, don't count; documents or labels may be empty, or ids repeat (each pair counts). Texts
of any length are measured whole. Only the key, the stratum and the text are read, so other columns may have any name.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from propalign.llm.tables import SPACE, materialise

#: Measures and their cutoffs, mild to strict.
CUTOFFS = {
    "symbol_share": [2.0, 1.5, 1.0, 0.8, 0.6, 0.5, 0.4, 0.3, 0.2, 0.15, 0.1],
    "dup_line_share": [0.95, 0.9, 0.8, 0.7, 0.6, 0.5, 0.4, 0.3, 0.2],
    "repeat_share": [0.45, 0.4, 0.35, 0.3, 0.25, 0.2, 0.15, 0.1],
    "word_length": [40.0, 30.0, 20.0, 15.0, 12.0, 11.0, 10.0],
    "capital_share": [0.95, 0.9, 0.8, 0.7, 0.6, 0.5, 0.4, 0.3, 0.2],
}
ALPHA = 0.02
DELTA = 0.05
#: Thresholds of at most so many strata (under 100 bytes each) are broadcast.
BROADCAST_STRATA = 50_000


def window_hash(a: Column, b: Column, c: Column) -> Column:
    return F.xxhash64(a, b, c)


def repeat_words(words: Column) -> Column:
    """The windows of three words as sorted numbers. words: an array that a projection has already made.

    Each window becomes one long, a hash shifted left with the window's place in the low bits; these are sorted as
    plain numbers, so equal windows come together.
    """
    size = F.size(words)
    bits = F.ceil(F.log2(size.cast("double"))).cast("int")
    return F.when(size < 3, F.array().cast("array<bigint>")).otherwise(
        F.sort_array(
            F.transform(
                F.sequence(F.lit(0), size - 3),
                lambda i: F.call_function(
                    "shiftleft", window_hash(F.get(words, i), F.get(words, i + 1), F.get(words, i + 2)), bits
                ).bitwiseOR(i.cast("bigint")),
            )
        )
    )


def _exact_places(words: Column) -> Column:
    """Places of windows found twice or more, by sorting the windows themselves; words hold no blank."""
    size = F.size(words)
    windows = F.array_sort(
        F.transform(F.sequence(F.lit(0), size - 3), lambda i: F.struct(F.concat_ws(" ", F.get(words, i), F.get(words, i + 1), F.get(words, i + 2)).alias("w"), i.alias("i")))
    )
    # Equal windows are neighbours; each pair tells both places.
    pairs = F.zip_with(windows, F.slice(windows, F.lit(2), size), lambda x, y: F.when(x["w"] == y["w"], F.array(x["i"], y["i"])))
    return F.array_sort(F.array_distinct(F.flatten(F.array_compact(pairs))))


def measured(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with the counts of the base rule and the measures; the text itself is used up row by row, without a shuffle."""
    word = lambda w, k: F.get(F.col("_words"), w + k)
    base = docs.withColumn("_text", F.coalesce(F.col(text), F.lit("")))
    base = base.withColumns(
        {
            "_words": F.array_remove(F.split("_text", SPACE), ""),
            "_lines": F.filter(F.split("_text", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")),
            "n_symbols": F.regexp_count("_text", F.lit(r"[#*$%&|<>]")).cast("long"),
            "_capitals": F.regexp_count("_text", F.lit(r"\p{Lu}")).cast("double"),
        }
    )
    base = base.withColumns(
        {
            "n_words": F.size("_words").cast("long"),
            "word_chars": F.length(F.array_join("_words", "")).cast("long"),
            "_n_lines": F.size("_lines").cast("long"),
            "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
            "_bits": F.ceil(F.log2(F.greatest(F.size("_words"), F.lit(2)).cast("double"))).cast("int"),
            "_keys": repeat_words(F.col("_words")),
        }
    )
    # Places of windows whose hash bits equal those of a neighbour and whose words do too.
    place = lambda k: k.bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("_bits")) - 1).cast("int")
    same_bits = lambda a, b: F.coalesce(F.call_function("shiftrightunsigned", a.bitwiseXOR(b), F.col("_bits")) == 0, F.lit(False))
    equal = lambda k, other: reduce(lambda x, y: x & y, [word(place(k), j) == word(place(other), j) for j in range(3)])
    base = base.withColumn(
        "_alike", F.filter("_keys", lambda k, i: same_bits(k, F.get("_keys", i + 1)) | same_bits(k, F.get("_keys", i - 1)))
    )
    # Different windows with equal hash bits may part equal ones; then, and only then, windows themselves are sorted.
    collide = F.exists(
        F.zip_with("_alike", F.slice("_alike", F.lit(2), F.size("_keys") + 1), lambda a, b: same_bits(a, b) & ~equal(a, b)), lambda x: x
    )
    base = base.withColumn("_places", F.when(F.coalesce(collide, F.lit(False)), _exact_places(F.col("_words"))).otherwise(F.sort_array(F.transform("_alike", place))))
    covered = F.aggregate(
        "_places",
        F.struct(F.lit(0).cast("bigint").alias("n"), F.lit(-3).alias("last")),
        lambda a, p: F.struct((a["n"] + F.least(F.lit(3), p - a["last"])).alias("n"), p.alias("last")),
        lambda a: a["n"],
    )
    base = base.withColumn("n_repeat_words", covered)
    share = lambda a, b: F.when(b > 0, a / b).otherwise(F.lit(0.0))
    n = F.col("n_words")
    return base.withColumns(
        {
            "symbol_share": share(F.col("n_symbols"), n),
            "dup_line_share": share(F.col("n_dup_lines"), F.col("_n_lines")),
            "repeat_share": share(F.col("n_repeat_words"), n),
            "word_length": share(F.col("word_chars"), n),
            "capital_share": share(F.col("_capitals"), F.col("word_chars")),
            "base_failed": (n < 50) | (100 * F.col("n_repeat_words") > 50 * n),
        }
    ).drop("_text", "_words", "_lines", "_capitals", "_n_lines", "_bits", "_keys", "_alike", "_places")


def _log_gamma(x: Column) -> Column:
    """Of x >= 1, by Stirling's series at x + 8; good to 1e-12."""
    y = x + 8
    shift = reduce(lambda a, b: a + b, [F.log(x + i) for i in range(8)])
    series = 1 / (12 * y) - 1 / (360 * F.pow(y, 3)) + 1 / (1260 * F.pow(y, 5)) - 1 / (1680 * F.pow(y, 7))
    return (y - 0.5) * F.log(y) - y + F.lit(0.9189385332046727) + series - shift


def binomial_tail(k: Column, n: Column, p: float) -> Column:
    """P(at most k of n) for chance p, exact up to rounding for k below the mean: there the j-th term from k down is at most
    exp(-j * j / (2 * k)) of the first, so those beyond sqrt(120 * k) are below any rounding and aren't summed."""
    k, n = k.cast("double"), n.cast("double")
    first = F.exp(_log_gamma(n + 1) - _log_gamma(k + 1) - _log_gamma(n - k + 1) + k * F.log(F.lit(p)) + (n - k) * F.log(F.lit(1 - p)))
    odds = F.lit((1 - p) / p)
    total = F.aggregate(
        F.sequence(F.lit(0), F.least(k, F.ceil(F.sqrt(120 * k))).cast("int")),
        F.struct(F.lit(0.0).alias("sum"), F.lit(1.0).alias("term")),
        lambda a, i: F.struct(
            (a["sum"] + a["term"]).alias("sum"),
            (a["term"] * (k - i) / (n - k + i + 1) * odds).alias("term"),
        ),
        lambda a: a["sum"],
    )
    # From the mean on, a tail is near a half or above; there no test passes.
    return F.when(k >= n * p, F.lit(1.0)).otherwise(F.least(F.lit(1.0), first * total))


def risk_thresholds(
    labelled: DataFrame, stratum: str = "lang", good: str = "quality",
    cutoffs: dict[str, list[float]] = CUTOFFS, alpha: float = ALPHA, delta: float = DELTA,
) -> DataFrame:
    """(stratum, measure, cutoff, n_good, n_rejected, p_value): the cutoff that each stratum takes of those that its labels, or
    its pool's, allow."""
    grid = [(m, i, float(c)) for m, cs in cutoffs.items() for i, c in enumerate(cs)]
    is_good = F.col(good) == 1
    counts = labelled.where(F.col(good).isNotNull() & ~F.col("base_failed")).groupBy(F.col(stratum).alias("stratum")).agg(
        F.count_if(is_good).alias("n_good"), F.count_if(~is_good).alias("n_bad"),
        *[F.count_if(is_good & (F.col(m) > c)).alias(f"good:{m}:{i}") for m, i, c in grid],
        *[F.count_if(~is_good & (F.col(m) > c)).alias(f"bad:{m}:{i}") for m, i, c in grid],
    ).where("n_good > 0")
    every = Window.partitionBy(F.lit(1))  # a row for each stratum
    counts = counts.withColumn("strata", F.count("*").over(every))
    level = F.lit(delta) / (F.col("strata") * len(cutoffs))
    few = lambda n: F.pow(F.lit(1 - alpha), n) > level  # noqa: E731  even without a rejection no test passes
    counts = counts.withColumn("_few", few(F.col("n_good")))
    counts = counts.withColumn("_all_too", few(F.coalesce(F.sum(F.when(F.col("_few"), F.col("n_good"))).over(every), F.lit(0))))
    cells = counts.select(
        "stratum", "n_good", "n_bad", "strata", "_few", "_all_too",
        F.inline(
            F.array(*[
                F.struct(F.lit(m).alias("measure"), F.lit(i).alias("step"), F.lit(c).alias("cutoff"), F.col(f"`good:{m}:{i}`").alias("n_rejected"), F.col(f"`bad:{m}:{i}`").alias("n_caught"))
                for m, i, c in grid
            ])
        ),
    )
    same = Window.partitionBy("measure", "step")  # a row for each stratum
    pooled = lambda c: F.when(F.col("_few"), F.sum(F.when(F.col("_few") | F.col("_all_too"), F.col(c))).over(same)).otherwise(F.col(c)).alias(c)
    tests = cells.select("stratum", "strata", "measure", "step", "cutoff", *[pooled(c) for c in ("n_good", "n_bad", "n_rejected", "n_caught")])
    tests = tests.withColumn("p_value", binomial_tail(F.col("n_rejected"), F.col("n_good"), alpha))
    passed = F.col("p_value") <= level
    order = Window.partitionBy("stratum", "measure").orderBy("step")
    # The lead over a common divisor is a whole number, so ties are ties in any engine.
    lead = F.col("n_caught") * F.col("n_good") - F.col("n_rejected") * F.col("n_bad")
    return (
        tests.withColumn("_all", F.min(passed.cast("int")).over(order))
        .withColumn("_lead", lead)
        .where("_all = 1 and _lead > 0")
        .groupBy("stratum", "measure")
        .agg(F.max_by(F.struct("cutoff", "n_good", "n_rejected", "p_value"), F.struct(F.col("_lead"), -F.col("step"))).alias("x"))
        .select("stratum", "measure", "x.*")
    )


def quality_rules(
    docs: DataFrame, labels: DataFrame, text: str = "text", key: str = "doc_id", stratum: str = "lang", good: str = "quality",
    cutoffs: dict[str, list[float]] = CUTOFFS, alpha: float = ALPHA, delta: float = DELTA,
) -> DataFrame:
    """(key, stratum, counts, measures, base_failed, failed: names of the measures above their cutoff, kept)."""
    counted = materialise(measured(docs.select(F.col(key).alias("_key"), F.col(stratum).alias("_stratum"), F.col(text).alias("text"))).drop("text"))
    known = labels.where(F.col(key).isNotNull() & F.col(good).isNotNull()).select(F.col(key).alias("_label_key"), F.col(good).alias("_good"))
    known = counted.join(known, F.col("_key") == F.col("_label_key"))
    taken = risk_thresholds(known, "_stratum", "_good", cutoffs, alpha, delta)
    wide = taken.groupBy("stratum").agg(*[F.max(F.when(F.col("measure") == m, F.col("cutoff"))).alias(f"_cut_{m}") for m in cutoffs])
    wide = materialise(wide)
    if wide.count() <= BROADCAST_STRATA:
        wide = F.broadcast(wide)
    out = counted.join(wide, F.col("_stratum").eqNullSafe(F.col("stratum")), "left").withColumn(
        "failed", F.array_compact(F.array(*[F.when(F.col(m) > F.col(f"_cut_{m}"), F.lit(m)) for m in cutoffs]))
    )
    out = out.withColumn("kept", ~F.col("base_failed") & (F.size("failed") == 0)).drop("stratum", *[f"_cut_{m}" for m in cutoffs])
    return out.withColumnsRenamed({"_key": key, "_stratum": stratum})
