"""Format features of values: counts and shares of character and token types, and the number that a value is.

All are plain column expressions: they stay in the JVM and in whole-stage code.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Character types as Java patterns, in the order of the features.
CHAR_TYPES = {
    "letter": r"\p{L}", "upper": r"\p{Lu}", "lower": r"\p{Ll}", "mark": r"\p{M}", "number": r"\p{N}",
    "punctuation": r"\p{P}", "symbol": r"\p{S}", "white": r"[\p{Z}\s]",
}
CHAR_NAMES = [*CHAR_TYPES, "other"]
#: Token types, as patterns that a white-space token must have.
TOKEN_TYPES = {
    "word": r"\p{L}", "lower_start": r"^\p{Ll}", "upper_start": r"^\p{Lu}", "all_upper": r"^[^\p{Ll}]*\p{Lu}[^\p{Ll}]*$", "numeric": r"^[+-]?[0-9]+([.,][0-9]+)*$",
}
TOKEN_NAMES = list(TOKEN_TYPES)
META_NAMES = [f"{k}_{n}" for n in CHAR_NAMES for k in ("n", "share")] + [f"{k}_{n}" for n in (f"token_{t}" for t in TOKEN_NAMES) for k in ("n", "share")]
#: A text is a number only in this form; a bare cast would also take suffixes, NaN and infinities. One with an exponent is a
#: number only up to a size, since identifiers such as 12e5678 have that form too; plain digits are one as far as doubles go.
LARGEST, FINITE = 1e12, 1.7976931348623157e308
EXPONENT = "[eE]"
NUMBER = r"^[+-]?([0-9]+\.?[0-9]*|\.[0-9]+)([eE][+-]?[0-9]+)?$"


def char_counts(value: Column) -> dict[str, Column]:
    """Count of each character type. The types but upper and lower part the characters; what is left is other."""
    counts = {n: F.regexp_count(value, F.lit(p)).cast("double") for n, p in CHAR_TYPES.items()}
    parted = [counts[n] for n in ("letter", "mark", "number", "punctuation", "symbol", "white")]
    counts["other"] = F.length(value).cast("double") - sum(parted[1:], parted[0])
    return counts


def tokens(value: Column) -> Column:
    return F.filter(F.split(value, r"[\p{Z}\s]+"), lambda t: t != "")


def token_counts(toks: Column) -> dict[str, Column]:
    like = lambda p: lambda t: t.rlike(p)
    return {n: F.size(F.filter(toks, like(p))).cast("double") for n, p in TOKEN_TYPES.items()}


def numeric(value: Column, missing: float | None = -1.0) -> Column:
    x = F.trim(value)
    read = x.try_cast("double")
    most = F.when(x.rlike(EXPONENT), F.lit(LARGEST)).otherwise(F.lit(FINITE))
    got = F.when(x.rlike(NUMBER) & (F.abs(read) <= most), read)
    return got if missing is None else F.coalesce(got, F.lit(missing))


def words(text: Column, camel: bool = False) -> Column:
    """Lower-cased words: cut at everything but letters and digits, never between a digit and a letter."""
    if camel:
        text = F.regexp_replace(text, r"(\p{Ll})(\p{Lu})", "$1 $2")
    return F.filter(pieces(text), lambda w: w != "")


def pieces(text: Column) -> Column:
    """As words, with empty ones at the ends: for rows that are exploded and then filtered, which makes plainer code."""
    return F.split(F.lower(text), r"[^\p{L}\p{N}]+")


def with_meta(df: DataFrame, value: str = "value") -> DataFrame:
    """df with the 28 format features, one double column each; empty values have shares of 0."""
    share = lambda n, d: F.when(d > 0, n / d).otherwise(F.lit(0.0))
    chars = {f"n_{n}": c for n, c in char_counts(F.col(value)).items()}
    df = df.withColumns(chars | {"_length": F.length(value).cast("double"), "_tokens": tokens(F.col(value))})
    df = df.withColumns({f"n_token_{n}": c for n, c in token_counts(F.col("_tokens")).items()} | {"_n_tokens": F.size("_tokens").cast("double")})
    shares = {f"share_{n}": share(F.col(f"n_{n}"), F.col("_length")) for n in CHAR_NAMES}
    shares |= {f"share_token_{n}": share(F.col(f"n_token_{n}"), F.col("_n_tokens")) for n in TOKEN_NAMES}
    return df.withColumns(shares).drop("_length", "_tokens", "_n_tokens")


def with_numeric(df: DataFrame, value: str = "value", missing: float | None = -1.0) -> DataFrame:
    return df.withColumn("num", numeric(F.col(value), missing))


def with_tokens(df: DataFrame, value: str = "value") -> DataFrame:
    return df.withColumn("words", words(F.col(value)))
