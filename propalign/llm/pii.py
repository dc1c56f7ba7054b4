"""Personal data: fixed patterns, and identifiers that bootstrapped contexts discover.

The fixed patterns (email, ip, card, phone) are seeds, and so are strings of some published key formats. *Lexical patterns*
are the contexts in which a candidate stands:

* a label in front and the quote behind: the label's word, the quote that closes it if any, its separator, the value's
  quote and what follows the value, such as ``token = "_"`` or ``token": "_"``; the candidate is the value, however long;
* in prose, the two words in front (``reach me _``), and the word in front with the one behind (``account _ expires``); the
  candidate is a string of six characters or more with a digit or an @, or a seed. A string that looks like a kind but
  fails its check (a card number's, say) is known not to be one and is no candidate.

Patterns and candidates form a graph over the corpus, which Spark scores in rounds: a pattern's confidence is the (smoothed)
share of trust among its different instances, an instance's trust is that of its best pattern, seeds have 1. Patterns with
enough support and confidence then mark all their instances, most of which no fixed pattern knows.

Whole texts are searched, in time that is linear in their length. Edge cases: a null or empty text has no spans; repeated
rows are searched each; null ids pass through; no documents give no rows and no patterns. Offsets are code points, ends are
exclusive. Kinds overlap freely, as each is found by itself; a discovered span is left out only within one already found.
Columns may have any name; kept ones that are called like results are replaced.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from propalign.llm.bytes_np import slices
from propalign.llm.tables import kept_columns, materialise, schema_with

#: Kinds in their order; the last is that of discovered spans.
KINDS = ("email", "ip", "card", "phone", "secret")
#: Published key formats, whose strings are seeds.
SEED_FORMATS = [r"[0-9a-f]{40}", r"[0-9A-F]{40}", r"AKIA[0-9A-Z]{16}", r"gh[pousr]_[A-Za-z0-9]{36}", r"xox[baprs]-[A-Za-z0-9-]{10,}", r"eyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}", r"[0-9a-f]{64}"]
SUPPORT, CONFIDENCE, SMOOTH, ROUNDS = 3.0, 0.5, 1.0, 3

_domain = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
# A run of digits that fails at its start fails at every later place too; the look-behind keeps this linear.
_ip = re.compile(r"(?<![0-9])[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+")
_card = re.compile(r"[0-9](?:[ -]?[0-9])+")
_phone = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_digit = re.compile(r"[0-9]")
# A label begins where nothing of a label stands before it, which keeps the search linear.
_label = re.compile(r"(?<![\w.-])([\w.-]+)([\"'`]?)[ \t]{0,2}(=>|:=|=|:)[ \t]{0,2}([\"'`]?)([^\s\"'`,;<>()\[\]{}|/][^\s\"'`,;<>()\[\]{}|]{5,})([\"'`]?)")
_letter = re.compile(r"[^\W\d]")
_loose = re.compile(r"[^\s\"'`,;<>()\[\]{}|=:]{6,}")
_before = re.compile(r"([^\W\d_]+)[^\w\n]{1,3}\Z")
_behind = re.compile(r"[^\w\n]{1,3}([^\W\d_]+)")
#: Characters in which a context's word is looked for; a longer word is no context.
_REACH = 40
_seed = re.compile("|".join(f"(?:{x})" for x in SEED_FORMATS))
_local = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost matches: what stands before an @, back to the last match, and a domain behind it."""
    out, floor, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > floor and text[start - 1] in _local:
            start -= 1
        m = _domain.match(text, at + 1) if start < at else None
        if m:
            out.append((start, m.end()))
            floor = m.end()
        else:
            floor = max(floor, at + 1)
        at = text.find("@", floor)
    return out


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        v = int(c) * (1 + i % 2)
        total += v - 9 * (v > 9)
    return total % 10 == 0


def checked_spans(text: str) -> list[tuple[str, int, int, bool]]:
    """(kind, start, end, whether it passes its kind's check), by kind and then start."""
    out = [("email", s, e, True) for s, e in emails(text)] if "@" in text else []
    if not _digit.search(text):
        return out
    if "." in text:
        for m in _ip.finditer(text):
            out.append(("ip", *m.span(), all(len(p := x.lstrip("0")) <= 3 and int(p or 0) <= 255 for x in m[0].split("."))))
    for m in _card.finditer(text):
        if m.end() - m.start() >= 13:
            d = m[0].replace(" ", "").replace("-", "")
            if len(d) >= 13:
                out.append(("card", *m.span(), len(d) <= 19 and luhn(d)))
    if "+" in text:
        for m in _phone.finditer(text):
            if 9 <= sum(c.isdigit() and c.isascii() for c in m[0]) <= 15:
                out.append(("phone", *m.span(), True))
    return out


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """(kind, start, end), by kind and then start."""
    return [x[:3] for x in checked_spans(text) if x[3]]


def _trimmed(text: str, s: int, e: int) -> int:
    while e > s and text[e - 1] in ".!?:=#$%&*":
        e -= 1
    return e


def _prose_patterns(text: str, s: int, e: int) -> list[str]:
    before = _before.search(text, max(0, s - _REACH), s)
    if not before:
        return []
    one = before[1].lower()
    second = _before.search(text, max(0, before.start() - _REACH), before.start(1))
    behind = _behind.match(text, e, e + _REACH)
    return ([f"{second[1].lower()} {one} _"] if second else []) + ([f"{one} _ {behind[1].lower()}"] if behind else [])


def contexts(text: str, base: list[tuple[str, int, int]], refused: list[tuple[int, int]] = ()) -> list[tuple[str, str, int, int, bool]]:
    """(pattern, instance, start, end, is a seed) for every candidate in a context. refused: spans that failed a check."""
    known = {(s, e) for _, s, e in base}
    out, labelled = [], []
    if "=" in text or ":" in text:
        for m in _label.finditer(text):
            if not _letter.search(m[1]):
                continue
            s, e = m.span(5)
            e = _trimmed(text, s, e)
            value = text[s:e]
            # Identifiers hold a digit, or are an address; plain words behind a colon are prose.
            if e - s < 6 or not (_digit.search(value) or "@" in value):
                continue
            labelled.append((s, e))
            out.append((f"{m[1].lower()}{m[2]} {m[3]} {m[4]}_{m[6]}", value.lower(), s, e, (s, e) in known or _seed.fullmatch(value) is not None))
    if not base and not _digit.search(text):
        return out
    taken = sorted([*known, *refused, *labelled])
    places = [(s, e, True) for s, e in known]
    at = 0
    for m in _loose.finditer(text):
        s, e = m.span()
        while at < len(taken) and taken[at][1] <= s:
            at += 1
        if at < len(taken) and taken[at][0] < e:
            continue
        e = _trimmed(text, s, e)
        if e - s >= 6 and (_digit.search(text, s, e) or "@" in text[s:e]):
            places.append((s, e, _seed.fullmatch(text, s, e) is not None))
    for s, e, seed in places:
        out += [(p, text[s:e].lower(), s, e, seed) for p in _prose_patterns(text, s, e)]
    return out


_SPANS = "array<struct<kind: string, start: bigint, stop: bigint>>"
_SPAN = pa.struct([("kind", pa.string()), ("start", pa.int64()), ("stop", pa.int64())])
_HIT = pa.struct([("pattern", pa.string()), ("instance", pa.string()), ("start", pa.int64()), ("stop", pa.int64()), ("seed", pa.bool_())])


def scanned(docs: DataFrame, text: str, keep: list[Column]) -> DataFrame:
    """row (a struct of the columns keep), text, base spans and candidates in contexts, from one pass over each text."""
    rows = docs.select(F.struct(*keep).alias("row"), F.col(f"`{text}`").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (s for whole in batches for s in slices(whole, 1)):
            base, hits = [], []
            for x in b.column(1).to_pylist():
                found = checked_spans(x) if x else []
                good = [f[:3] for f in found if f[3]]
                base.append([{"kind": k, "start": s, "stop": e} for k, s, e in good])
                told = contexts(x, good, [(s, e) for _, s, e, ok in found if not ok]) if x else []
                hits.append([dict(zip(("pattern", "instance", "start", "stop", "seed"), h, strict=True)) for h in told])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(base, pa.list_(_SPAN)), pa.array(hits, pa.list_(_HIT))], names=["row", "base", "hits"])

    return rows.mapInArrow(run, schema_with([rows.schema["row"]], f"base {_SPANS}, hits array<struct<pattern: string, instance: string, start: bigint, stop: bigint, seed: boolean>>"))


def score_patterns(hits: DataFrame, rounds: int = ROUNDS, smooth: float = SMOOTH) -> DataFrame:
    """(pattern, instances, support, confidence) after so many rounds over the graph of patterns and instances."""
    edges = materialise(hits.groupBy("pattern", F.xxhash64("instance").alias("instance")).agg(F.max(F.col("seed").cast("double")).alias("seed")))
    instances = edges.groupBy("instance").agg(F.max("seed").alias("trust"))
    patterns = None
    for _ in range(rounds):
        trusted = materialise(instances)
        patterns = edges.join(trusted, "instance").groupBy("pattern").agg(F.count("*").alias("instances"), F.sum("trust").alias("support"))
        patterns = materialise(patterns.withColumn("confidence", F.col("support") / (F.col("instances") + smooth)))
        instances = edges.join(patterns, "pattern").groupBy("instance").agg(
            F.greatest(F.max("seed"), F.max(F.when(F.col("support") >= SUPPORT, F.col("confidence")).otherwise(0.0))).alias("trust")
        )
    return patterns


def _found(docs: DataFrame, text: str, keep: list[Column]) -> DataFrame:
    """(row, base, spans)."""
    first = materialise(scanned(docs, text, keep).withColumn("uid", F.monotonically_increasing_id()))
    hits = first.where(F.size("hits") > 0).select("uid", F.inline("hits"))
    good = materialise(score_patterns(hits).where((F.col("support") >= SUPPORT) & (F.col("confidence") >= CONFIDENCE)).select("pattern"))
    # A text's spans are bounded by its length. Several patterns may tell one span.
    more = hits.join(good, "pattern").groupBy("uid").agg(F.array_sort(F.collect_set(F.struct(F.lit(KINDS[-1]).alias("kind"), F.col("start"), F.col("stop")))).alias("more"))
    both = first.drop("hits").join(more, "uid", "left")
    fresh = F.filter("more", lambda m: ~F.exists("base", lambda b: (b["start"] <= m["start"]) & (b["stop"] >= m["stop"])))
    return both.select("row", "base", F.when(F.col("more").isNull(), F.col("base")).otherwise(F.concat("base", fresh)).alias("spans"))


def personal_data(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """keep, base and spans: arrays of (kind, start, stop), each by kind and then start. spans has the base ones too."""
    return _found(docs, text, kept_columns(docs, keep, ("base", "spans"))).select("row.*", "base", "spans")


def redact(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with each span in text replaced by its kind in angle brackets; overlapping spans become one, of the first's kind."""
    found = _found(docs, text, kept_columns(docs, docs.columns, ()))
    place = docs.columns.index(text)
    schema = found.schema["row"].dataType

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            new, cols = [], b.column(0).flatten()
            for x, spans in zip(cols[place].to_pylist(), b.column(1).to_pylist(), strict=True):
                if x and spans:
                    parts, at = [], 0
                    for s in sorted(spans, key=lambda s: (s["start"], -s["stop"])):
                        if s["start"] >= at:
                            parts += [x[at : s["start"]], f"<{s['kind'].upper()}>"]
                        at = max(at, s["stop"])
                    x = "".join(parts) + x[at:]
                new.append(x)
            cols[place] = pa.array(new, pa.string())
            yield pa.RecordBatch.from_arrays(cols, names=schema.names)

    return found.select("row", "spans").mapInArrow(run, schema)
