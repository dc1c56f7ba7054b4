"""Quality rules, URL filter and mixing against plain Python."""

import math
import re
from collections import Counter

import pytest
from pyspark.sql import functions as F

from propalign.llm.mixing import emit_mix, systematic_mix
from propalign.llm.quality_rules import binomial_tail, measured, quality_rules, risk_thresholds
from propalign.llm.url_filter import rule_table, url_filter

DOCS = "doc_id long, text string, lang string, source string"


def counted(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    grams = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    often = {g for g, n in Counter(grams).items() if n > 1}
    covered = {i + j for i, g in enumerate(grams) if g in often for j in range(3)}
    lines = [x for x in (text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), len(covered)


TEXTS = [
    None, "", " \n\t ", "one", "a b c a b c", "x y z x y z x y", "é ü\x0bö | # $\n\n| #\n| #", "w " * 300, " lead and trail ",
    "\n".join(["same line here", "other", "same line here", "  ", "  "]), " ".join(str(i % 97) for i in range(400)), "a b c d " * 3 + "e f g h a b c",
]


def test_base_measures(spark):
    docs = spark.createDataFrame([(i, t, "en", "s") for i, t in enumerate(TEXTS)], DOCS)
    got = {r["doc_id"]: r for r in measured(docs).collect()}
    for i, t in enumerate(TEXTS):
        n = counted(t)
        assert tuple(got[i][c] for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")) == n, (i, t)
        assert got[i]["base_failed"] == (n[0] < 50 or 100 * n[4] > 50 * n[0])


def test_binomial_tail(spark):
    cases = [(0, 100), (1, 100), (3, 1000), (0, 1), (7, 5000), (20, 9000)]
    got = spark.createDataFrame(cases, "k long, n long").select("k", "n", binomial_tail(F.col("k"), F.col("n"), 0.004).alias("p")).collect()
    for r in got:
        k, n = r["k"], r["n"]
        want = sum(math.comb(n, i) * 0.004**i * 0.996 ** (n - i) for i in range(k + 1))
        assert r["p"] == pytest.approx(want, rel=1e-8) or (k >= n * 0.004 and r["p"] == 1.0)


def test_binomial_tail_with_many_terms(spark):
    """No number of terms is too large: exact tails by logarithms, term by term."""
    cases = [(2500, 200_000), (19_500, 1_000_000), (199_000, 10_000_000)]
    got = spark.createDataFrame(cases, "k long, n long").select("k", "n", binomial_tail(F.col("k"), F.col("n"), 0.02).alias("p")).collect()
    for r in got:
        k, n = r["k"], r["n"]
        logs = [math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * math.log(0.02) + (n - i) * math.log(0.98) for i in range(k + 1)]
        assert r["p"] == pytest.approx(math.fsum(map(math.exp, logs)), rel=1e-6), (k, n)


def test_repeated_words_when_hashes_collide(spark, monkeypatch):
    """Windows that a bad hash throws together, with equal ones apart, are told apart by their words."""
    import propalign.llm.quality_rules as qr

    monkeypatch.setattr(qr, "window_hash", lambda a, b, c: F.length(a).cast("bigint"))
    test_base_measures(spark)


def test_thresholds_bound_false_rejections(spark):
    # Bad documents have many symbols, good ones none; enough labels in one stratum, few in another.
    good = " ".join(f"w{i}" for i in range(60))
    bad = " ".join(f"w{i}###" for i in range(60))
    rows = [(i, good if i % 4 else bad, "en", "s") for i in range(8000)] + [(9000 + i, bad, "xx", "s") for i in range(5)]
    labels = spark.createDataFrame([(i, 1 if i % 4 else 0) for i in range(8000)] + [(None, 1), (3, None)], "doc_id long, quality int")
    docs = spark.createDataFrame(rows, DOCS)
    out = quality_rules(docs, labels)
    kept = {(r["lang"], r["text_bad"], r["kept"]) for r in out.select("lang", (F.col("n_symbols") > 0).alias("text_bad"), "kept").distinct().collect()}
    assert kept == {("en", False, True), ("en", True, False), ("xx", True, True)}
    known = out.join(labels.where("doc_id is not null and quality is not null").select("doc_id", "quality"), "doc_id")
    taken = {(r["stratum"], r["measure"]): r for r in risk_thresholds(known, "lang", "quality").collect()}
    assert set(taken) == {("en", "symbol_share")}  # no other measure tells good from bad
    assert taken["en", "symbol_share"]["cutoff"] == 2.0 and taken["en", "symbol_share"]["n_rejected"] == 0 and taken["en", "symbol_share"]["p_value"] < 0.01


def test_false_rejections_on_other_labels(spark):
    """Cutoffs learned from one half of the labels lose no more good documents of the other half than they may."""
    import propalign.llm.quality_rules as qr

    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    half = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(2)) == 0
    out = quality_rules(docs, labels.where(half)).join(labels.where(~half).select("doc_id", "quality"), "doc_id").where("not base_failed")
    share = {r["quality"]: (r["n"], r["lost"] / r["n"]) for r in out.groupBy("quality").agg(F.count("*").alias("n"), F.count_if(~F.col("kept")).alias("lost")).collect()}
    assert share[1][0] > 1000 and share[1][1] <= qr.ALPHA * len(qr.CUTOFFS) and share[0][1] > 0.9


def test_quality_rules_empty(spark):
    docs, labels = spark.createDataFrame([], DOCS), spark.createDataFrame([], "doc_id long, quality int")
    assert quality_rules(docs, labels).count() == 0
    assert quality_rules(spark.createDataFrame([(None, None, None, None)], DOCS), labels).first()["base_failed"] is True


def judged(url):
    m = re.match(r"(?s).*?://([^/?#]*)(/[^?#]*)?", url or "")
    host = re.sub("[A-Z]", lambda x: x[0].lower(), m[1]) if m else ""
    path = (m[2] or "") if m else ""
    best = None
    for h, p, v in [("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block")]:
        if (host == h or host.endswith("." + h)) and path.startswith(p) and (best is None or len(h + p) > len(best[0])):
            best = (h + p, v)
    return host, path, best and best[0], best[1] if best else "allow"


def test_url_filter(spark):
    urls = [
        None, "", "no scheme", "http://", "https://Example.ORG/es/x?q", "http://a.example.org/en/12#f", "http://a.example.org/en/2", "http://xexample.org/es/", "ftp://x.com/fr/", "http://b.com/de/1",
        "http://b.com?x=/de/", "http://b.com/a://b.org/", "http://org/", "http://.org/es", "http://é.example.org/es/ü", "http://a.com/DE/", "http://b.com/de/1", "x\n://b.com/de/\n?",
    ]
    pages = spark.createDataFrame([(i, u, "x") for i, u in enumerate(urls)], "page_id long, url string, url_host string")
    got = {r["page_id"]: (r["url_host"], r["url_path"], r["url_rule"], r["url_verdict"]) for r in url_filter(pages, rule_table(spark)).collect()}
    assert got == {i: judged(u) for i, u in enumerate(urls)}
    assert url_filter(pages.limit(0), rule_table(spark)).count() == 0
    assert {r["url_verdict"] for r in url_filter(pages, rule_table(spark).limit(0), default="block").collect()} == {"block"}


def targets(sizes, most=3):
    order = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    weight = {s: (1, 2, 3)[i % 3] for i, s in enumerate(order)}
    total, open_, target = sum(sizes.values()), set(sizes), {}
    while open_:
        rest = total - sum(target.values())
        share = {s: rest * weight[s] / sum(weight[x] for x in open_) for s in open_}
        over = [s for s in open_ if share[s] > most * sizes[s]]
        if not over:
            return target | share
        for s in over:
            target[s] = most * sizes[s]
            open_.discard(s)
    return target


def test_mix(spark):
    rows = []
    for i in range(3000):
        s = [None, "a", "b", "ü", "Z", "tiny"][i % 6] if i % 60 else "tiny2"
        rows.append((i, "w " * (i % 50 if s != "tiny" else i % 2), "en", s))
    rows += [(1, rows[1][1], "en", "a"), (None, None, None, None), (None, "", "x", "a")]
    docs = spark.createDataFrame(rows, DOCS).repartition(3)
    out = systematic_mix(docs).collect()
    assert len(out) == len(rows)
    sizes = Counter()
    for r in out:
        sizes[r["source"]] += r["mix_size"]
    want = targets({s: sizes[s] for s in {r[3] for r in rows}})
    taken = Counter()
    for r in out:
        assert r["mix_size"] == len((r["text"] or "").split()) and 0 <= r["mix_copies"] <= 3
        assert r["mix_source_size"] == sizes[r["source"]] and r["mix_target"] == pytest.approx(want[r["source"]])
        taken[r["source"]] += r["mix_size"] * r["mix_copies"]
    for s in want:
        assert abs(taken[s] - want[s]) <= 0.02 * want[s] + 100
    again = {(r["doc_id"], r["mix_size"]): r["mix_copies"] for r in systematic_mix(docs.repartition(5)).collect() if r["doc_id"] not in (None, 1)}
    assert again == {(r["doc_id"], r["mix_size"]): r["mix_copies"] for r in out if r["doc_id"] not in (None, 1)}
    assert emit_mix(docs).columns == docs.columns and emit_mix(docs).count() == sum(r["mix_copies"] for r in out)
    assert systematic_mix(docs.limit(0)).count() == 0
    empty = systematic_mix(spark.createDataFrame([(1, "", "en", "a"), (2, None, "en", None)], DOCS)).collect()
    assert [r["mix_copies"] for r in empty] == [0, 0]
