"""Cases in which an operator once did less than its whole job."""

import random

import re
from collections import Counter

import numpy as np

from propalign.llm import license_scan as lic
from propalign.llm import pii
from propalign.llm.mixing import emit_mix, systematic_mix
from propalign.llm.nnpu import quality_classifier
from propalign.llm.minhash import HASHES, near_duplicates, one_of_each
from propalign.llm.quality_rules import ALPHA, DELTA, CUTOFFS, quality_rules, risk_thresholds
from propalign.llm.suffix_dedup import suffix_dedup
from propalign.llm.topk import top_k

DOCS = "doc_id long, text string, lang string, source string"


def test_small_strata_are_pooled(spark):
    """Each of three languages has too few good labels for a test; together they have enough."""
    assert (1 - ALPHA) ** 150 > DELTA / (3 * len(CUTOFFS)) > (1 - ALPHA) ** 450
    good = " ".join(f"w{i}" for i in range(60))
    bad = " ".join(f"w{i}###" for i in range(60))
    rows = [(i, good, lang, "s") for k, lang in enumerate(("fr", "de", "es")) for i in range(1000 * k, 1000 * k + 150)]
    rows += [(9000, bad, "fr", "s"), (9001, bad, "de", "s"), (9002, bad, "es", "s"), (9003, bad, "xx", "s")]
    docs, labels = spark.createDataFrame(rows, DOCS), spark.createDataFrame([(i, int(i < 3000)) for i in [*range(3000), 9000, 9003]], "doc_id long, quality int")
    kept = {r["doc_id"]: r["kept"] for r in quality_rules(docs, labels).collect()}
    assert [kept[i] for i in range(9000, 9004)] == [False, False, False, True] and all(kept[r[0]] for r in rows if r[0] < 9000)


def test_a_large_stratum_keeps_its_own_test(spark):
    """One stratum has enough labels for itself; the small ones, too few together, are tested on all."""
    low, high = ({m: x for m in CUTOFFS} for x in (0.0, 99.0))
    rows = [("en", 1, False, *[v + (i < 3) * 0.12 for v in low.values()]) for i in range(1000)] + [(s, 1, False, *low.values()) for s in ("fr", "de") for _ in range(60)]
    rows += [(s, 0, False, *high.values()) for s in ("en", "fr", "de")]
    known = spark.createDataFrame(rows, "lang string, quality int, base_failed boolean, " + ", ".join(f"{m} double" for m in low))
    got = {(r["stratum"], r["measure"]): (r["n_good"], r["n_rejected"], r["cutoff"]) for r in risk_thresholds(known).collect()}
    for s, n in (("en", 1000), ("fr", 1120), ("de", 1120)):
        assert all(got[s, m] == (n, 0, c[0]) for m, c in CUTOFFS.items())  # the mildest leads as much as the others
    alone = {(r["stratum"], r["measure"]): r["cutoff"] for r in risk_thresholds(known.where("lang <> 'en'")).collect()}
    assert alone == {}


def test_top_k_counts_repeated_rows(spark):
    rng = np.random.default_rng(16)
    vec = lambda: [float(v) for v in rng.normal(size=6) / 3]
    rows = [(i, vec()) for i in range(300)]
    near = [v * 2 for v in rows[50][1]]
    rows += [(700, near)] * 6 + [(701, near)] * 2 + [rows[7]] * 9 + [rows[100]] * 2 + [(150, vec())]
    whole = [(i, np.floor(256 * np.array(v, dtype=np.float32).astype(float))) for i, v in rows]
    want = []
    for q in {i for i, _ in whole if i % 50 == 0}:
        found = sorted((-int(v @ x), i) for p, v in whole if p == q for i, x in whole if i != q)
        want += [(q, k + 1, i, -s) for k, (s, i) in enumerate(found[:5])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(3)
    assert sorted(tuple(r) for r in top_k(df, lambda c: c % 50 == 0).collect()) == sorted(want)


def test_long_secrets_and_quoted_keys(spark):
    rng = random.Random(17)
    key = lambda n: "".join(rng.choice("0123456789abcdef") for _ in range(n))
    long, other = key(2000), key(300)
    web = "eyJ" + key(400) + "." + key(400) + "." + key(200)
    assert [(h[2], h[3], h[4]) for h in pii.contexts(f'token="{web}"', [])] == [(7, 7 + len(web), True)]
    assert len({h[1] for x in ("1a", "2b") for h in pii.contexts(f'token="{other}{x}"', [])}) == 2
    texts = [f'a {{"token": "{key(40)}", "n": 1}}' for _ in range(10)] + [f"b 'auth' => '{key(40)}' c" for _ in range(10)] + [f'c token="{key(40)}" d' for _ in range(10)]
    texts += [f'x token="{long}1" y', f'{{"token": "{long}"}}', f"'auth' => '{long}2'", '"title": "plain words"']
    docs = spark.createDataFrame([(i, t, "en", "s") for i, t in enumerate(texts)], DOCS)
    clean = {r["doc_id"]: r["text"] for r in pii.redact(docs).collect()}
    assert [clean[i] for i in range(30, 34)] == ['x token="<SECRET>" y', '{"token": "<SECRET>"}', "'auth' => '<SECRET>'", texts[33]]
    assert pii.contexts("a=" + "7" * 500_000, [])[0][3] == 500_002
    name = "l" * 900
    assert pii.contexts(f'{name}: "abc123def"', [])[0][0] == f'{name} : "_"' and pii.contexts("a" * 400_000 + "=" * 3 + "1" * 300_000, []) is not None


def brute_scores(edges, rounds):
    """Confidence of patterns: over and over, by plain sums."""
    trust = {i: max(s for p, j, s in edges if j == i) for _, i, _ in edges}
    seeds = dict(trust)
    for _ in range(rounds):
        own = {p: {i for q, i, _ in edges if q == p} for p, _, _ in edges}
        support = {p: sum(trust[i] for i in x) for p, x in own.items()}
        confidence = {p: support[p] / (len(x) + pii.SMOOTH) for p, x in own.items()}
        trust = {i: max([seeds[i], *(confidence[p] for p, j, _ in edges if j == i and support[p] >= pii.SUPPORT)]) for i in seeds}
    return {p: (len(own[p]), round(support[p], 9), round(confidence[p], 9)) for p in own}


def test_pattern_scores(spark):
    rng = random.Random(20)
    edges = [(f"p{rng.randrange(12)}", f"i{int(rng.random() ** 2 * 60)}") for _ in range(260)]
    seed = {f"i{k}" for k in range(0, 60, 3)}
    hits = spark.createDataFrame([(p, i, i in seed) for p, i in edges] * 2, "pattern string, instance string, seed boolean")
    got = {r["pattern"]: (r["instances"], round(r["support"], 9), round(r["confidence"], 9)) for r in pii.score_patterns(hits).collect()}
    assert got == brute_scores([(p, i, float(i in seed)) for p, i in edges], pii.ROUNDS)


def test_contexts_in_prose(spark):
    """Words on both sides of seeds find identifiers of no known format; numbers that fail a check are none."""
    rng = random.Random(21)
    digits = lambda n: "".join(rng.choice("0123456789") for _ in range(n))
    phone = lambda: f"+1 ({digits(3)}) 555-{digits(4)}"
    texts = [f"please reach me {phone()} today" for _ in range(8)] + [f"my account u{digits(4)}@x.org expires soon" for _ in range(8)]
    texts += ["please reach me 555.0199x now", "an account QX-99-1200 expires soon", "he paid 1200300 in all", "please reach me 1234567890123456 today"]
    docs = spark.createDataFrame([(i, t, "en", "s") for i, t in enumerate(texts)], DOCS)
    clean = {r["doc_id"]: r["text"] for r in pii.redact(docs).collect()}
    assert [clean[i] for i in range(16, 20)] == ["please reach me <SECRET> now", "an account <SECRET> expires soon", texts[18], texts[19]]


def test_personal_data_of_clashing_columns(spark):
    names = "base int, spans string, hits int, _uid int, more string, uid int, `row` int, text string, `a.b` int, doc_id long"
    docs = spark.createDataFrame([(1, "s", 2, 3, "m", 4, 5, "mail a@b.org", 6, None), (1, "s", 2, 3, "m", 4, 5, None, 6, 8)], names)
    out = pii.redact(docs)
    assert out.columns == docs.columns
    assert {tuple(r) for r in out.collect()} == {(1, "s", 2, 3, "m", 4, 5, "mail <EMAIL>", 6, None), (1, "s", 2, 3, "m", 4, 5, None, 6, 8)}
    assert pii.personal_data(docs, keep=tuple(docs.columns)).columns == ["hits", "_uid", "more", "uid", "row", "text", "a.b", "doc_id", "base", "spans"]


def test_license_cues_lose_no_match():
    """Where a statement has just as many words as a match needs, cues find what alignment at every word finds."""
    assert [m[0] for x in ("Distributed", "Available") for m in lic.Scanner().scan(f"{x} under the MIT License.")] == ["mit", "mit"]
    rng = random.Random(18)
    for name, template in lic.TEMPLATES.items():
        cued, every = lic.Scanner({name: template}), lic.Scanner({name: template})
        words = every.words[name]
        every.lead = {w: [name] for w in words}
        every.possible = lambda has: {name}  # noqa: B023
        for _ in range(60):
            gone = set(rng.sample(range(len(words)), len(words) - -(-len(words) * 4 // 5)))
            text = " ".join([*(f"q{i}" for i in range(9)), *(f"z{i}" if i in gone else w for i, w in enumerate(words)), *(f"y{i}" for i in range(9))])
            assert bool(cued.scan(text)) == bool(every.scan(text)), (name, text)


def test_passages_of_words(spark, monkeypatch):
    """Runs of words that stand elsewhere, whatever the space between them, shorter in bytes than what dedup removes."""
    import propalign.llm.suffix_dedup as sd

    monkeypatch.setattr(sd, "FEW", 6)
    rng = random.Random(19)
    prose = lambda n: " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randint(1, 4))) for _ in range(n))
    shared = prose(26).split()
    texts = [None, "", prose(9), prose(40), "x " * 30, "é " * 14, prose(40)]
    for i in range(14):
        a = rng.randrange(17)
        part = shared[a : a + rng.randint(7, 20)]
        texts.append(prose(rng.randint(0, 30)) + rng.choice([" ", "\n", "\t "]) + rng.choice([" ", "  ", "\n"]).join(part) + " " + prose(rng.randint(0, 30)))
    texts += [texts[3], texts[3]]
    words, found = 8, [list(re.finditer(r"[^\x20\x09-\x0D]+", t or "")) for t in texts]
    window = lambda ws, i: tuple(m[0] for m in ws[i : i + words])
    seen = Counter(window(ws, i) for ws in found for i in range(len(ws) - words + 1))
    docs = spark.createDataFrame([(i, t, "en", "s") for i, t in enumerate(texts)], DOCS).repartition(3)
    got = {r["doc_id"]: [(p["start"], p["stop"]) for p in r["passages"]] for r in suffix_dedup(docs, length=200, gram=12, words=words).collect()}
    assert sum(map(bool, got.values())) > 10
    for i, (t, ws) in enumerate(zip(texts, found, strict=True)):
        hit = bytearray(len(ws))
        for k in range(len(ws) - words + 1):
            if seen[window(ws, k)] > 1:
                hit[k : k + words] = b"\1" * words
        size = lambda k: len((t or "")[:k].encode())  # noqa: E731, B023
        assert got[i] == [(size(ws[m.start()].start()), size(ws[m.end() - 1].end())) for m in re.finditer(b"\1+", bytes(hit))], i


def test_suffix_dedup_of_clashing_columns(spark):
    names = "doc_id long, text string, row string, raw string, md5 string, spans string, kept string, runs int, tid int, gram int, `a b` int"
    docs = spark.createDataFrame([(None, "ab " * 300, "r", "w", "m", "s", "k", 1, 2, 3, 4), (5, None, "r", "w", "m", "s", "k", 1, 2, 3, 4)], names)
    out = suffix_dedup(docs, keep=tuple(docs.columns))
    assert out.columns == ["doc_id", "text", "row", "raw", "md5", "runs", "tid", "gram", "a b", "kept", "n_bytes", "spans", "passages"]
    assert {(r["doc_id"], r["row"], r["a b"], len(r["kept"]), r["n_bytes"], len(r["passages"])) for r in out.collect()} == {(None, "r", 4, 0, 900, 1), (5, "r", 4, 0, 0, 0)}


def test_one_row_of_each_component_stays(spark):
    """By row: of an id with two texts only the right one, and of null ids no copy of what stays."""
    rng = random.Random(22)
    prose = lambda n: " ".join("".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 6))) for _ in range(n))
    a, b, c = prose(60), prose(60), prose(9000)
    rows = [(1, a), (1, b), (2, b + " more"), (3, a), (None, a), (None, b), (None, "just this one here now"), (None, None), (4, None), (5, ""), (6, c), (7, c + " x"), (6, c), (None, "Just this one here now")]
    names = "doc_id long, text string, id int, digest string, uid long, same int, label int, `x y` int, stay int, docs int"
    docs = spark.createDataFrame([(i, t, 1, "d", 2, 3, 4, 5, 6, 7) for i, t in rows], names).repartition(3)
    for loose in (56, HASHES):
        out = one_of_each(docs, loose=loose)
        assert out.columns == docs.columns
        got = sorted(((r["doc_id"], r["text"]) for r in out.collect()), key=repr)
        null = [r for r in got if r[0] is None and r[1] is not None]
        assert len(null) == 1 and null[0][1].lower() == "just this one here now"
        assert [r for r in got if r not in null] == sorted([(1, a), (1, b), (None, None), (4, None), (5, ""), (6, c)], key=repr)
    assert near_duplicates(docs).count() == len(rows) and one_of_each(docs.limit(0)).count() == 0


CLASHING = "doc_id long, text string, lang string, source string, mix_x int, _band int, mix_size int, score double, _y int, row int, found int, y int, id int, matches int, `a.b c` int, hash int, rank int"


def clashing(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, 1, 2, 3, 0.5, 4, 5, 6, 7, 8, 9, 10, 11, 12) for i, t, s in rows], CLASHING)


def test_clashing_columns(spark):
    """Columns called like an operator's own pass through, or are replaced where a result has the name."""
    docs = clashing(spark, [(i, f"w{i} " * (i % 7), f"s{i % 3}") for i in range(60)] + [(None, None, None), (3, "Released under the MIT License.", None)])
    mix = emit_mix(docs)
    assert mix.columns == docs.columns and {(r["mix_x"], r["mix_size"], r["a.b c"]) for r in mix.collect()} == {(1, 3, 10)}
    out = systematic_mix(docs)
    assert out.columns == [c for c in docs.columns if c != "mix_size"] + ["mix_size", "mix_source_size", "mix_target", "mix_copies"] and out.count() == 62
    scored = quality_classifier(docs, spark.createDataFrame([(1, 1), (2, 0), (4, 1)], "doc_id long, quality int"))
    assert scored.columns == [c for c in docs.columns if c != "score"] + ["score"] and scored.where("_y = 4 and score between 0 and 1").count() == 62
    found = lic.license_scan(docs, keep=tuple(docs.columns))
    assert found.columns == [c for c in docs.columns if c != "matches"] + ["matches"] and found.where("size(matches) > 0").count() == 1
    for empty in (emit_mix(docs.limit(0)), systematic_mix(docs.limit(0)), lic.license_scan(docs.limit(0))):
        assert empty.count() == 0


def test_reruns_of_the_mix_agree_for_repeated_ids(spark):
    rng = random.Random(23)
    rows = [(rng.choice([None, 1, 2]), " ".join(rng.choice("abc") for _ in range(rng.choice([4, 5]))), "s") for _ in range(300)]
    rows += [(9, "w " * 60_000, "t"), (10, "v", "t")]
    runs = [Counter((r["doc_id"], r["text"], r["mix_copies"]) for r in systematic_mix(clashing(spark, rng.sample(rows, len(rows))).repartition(k)).collect()) for k in (2, 5)]
    assert runs[0] == runs[1] and sum(runs[0].values()) == 302


def test_mix_comes_near_its_targets(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    out = systematic_mix(docs).groupBy("source").agg({"mix_target": "max", "mix_size": "max"}).collect()
    words = {r["source"]: r["w"] for r in systematic_mix(docs).selectExpr("source", "mix_size * mix_copies w").groupBy("source").sum("w").toDF("source", "w").collect()}
    far = sorted(abs(words[r["source"]] / r["max(mix_target)"] - 1) for r in out)
    assert far[len(far) // 2] < 0.02 and far[-1] < 0.15, far


def test_templates_as_a_table(spark):
    rng = random.Random(24)
    table = spark.createDataFrame([("one", "Use of this thing is free for all who ask"), ("none", None), ("blank", " ... "), (None, "x y z")], "license string, template string")
    words = "use of this thing is free for all who ask".split()
    texts = [None, "", "Use of this thing, is FREE for all who ask!"] + [" ".join(rng.choice([w, w, w, "other"]) for w in words) for _ in range(60)]
    got = {r["doc_id"]: r["matches"] for r in lic.license_scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), templates=table).collect()}
    for i, t in enumerate(texts):
        same = sum(a == b for a, b in zip(words, re.findall("[a-z]+", (t or "").lower()), strict=False))
        assert bool(got[i]) == (same >= 8), t
    assert lic.license_scan(spark.createDataFrame([(1, "x")], "doc_id long, text string"), templates=table.limit(0)).first()["matches"] == []


def test_the_classifier_reads_one_row_of_an_id(spark):
    """Where every document has a label the corpus is unlabelled text all the same, and a repeated id counts once."""
    rng = random.Random(25)
    good = lambda: " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 7))) for _ in range(60))
    rows = [(i, good() if i % 3 else "### " * 60) for i in range(400)] + [(5, "### " * 60)] * 2000
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 3 > 0)) for i in range(400)], "doc_id long, quality int")
    out = {(r["doc_id"], r["text"][:3]): r["score"] for r in quality_classifier(docs, labels).collect()}
    assert np.mean([(out[i, t[:3]] >= 0.5) == (t[:3] != "###") for i, t in rows[:400]]) > 0.97


def test_annuli_are_left_out_where_bounds_allow(spark):
    """Clusters far apart: the annuli of other clusters are never searched, and results are those of brute force."""
    rng = np.random.default_rng(26)
    centres = rng.normal(size=(12, 8)) * 6
    rows = [(i, [float(v) for v in centres[i % 12] + rng.normal(size=8) / 20]) for i in range(3000)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(4)
    report = []
    got = sorted(tuple(r) for r in top_k(df, lambda c: c % 50 == 0, report=report).collect())
    x = np.floor(256 * np.array([v for _, v in rows]))
    want = []
    for q in range(0, 3000, 50):
        s = x @ x[q]
        want += [(q, k + 1, i, int(v)) for k, (v, i) in enumerate(sorted(((-s[i], i) for i in range(3000) if i != q))[:5])]
    assert got == sorted((q, k, i, -v) for q, k, i, v in want)
    assert 0 < sum(report) < 0.6 * 60 * 3000, report
