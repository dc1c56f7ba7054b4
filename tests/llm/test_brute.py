"""Packing, suffix dedup, search, PII, license scans, classifier and near-duplicates against brute force."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from propalign.llm import license_scan as lic
from propalign.llm import pii
from propalign.llm.components import components
from propalign.llm.minhash import near_duplicates
from propalign.llm.nnpu import fit_nnpu, quality_classifier, text_features
from propalign.llm.packing import best_fit_packing, fit_counts, patterns, pieces, plan_slots, sequences
from propalign.llm.suffix_dedup import suffix_dedup, suffix_sort
from propalign.llm.topk import top_k

DOCS = "doc_id long, text string, lang string, source string"


def frame(spark, texts):
    return spark.createDataFrame([(i, t, "en", "s") for i, t in enumerate(texts)], DOCS)


def prose(rng, n):
    return " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 7))) for _ in range(n))


# --- packing


def test_tokens_equal_the_tokenizer(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    rng = random.Random(1)
    texts = ["", None, " ", "  ", " a", "a ", "a  b", "a \nb", "don't  we'll\n\n x", "é è\u00a0ü \u2003 z", "12 345 6", "<|endoftext|> x", "x<|endoftext|>", "日本 語", "a\tb \t c", "!! ## $$"]
    texts += ["".join(rng.choice("ab 1.'\n\té \u3000") for _ in range(60)) for _ in range(200)]
    got = defaultdict(list)
    for r in pieces(frame(spark, texts), keep_ids=True, length=16).collect():
        got[r["doc_id"]].append(r)
    for i, x in enumerate(texts):
        ids = [*t.encode(x or "", add_special_tokens=False).ids, 2]
        own = sorted(got[i], key=lambda r: r["piece"])
        assert [v for r in own for v in r["ids"]] == ids, repr(x)
        assert [r["piece"] for r in own] == list(range(len(own))) and all(r["length"] == 16 for r in own[1:])
        for r in own:
            assert r["ids_crc32"] == zlib.crc32(np.array(r["ids"], dtype="<u4").tobytes()) and ids[r["start"] : r["start"] + r["length"]] == r["ids"]


def check_packing(rows, length):
    by = defaultdict(list)
    for r in rows:
        by[r["sequence_id"]].append((r["offset"], r["length"]))
    for x in by.values():
        at = 0
        for off, n in sorted(x):
            assert off == at
            at += n
        assert at <= length
    return len(by)


def test_packing(spark):
    rng = random.Random(2)
    docs = frame(spark, [prose(rng, rng.randint(0, 90)) for _ in range(500)] + [None, ""]).repartition(5)
    rows = best_fit_packing(docs, length=64, keep_ids=True)
    n = check_packing(rows.collect(), 64)
    total = sum(r["length"] for r in rows.collect())
    assert n <= 1.02 * -(-total // 64) + 1
    assert sum(len(r["ids"]) for r in sequences(rows).collect()) == total
    assert best_fit_packing(docs.limit(0), length=64).count() == 0


@pytest.mark.parametrize("shape", ["flat", "short", "long", "one", "few"])
def test_plan(shape):
    rng = np.random.default_rng(3)
    h = np.zeros(256, dtype=np.int64)
    sizes = {"flat": rng.integers(1, 256, 20000), "short": rng.integers(1, 30, 20000), "long": rng.integers(130, 256, 3000), "one": np.full(999, 100), "few": np.array([255, 1, 3])}[shape]
    np.add.at(h, sizes, 1)
    slots, n = plan_slots(h, 256)
    fill, ranks = Counter(), defaultdict(list)
    for size, first, count, seq, off in slots:
        ranks[size].append((first, count))
        for k in range(count):
            fill[seq + k] += size
    assert all(v <= 256 for v in fill.values()) and len(fill) == n
    for size, spans in ranks.items():
        at = 0
        for first, count in sorted(spans):
            assert first == at
            at += count
        assert at == h[size]
    # Best fit, longest first, one by one.
    gaps: list[int] = []
    for s in sorted(sizes.tolist(), reverse=True)[:4000] if shape != "flat" else []:
        fits = [g for g in gaps if g >= s]
        if fits:
            gaps.remove(min(fits))
            gaps.append(min(fits) - s)
        else:
            gaps.append(256 - s)
    if shape in ("long", "one", "few"):
        assert n <= len(gaps) * 1.005 + 1
    assert n >= -(-int(sizes.sum()) // 256) and (shape not in ("flat", "short") or n <= 1.01 * sizes.sum() / 256 + 2)


def test_fit_is_non_negative_and_close():
    rows = patterns(32)
    assert set(rows.sum(1)) == {32}
    h = np.zeros(33)
    for r in rows[::7]:
        for s in r[r > 0]:
            h[s] += 3
    x = fit_counts(rows, h, 2000)
    used = np.bincount(rows.ravel(), weights=np.repeat(x, 3), minlength=33)
    assert (x >= 0).all() and np.abs(used[2:] - h[2:]).sum() < 0.05 * h.sum()


# --- suffix dedup


def brute_dedup(texts, length):
    raw = [(t or "").encode() for t in texts]
    seen = Counter(r[i : i + length] for r in raw for i in range(len(r) - length + 1))
    out = []
    for r in raw:
        gone = bytearray(len(r))
        for i in range(len(r) - length + 1):
            if seen[r[i : i + length]] > 1:
                gone[i : i + length] = b"\1" * length
        spans = [m.span() for m in re.finditer(b"\1+", bytes(gone))]
        out.append((len(r), sum(gone), len(spans), hashlib.sha256(bytes(c for c, g in zip(r, gone) if not g)).hexdigest()))
    return out


@pytest.mark.parametrize("few", [48, 2])
def test_suffix_dedup(spark, monkeypatch, few):
    import propalign.llm.suffix_dedup as sd

    monkeypatch.setattr(sd, "FEW", few)
    rng = random.Random(4)
    base = prose(rng, 400)
    passage = prose(rng, 25)
    texts = [None, "", "short", base, base, "x" * 300, "ab" * 200, "ü" * 90, passage + base[500:900], base[100:700] + prose(rng, 40) + base[100:400]]
    for _ in range(12):  # near copies, each with changes of its own
        t = list(base)
        for _ in range(rng.randint(1, 6)):
            t[rng.randrange(len(t))] = rng.choice("xyz")
        texts.append("".join(t))
    texts += [prose(rng, 50) + " " + passage + " " + prose(rng, 50) for _ in range(8)] + [prose(rng, 100) for _ in range(5)]
    length, gram = 60, 20
    monkeypatch.setattr(sd, "RUNS", (41, 12, 4, 1))
    want = brute_dedup(texts, length)
    got = {r["doc_id"]: r for r in suffix_dedup(frame(spark, texts).repartition(3), length=length, gram=gram).collect()}
    for i, w in enumerate(want):
        r = got[i]
        assert (r["n_bytes"], r["n_bytes"] - len(r["kept"]), len(r["spans"]), hashlib.sha256(r["kept"]).hexdigest()) == w, i


def test_suffix_sort():
    from propalign.llm.bytes_np import Prefix

    rng = random.Random(5)
    data = np.frombuffer("".join(rng.choice("ab") for _ in range(700)).encode(), dtype=np.uint8)
    start = np.array([rng.randrange(600) for _ in range(300)])
    group = np.sort(np.array([rng.randrange(7) for _ in range(300)]))
    order = suffix_sort(data, Prefix(data), start, group, 100)
    keys = [(group[i], bytes(data[start[i] : start[i] + 100])) for i in order]
    assert keys == sorted(keys)


def test_suffix_dedup_without_repeats(spark):
    """Anchors that repeat in stretches that don't: nothing is removed."""
    rng = random.Random(15)
    passage = prose(rng, 8)[:40]
    texts = [prose(rng, 30) + passage + prose(rng, 30) for _ in range(6)]
    got = suffix_dedup(frame(spark, texts), length=60, gram=20).collect()
    assert [(len(r["kept"]), list(r["spans"])) for r in sorted(got, key=lambda r: r["doc_id"])] == [(len(t), []) for t in texts]


def test_suffix_dedup_empty(spark):
    assert suffix_dedup(frame(spark, ["x"]).limit(0)).count() == 0


# --- search


def test_top_k(spark):
    rng = np.random.default_rng(6)
    rows = [(i, [float(v) for v in rng.normal(size=8) / 3]) for i in range(400)]
    rows += [(1000 + i, rows[5][1]) for i in range(50)] + [(2000, None), (2001, [float("nan")] * 8), (2002, []), (2003, [1.0, 2.0]), (2004, [None, 1.0]), (None, [0.5] * 8), (2050, [-0.1] * 8)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    ok = [(i, np.floor(256 * np.array(v, dtype=np.float32).astype(float))) for i, v in rows if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v)]
    pad = lambda v: np.concatenate([v, np.zeros(8 - len(v))])
    want = set()
    for q, v in ok:
        if q % 50 == 0:
            best = sorted(((-int(pad(v) @ pad(x)), i) for i, x in ok if i != q))[:5]
            want |= {(q, k + 1, i, -s) for k, (s, i) in enumerate(best)}
    assert {tuple(r) for r in top_k(df, lambda c: c % 50 == 0).collect()} == want
    few = spark.createDataFrame(rows[:3], "vec_id long, embedding array<float>")
    assert top_k(few, lambda c: c % 50 == 0).count() == 2 and top_k(df.limit(0), lambda c: c % 50 == 0).count() == 0


# --- personal data


def brute_spans(t):
    t = t or ""
    out = [("email", *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [("ip", *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(p) <= 255 for p in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = re.sub("[ -]", "", m[0])
        s = sum(sum(divmod(2 * int(c), 10)) if i % 2 else int(c) for i, c in enumerate(d[::-1]))
        if 13 <= len(d) <= 19 and s % 10 == 0:
            out.append(("card", *m.span()))
    out += [("phone", *m.span()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 9 <= len(re.sub("[^0-9]", "", m[0])) <= 15]
    return out


def test_base_spans():
    rng = random.Random(7)
    pieces_ = ["a@b.c", "@", ".", "x.y@z", "1.2.3.4", "999.1.1.1", "4111 1111 1111 1111", "+1 (555) 123-4567", "+", "12", "-", " ", "é", "a1@b-c.d.e", "0.0.0.0255", "5500-0000-0000-0004", "..", "%+"]
    for _ in range(4000):
        t = "".join(rng.choice(pieces_) for _ in range(rng.randint(1, 9)))
        assert pii.base_spans(t) == brute_spans(t), t
    assert pii.base_spans("7" * 200_000) == [] and pii.base_spans("a" * 200_000 + "@") == []


def test_discovery_and_redaction(spark):
    rng = random.Random(8)
    key = lambda n: "".join(rng.choice("0123456789abcdef") for _ in range(n))
    texts = [f'word token = "{key(40)}" more' for _ in range(10)] + [f'x token = "{key(33)}1" y', "at time: 12345678 it was", "ratio = 12.345678", None, "", "mail me@x.org now"]
    docs = frame(spark, texts)
    got = {r["doc_id"]: r for r in pii.personal_data(docs).collect()}
    assert [s["kind"] for s in got[10]["spans"]][-1] == "secret" and texts[10][got[10]["spans"][-1]["start"] : got[10]["spans"][-1]["stop"]].endswith("1")
    assert all(not any(s["kind"] == "secret" for s in got[i]["spans"]) for i in range(11, 16))
    clean = {r["doc_id"]: r["text"] for r in pii.redact(docs).collect()}
    assert clean[10] == 'x token = "<SECRET>" y' and clean[15] == "mail <EMAIL> now" and clean[11] == texts[11] and clean[13] is None and clean[14] == ""
    assert pii.personal_data(docs.limit(0)).count() == 0


# --- licenses


def brute_rising(pairs):
    best = [1] * len(pairs)
    for i in range(len(pairs)):
        best[i] = 1 + max([best[j] for j in range(i) if pairs[j][1] < pairs[i][1]], default=0)
    return max(best, default=0)


def test_patience():
    rng = random.Random(9)
    for _ in range(300):
        a, b = ([rng.choice("abcdefgh") for _ in range(rng.randint(0, 12))] for _ in range(2))
        p = lic.patience(a, b)
        assert all(a[i] == b[j] for i, j in p) and all(x[0] < y[0] and x[1] < y[1] for x, y in zip(p, p[1:]))
        if a == b:
            assert len(p) == len(a)
        seconds = [rng.randint(0, 20) for _ in range(10)]
        pairs = list(enumerate(seconds))
        r = lic._rising(pairs)
        assert len(r) == brute_rising(pairs) and all(x[1] < y[1] for x, y in zip(r, r[1:]))


def test_license_scan(spark):
    rng = random.Random(10)
    texts = [None, "", prose(rng, 500)]
    names = list(lic.TEMPLATES)
    for n in names:
        texts.append(prose(rng, 40) + "\n" + lic.TEMPLATES[n] + "\n" + prose(rng, 40) + " license")
    words = lic.TEMPLATES["mit-text"].split()
    texts.append("\n// ".join([prose(rng, 5), *[" ".join(words[i : i + 7]) for i in range(0, len(words), 7)]]))
    texts.append(" ".join(w for i, w in enumerate(words) if i % 2))
    texts.append(lic.TEMPLATES["mit"] + " x y " + lic.TEMPLATES["mit"])
    got = {r["doc_id"]: [m["license"] for m in r["matches"]] for r in lic.license_scan(frame(spark, texts)).collect()}
    assert got[0] == got[1] == got[2] == []
    for i, n in enumerate(names):
        assert n in got[3 + i], (n, got[3 + i])
    assert got[3 + len(names)] == ["mit-text"] and got[4 + len(names)] == [] and got[5 + len(names)] == ["mit", "mit"]


# --- classifier


def test_nnpu_separates():
    rng = np.random.default_rng(11)
    good, bad = rng.normal(1, 1, (900, 6)), rng.normal(-1.5, 1, (300, 6))
    w, mean, scale = fit_nnpu(good[:300], np.concatenate([good[300:], bad]), 0.67)
    z = lambda x: np.c_[(x - mean) / scale, np.ones(len(x))] @ w
    assert (z(good) > 0).mean() > 0.9 and (z(bad) < 0).mean() > 0.9


def test_classifier(spark):
    rng = random.Random(12)
    texts = [prose(rng, 80) if i % 4 else " ".join(x + "###" for x in prose(rng, 60).split()) for i in range(800)] + [None, ""]
    docs = frame(spark, texts)
    labels = spark.createDataFrame([(i, int(i % 4 > 0)) for i in range(0, 800, 3)] + [(None, 1), (1, None)], "doc_id long, quality int")
    out = {r["doc_id"]: r["score"] for r in quality_classifier(docs, labels).collect()}
    assert len(out) == 802 and all(0 <= s <= 1 for s in out.values())
    right = [(out[i] >= 0.5) == bool(i % 4) for i in range(800)]
    assert np.mean(right) > 0.95
    none = quality_classifier(docs.limit(5), labels.limit(0)).collect()
    assert {r["score"] for r in none} == {0.5} and quality_classifier(docs.limit(0), labels).count() == 0
    assert not text_features("").any() and len(text_features("a b")) == len(text_features(None))


# --- near-duplicates


def brute_components(texts):
    sets = []
    for t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set()))
    root = list(range(len(texts)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            if sets[i] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return {i: (len(sets[i]), find(i)) for i in range(len(texts))}


@pytest.mark.parametrize("block", [256, 4])
def test_near_duplicates(spark, monkeypatch, block):
    import propalign.llm.minhash as mh

    monkeypatch.setattr(mh, "BLOCK", block)
    rng = random.Random(13)
    texts = [None, "", " ", "One two", "one TWO", "one two three four five", "É a b c d e"]
    for _ in range(12):
        base = prose(rng, rng.randint(30, 200)).split()
        for _ in range(rng.randint(1, 9)):
            t = list(base)
            for _ in range(rng.randint(0, 4)):
                t[rng.randrange(len(t))] = prose(rng, 1)
            texts.append(" ".join(t))
    passage = prose(rng, 60)
    texts += [passage + " " + prose(rng, rng.randint(5, 60)) for _ in range(30)] + [texts[10], texts[10].upper()]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_duplicates(frame(spark, texts).repartition(3)).collect()}
    assert got == brute_components(texts)
    assert near_duplicates(frame(spark, texts).limit(0)).count() == 0


def test_components(spark):
    rng = random.Random(14)
    pairs = [(rng.randrange(300), rng.randrange(300)) for _ in range(170)] + [(i, i + 1) for i in range(500, 560)] + [(None, 3)]
    root = {}

    def find(x):
        root.setdefault(x, x)
        while root[x] != x:
            x = root[x]
        return x

    for a, b in pairs:
        if a is not None and a != b:
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    got = {r["node"]: r["label"] for r in components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    assert got == {x: find(x) for x in root}
