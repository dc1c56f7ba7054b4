"""Word2vec in the cluster, against a plain version that holds everything."""

import random
from collections import Counter, defaultdict

import numpy as np
import pytest

from propalign.functions import lexicon
from propalign.operators import skipgram as sg


def texts(n=300):
    rnd = random.Random(3)
    return [" ".join(rnd.choice("abcdefghijklmnopqrstuvwxyz"[: rnd.randint(2, 26)]) + rnd.choice("xyz") for _ in range(rnd.randint(1, 9))) for _ in range(n)]


def codes(given, min_count):
    counts = {w: n for w, n in Counter(w for t in given for w in t.split()).items() if n >= min_count}
    ranked, out = sorted(counts, key=lambda w: (-counts[w], w)), {}
    for _, first, end, number in sg._code_starts(sg.code_lengths(sorted(Counter(counts.values()).items()))):
        out |= {ranked[r]: number + r - first for r in range(first, end)}
    return out, counts


def dense(given, h):
    n, left = defaultdict(float), defaultdict(float)
    for t in given:
        ws = [h[w] for w in t.split() if w in h]
        for i, w in enumerate(ws):
            for j, c in enumerate(ws):
                if 0 < abs(i - j) <= 5:
                    x = w
                    while x > 1:
                        n[c, x >> 1] += (6 - abs(i - j)) / 5
                        left[c, x >> 1] += (1 - (x & 1)) * (6 - abs(i - j)) / 5
                        x >>= 1
    words, nodes = sorted(h.values()), sorted({k[1] for k in n})
    return words, *(np.array([[x[c, k] for k in nodes] for c in words]) for x in (n, left))


def plain(given, size, min_count, slices):
    h, _ = codes(given, min_count)
    words, n, left = dense(given, h)
    u, v, losses = sg.beginning(np.array(words), size, 7).astype(float), np.zeros((n.shape[1], size)), []
    for k in range(slices):
        rate = 0.025 * (1 - (k + 0.5) / slices) / slices
        for words_move in (False, True):
            x, f, many, on = (u, v, n, left) if words_move else (v, u, n.T, left.T)
            z = x @ f.T
            slope = (many / (1 + np.exp(-z)) - on) @ f
            along = slope / np.maximum(np.linalg.norm(slope, axis=1, keepdims=True), 1e-300)
            bent = np.where(np.abs(z) < 1e-3, 0.25, np.tanh(z / 2) / np.where(np.abs(z) < 1e-3, 1, 2 * z))
            curve = (many * bent * (along @ f.T) ** 2).sum(1)
            x = x - np.where(curve > 0, -np.expm1(-rate * curve) / np.maximum(curve, 1e-300), rate)[:, None] * slope
            u, v = (x, v) if words_move else (u, x)
        losses.append((n * np.logaddexp(0, u @ v.T) - left * (u @ v.T)).sum())
    return {w: u[words.index(x)] for w, x in h.items()}, losses


@pytest.mark.parametrize("block_tokens, looked_up", [(10**6, 10**6), (60, 10)])
def test_vectors_are_those_of_the_plain_version(spark, block_tokens, looked_up):
    """Whatever the blocks, and whether words are looked up or joined."""
    given = [*texts(), "alone alone", *["alone"] * 4]
    want, _ = plain(given, 8, 5, 2)
    got = {r["word"]: r["vec"] for r in sg.fit(spark.createDataFrame([(t,) for t in given], "text string"), 8, 7, 5, 2, block_tokens, looked_up).collect()}
    assert got.keys() == want.keys()
    for w in want:
        assert np.allclose(got[w], want[w], atol=1e-6)


def test_codes_are_as_short_as_huffman_s():
    import heapq

    for counts in ([(5, 1)], [(1, 2)], [(1, 5), (2, 1), (9, 3)], [(n, n % 4 + 1) for n in range(5, 90)]):
        heap, cost = [w for w, m in counts for _ in range(m)], 0
        heapq.heapify(heap)
        while len(heap) > 1:
            x = heapq.heappop(heap) + heapq.heappop(heap)
            cost += x
            heapq.heappush(heap, x)
        lengths = [n for n, m in sg.code_lengths(counts).items() for _ in range(m)]
        every = sorted((w for w, m in counts for _ in range(m)), reverse=True)
        assert len(lengths) == len(every) and sum(a * b for a, b in zip(lengths, every, strict=True)) == cost
        assert sum(2.0**-n for n in lengths) == 1


def test_slices_learn_as_much_as_single_steps():
    """The loss never rises, and the pass lowers it as far as word2vec's steps one by one do, within a fiftieth."""
    given = ["red colour deep"] * 300 + ["blue colour deep"] * 300 + ["small size of thing"] * 300 + ["large size of thing"] * 300
    random.Random(5).shuffle(given)
    h, _ = codes(given, 5)
    words, n, left = dense(given, h)
    nodes = sorted({x >> t for x in words for t in range(1, x.bit_length())})
    u = dict(zip(words, sg.beginning(np.array(words), 16, 7).astype(float), strict=True))
    v, rnd, done = {k: np.zeros(16) for k in nodes}, random.Random(1), 0
    for t in given:
        ws, rate = [h[w] for w in t.split()], 0.025 * (1 - done / len(given))
        done += 1
        for i, w in enumerate(ws):
            reach = 5 - rnd.randrange(5)
            for j, c in enumerate(ws):
                if 0 < abs(i - j) <= reach:
                    x, step = w, 0
                    while x > 1:
                        g = rate * (1 - (x & 1) - 1 / (1 + np.exp(-u[c] @ v[x >> 1])))
                        step = step + g * v[x >> 1]
                        v[x >> 1] = v[x >> 1] + g * u[c]
                        x >>= 1
                    u[c] = u[c] + step
    z = np.array([[u[c] @ v[k] for k in nodes] for c in words])
    one_by_one = (n * np.logaddexp(0, z) - left * z).sum()
    losses, nothing = plain(given, 16, 5, sg.SLICES)[1], n.sum() * np.log(2)
    assert nothing >= losses[0] and all(a >= b - 1e-6 for a, b in zip(losses, losses[1:], strict=False))
    assert nothing - losses[-1] >= 0.98 * (nothing - one_by_one), (losses[-1], one_by_one)


def test_the_driver_gets_no_vectors_of_words(spark, monkeypatch):
    """What the driver holds is the top of the tree; MLlib's model, which it would hold whole, is not used."""
    monkeypatch.setattr("pyspark.ml.feature.Word2Vec.fit", lambda *a, **k: 1 / 0)
    rows = spark.createDataFrame([(t,) for t in texts()], "text string")
    got = lexicon.trained(rows)
    assert got.columns == ["word", "vec"] and got.dtypes[1][1] == "array<double>" and got.count() == len(codes(texts(), 5)[0])


def test_few_or_no_words(spark):
    rows = lambda *t: spark.createDataFrame([(x,) for x in t], "text string")
    assert sg.fit(rows("a b", "c")).collect() == []
    assert [r["word"] for r in sg.fit(rows(*["only only"] * 3), 4, slices=1).collect()] == ["only"]
