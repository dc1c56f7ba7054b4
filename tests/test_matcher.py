"""The property matcher: worked examples, invariants, equivalences and directions."""

import math
import random
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from propalign.baselines import boosted, cosine, lattice, lexical, lsh, semgraph
from propalign.functions import formats, strings
from propalign.functions.lexicon import blended, cosine as cos_col
from propalign.model import CONFIGS, INSTANCE, PAIR_KEY, PROPERTY_KEY, FeatureConfig
from propalign.operators import graph, relational
from propalign.operators.classifier import MatcherSpec, PropertyPairClassifier, PropertyPairModel
from propalign.operators.network import Network, NetworkSpec, fit
from propalign.operators.pairs import assemble, candidates, combine
from propalign.operators.profile import profile, value_word_weights, vector_of
from propalign.operators.sampling import labelled, training_pairs, truth
from propalign.plans import experiments as ex
from propalign.plans import metrics, splits, stats
from propalign.sources import domains, readers

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def small(spark):
    rows = [
        ("c", "s1", "e1", "screen size", "5 in"), ("c", "s1", "e2", "screen size", "6 in"), ("c", "s1", "e1", "price", "12.50"),
        ("c", "s2", "x1", "size", "5 in"), ("c", "s2", "x1", "cost", "13"), ("c", "s3", "y1", "price", ""), ("d", "s1", "z", "price", "9"),
    ]
    return spark.createDataFrame(rows, INSTANCE)


@pytest.fixture(scope="module")
def lex(spark):
    return spark.createDataFrame([("price", [1.0, 0.0]), ("cost", [0.9, 0.1]), ("size", [0.0, 1.0]), ("in", [0.5, 0.5])], "word string, vec array<double>")


def test_worked_value(spark):
    r = formats.with_numeric(formats.with_meta(spark.createDataFrame([("12 MP",), ("",), ("ÀÉ ó €!",)], "value string"))).collect()
    assert (r[0]["n_number"], r[0]["n_white"], r[0]["share_letter"], r[0]["num"]) == (2, 1, 0.4, -1.0)
    assert all(r[1][n] == 0 for n in formats.META_NAMES) and len(formats.META_NAMES) == 28
    for x in r:
        parts = sum(x[f"n_{n}"] for n in ("letter", "mark", "number", "punctuation", "symbol", "white", "other"))
        assert parts == len(x["value"]) and x["n_upper"] + x["n_lower"] <= x["n_letter"]
        assert all(0 <= x[n] <= 1 for n in formats.META_NAMES if n.startswith("share"))


def test_numbers_and_words(spark):
    told = {"12d": -1, "NaN": -1, "inf": -1, "1_000": -1, "1,024.5": -1, "+7": 7, ".5": 0.5, "1e3": 1000, " 12 ": 12, "": -1}
    rows = spark.createDataFrame([(k,) for k in told], "value string").select("value", formats.numeric(F.col("value")).alias("n")).collect()
    assert {r["value"]: r["n"] for r in rows} == told
    w = spark.createDataFrame([("28mm Lens_cap-X",)], "value string").select(formats.words(F.col("value"))).first()[0]
    assert w == ["28mm", "lens", "cap", "x"]


def test_widths():
    for d, whole in ((300, 637), (64, 165)):
        assert FeatureConfig().width(d) == whole
        want = {"instances": (29, d, 29 + d), "names": (8, d, 8 + d), "both": (37, 2 * d, 37 + 2 * d)}
        for o, (plain, emb, every) in want.items():
            assert [FeatureConfig(o, k).width(d) for k in ("non_embedding", "embedding", "all")] == [plain, emb, every]
    assert len(CONFIGS) == 9


def naive_vectors(rows, lex):
    out = {}
    for cls, s, _, p, v in rows:
        ws = [w for w in "".join(c if c.isalnum() else " " for c in v.lower()).split()]
        vec = np.mean([lex.get(w, np.zeros(2)) for w in ws], axis=0) if ws else np.zeros(2)
        out.setdefault((cls, s, p), []).append(vec)
    return {k: np.mean(v, axis=0) for k, v in out.items()}


def test_profile_means(spark, small, lex):
    prof = {tuple(r[c] for c in PROPERTY_KEY): r for r in profile(small, lex).collect()}
    want = naive_vectors([tuple(r) for r in small.collect()], {r["word"]: np.array(r["vec"]) for r in lex.collect()})
    assert prof.keys() == want.keys()
    for k, v in want.items():
        assert np.allclose(prof[k]["val_emb"], v)
    assert np.allclose(prof["c", "s1", "screen size"]["name_emb"], [0, 0.5])  # the unknown word counts as zeros
    assert prof["c", "s1", "screen size"]["num"] == -1 and prof["c", "s2", "cost"]["num"] == 13
    weights = value_word_weights(small).groupBy(*PROPERTY_KEY).agg(F.sum("weight").alias("w")).collect()
    assert all(r["w"] == pytest.approx(prof[r["cls"], r["source"], r["prop"]]["n_instances"]) for r in weights)


def test_set_and_multiset(spark, lex):
    df = spark.createDataFrame([("c", "s", str(i), "p", "1" if i else "3") for i in range(4)], INSTANCE)
    assert profile(df, lex).first()["num"] == 1.5 and profile(df, lex, distinct_values=True).first()["num"] == 2.0
    for agg, want in (("median", 1.0), ("min", 1.0), ("max", 3.0)):
        assert profile(df, lex, agg).first()["num"] == want


def test_candidates(spark, small, lex):
    prof = profile(small, lex)
    by = {s: {tuple(r) for r in candidates(prof, strategy=s, blocks=3).collect()} for s in ("broadcast", "blocks", "auto")}
    assert by["broadcast"] == by["blocks"] == by["auto"]
    props = [tuple(r) for r in prof.select(*PROPERTY_KEY).collect()]
    want = {(a[0], *min(a, b)[1:], *max(a, b)[1:]) for a, b in combinations(props, 2) if a[0] == b[0] and a[1] != b[1]}
    assert by["auto"] == want


def test_combinations(spark):
    df = spark.createDataFrame([([1.0, 5.0], [4.0, 3.0])], "a array<double>, b array<double>")
    got = {m: df.select(combine(F.col("a"), F.col("b"), m)).first()[0] for m in ("abs_diff", "diff", "mean", "concat")}
    assert got == {"abs_diff": [3, 2], "diff": [-3, 2], "mean": [2.5, 4], "concat": [1, 5, 4, 3]}


def test_assemble_equals_tiles(spark, small, lex):
    """The features that tiles form, seen through a network that returns one of them."""
    prof = profile(small, lex)
    rows = {tuple(r[c] for c in PAIR_KEY): np.array(r["features"]) for r in assemble(prof).collect()}
    width = FeatureConfig().width(2)
    for f in (0, 28, 30, width - 8, width - 1):
        w = np.zeros((width, 2), dtype=np.float32)
        w[f, 1] = 1
        net = Network(NetworkSpec(hidden=()), np.zeros(width), np.ones(width), [w], [np.zeros(2, dtype=np.float32)])
        sim = PropertyPairModel(MatcherSpec(), net, 2).score(prof, blocks=2).collect()
        assert {tuple(r[c] for c in PAIR_KEY) for r in sim} == rows.keys()
        for r in sim:
            x = rows[tuple(r[c] for c in PAIR_KEY)][f]
            assert r["score"] == pytest.approx(1 / (1 + math.exp(-x)), abs=1e-5)


def brute_edits(a, b, free):
    """Shortest edit path by search over strings (free: unrestricted swaps), for short strings."""
    from functools import lru_cache

    if free:
        alphabet = set(a + b)
        frontier, seen, n = {a}, {a}, 0
        while b not in frontier:
            n += 1
            new = set()
            for s in frontier:
                for i in range(len(s) + 1):
                    new |= {s[:i] + c + s[i:] for c in alphabet if len(s) < len(b) + 2}
                    if i < len(s):
                        new |= {s[:i] + s[i + 1 :]} | {s[:i] + c + s[i + 1 :] for c in alphabet}
                    if i + 1 < len(s):
                        new.add(s[:i] + s[i + 1] + s[i] + s[i + 2 :])
            frontier = new - seen
            seen |= new
        return n

    @lru_cache(None)
    def go(i, j):
        if i == 0 or j == 0:
            return i + j
        best = min(go(i - 1, j) + 1, go(i, j - 1) + 1, go(i - 1, j - 1) + (a[i - 1] != b[j - 1]))
        if i > 1 and j > 1 and a[i - 1] == b[j - 2] and a[i - 2] == b[j - 1]:
            best = min(best, go(i - 2, j - 2) + 1)
        return best

    return go(len(a), len(b))


def test_distances_brute():
    assert (strings.osa("ca", "abc"), strings.damerau("ca", "abc")) == (3, 2)
    rng = random.Random(1)
    for _ in range(150):
        a, b, c = ("".join(rng.choice("abc") for _ in range(rng.randint(0, 4))) for _ in range(3))
        x = dict(zip(strings.DISTANCES, strings.all_eight(a, b)))
        assert x["osa"] == brute_edits(a, b, False) and x["damerau"] == brute_edits(a, b, True)
        assert x["damerau"] <= x["osa"] <= x["levenshtein"] <= x["lcs"]
        best = max(len(s) for n in range(len(a) + 1) for t in combinations(range(len(a)), n) if (s := "".join(a[i] for i in t)) in {"".join(b[i] for i in u) for m in range(len(b) + 1) for u in combinations(range(len(b)), m)})
        assert x["lcs"] == len(a) + len(b) - 2 * best
        assert strings.all_eight(a, b) == strings.all_eight(b, a) and all(v == 0 for v in strings.all_eight(a, a))
        assert 0 <= x["jaro_winkler"] <= 1 and 0 <= x["trigram_jaccard"] <= 1
        for k in ("levenshtein", "damerau", "lcs"):
            i = strings.DISTANCES.index(k)
            assert strings.all_eight(a, c)[i] <= strings.all_eight(a, b)[i] + strings.all_eight(b, c)[i]


def test_distance_columns(spark):
    pairs = spark.createDataFrame([("Price_tag", "price"), ("a", ""), ("Screen-Size", "size screen"), ("ab", "ab")], "prop_a string, prop_b string")
    for r in strings.distances(pairs).collect():
        want = strings.all_eight(strings.normal_py(r["prop_a"]), strings.normal_py(r["prop_b"]))
        assert [r[f"dist_{k}"] for k in strings.DISTANCES] == pytest.approx(want)


def test_lexicon_concepts(spark):
    lexicon = blended(spark, spark.read.parquet(f"{SF}/embeddings.parquet"))
    a, b = lexicon.withColumnsRenamed({"word": "wa", "vec": "va"}), lexicon.withColumnsRenamed({"word": "wb", "vec": "vb"})
    got = {(r[0], r[1]): r[2] for r in a.crossJoin(b).where("wa in ('price') and wb in ('cost', 'brand')").select("wa", "wb", cos_col(F.col("va"), F.col("vb"))).collect()}
    assert got["price", "cost"] > 0.8 and abs(got["price", "brand"]) < 0.5


def test_splits():
    names = [f"s{i}" for i in range(8)]
    for f in splits.FRACTIONS:
        got = splits.training_sources(names, f)
        assert len(set(got)) == 25 and {len(x) for x in got} == {max(2, round(f * 8))}
    assert len(set(splits.training_sources([f"s{i:02d}" for i in range(24)], 0.4))) == 25
    tl = splits.transfer_combinations()
    assert len(tl) == 28 and len({a for a, _ in tl}) == 14 and all(t not in a.split("+") for a, t in tl)


def test_training_pairs(spark):
    prof = domains.instances(spark, SF, "event").select(*PROPERTY_KEY).distinct()
    align = domains.align_table(spark, ["event"])
    lab = labelled(candidates(prof), align)
    assert lab.where("label = 1").select(*PAIR_KEY).exceptAll(truth(align)).isEmpty() and lab.where("label = 1").count() == truth(align).count() == 5 * 28
    sample = training_pairs(lab)
    n = {r["label"]: r["count"] for r in sample.groupBy("label").count().collect()}
    assert n[0] == 2 * n[1] and {tuple(r) for r in sample.collect()} == {tuple(r) for r in training_pairs(lab.repartition(7)).collect()}
    split = splits.splits(spark, "event", [f"e{i:02d}" for i in range(8)], (0.4,), 2)
    dealt = splits.deal(lab, split)
    assert dealt.count() == 2 * lab.count() and dealt.where("in_train and not seen").isEmpty()


def test_one_to_many_truth(spark):
    pairs = {tuple(r) for r in truth(domains.align_table(spark, ["order"])).collect()}
    assert {("order", "o00", "order date", "o02", "order year"), ("order", "o00", "order date", "o02", "order month")} <= pairs


def test_network():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(600, 10)) * np.array([1e4] + [1] * 9)
    y = (x[:, 1] + x[:, 2] > 0).astype(int)
    net = fit(x, y)
    assert ((net.score(x) > 0.5) == y).mean() > 0.95 and np.allclose(net.outputs(x).sum(1), 1, atol=1e-6)
    assert np.array_equal(net.score(x), fit(x, y).score(x))
    again = Network.from_json(net.to_json())
    assert np.allclose(again.score(x), net.score(x))
    shuffled = fit(x, rng.permutation(y))
    assert ((shuffled.score(rng.normal(size=(600, 10))) > 0.5) == y).mean() < 0.7
    assert set(fit(x[:0], y[:0]).score(x)) == {0.5}


def test_scores_unlabelled_pairs_exactly(spark):
    inst = domains.instances(spark, SF, "event")
    prof = profile(inst, ex.lexicon(spark, SF)).cache()
    lab = labelled(candidates(prof), domains.align_table(spark, ["event"]))
    sample = training_pairs(lab.where("source_a < 'e04' and source_b < 'e04'")).cache()
    model = PropertyPairClassifier(MatcherSpec()).fit_profile(prof, sample)
    sim = model.score(exclude=sample).cache()
    assert sim.count() == lab.count() - sample.count() and sim.join(sample, PAIR_KEY, "left_semi").isEmpty()
    assert sim.where("score < 0 or score > 1 or is_match != (score > 0.5)").isEmpty()
    full = model.score(exclude=sample, include_labelled=True)
    assert full.count() == lab.count() and full.where("given").count() == sample.count()
    real = truth(domains.align_table(spark, ["event"])).join(sample, PAIR_KEY, "left_anti")
    f1 = metrics.prf(sim, real).first()["f1"]
    assert f1 > 0.6, f1


def test_baselines_directions(spark):
    """Supervised beats unsupervised; unsupervised lexical methods are precise, with less recall."""
    rows = {(r["dataset"], r["method"]): r for r in ex.flat_baselines(spark, SF, ("order", "event")).collect()}
    for d in ("order", "event"):
        for m in ("lexical_onto", "concept_lattice"):
            assert rows[d, m]["precision"] > rows[d, m]["recall"]
    data = ex.prepare(spark, SF, ("order", "event"))
    runs = ex.run_grid(spark, data, ex.single_domain_grid(data, (0.8,), 3, [FeatureConfig()]), "t")
    mean = {(r["dataset"], r["method"]): r["f"] for r in runs.groupBy("dataset", "method").agg(F.avg("f1").alias("f")).collect()}
    for d in ("order", "event"):
        best = max(rows[d, m]["f1"] for m in ("lexical_onto", "concept_lattice", "semantic_graph", "lsh_instances"))
        assert mean[d, "ppc"] >= best - 0.02, (d, mean, best)
    assert runs.where("tp + fn = 0").isEmpty()


def test_lsh_against_theory(spark):
    rng = random.Random(2)
    rows = []
    for i in range(12):
        base = [f"w{rng.randrange(10**6)}" for _ in range(40)]
        other = base[:32] + [f"w{rng.randrange(10**6)}" for _ in range(8)]
        rows += [("c", "a", "e", f"p{i}", w) for w in base] + [("c", "b", "e", f"p{i}", w) for w in other]
    df = spark.createDataFrame(rows, INSTANCE)
    j = 32 / 48
    got = {(r["prop_a"], r["prop_b"]): r["score"] for r in lsh.match(df, n_hash=200, band=1).collect()}
    assert all(abs(got[f"p{i}", f"p{i}"] - j) < 0.15 for i in range(12))
    sig = lsh.minhash(lsh.elements(df), 200)
    found = lsh.banded(sig, [10], 200).where("prop_a = prop_b").count()
    assert abs(found / 12 - lsh.candidate_chance(j, 10, 200)) < 0.35
    proj = {(r["prop_a"], r["prop_b"]): r["score"] for r in lsh.match(df, "projection", 300, 5).collect()}
    assert all(abs(proj[f"p{i}", f"p{i}"] - 0.8) < 0.2 for i in range(12) if (f"p{i}", f"p{i}") in proj)
    assert len(lsh.BANDS) == 18


def test_semgraph_sweep_equals_filters(spark):
    props = domains.instances(spark, SF, "event").select(*PROPERTY_KEY).distinct()
    scored = labelled(semgraph.scores(props, ex.lexicon(spark, SF)), domains.align_table(spark, ["event"])).withColumn("dataset", F.lit("event")).cache()
    got = {(r["syn_t"], r["neg_t"], r["pos_t"]): (r["tp"], r["fp"], r["fn"]) for r in semgraph.sweep(scored, spark).collect()}
    assert len(got) == 64
    for s, n, p in [(0.2, 0.2, 0.4), (0.8, 0.6, 0.2), (0.4, 0.8, 0.8)]:
        m = scored.withColumn("m", semgraph.decide(F.col("syn"), F.col("coherence"), F.lit(s), F.lit(n), F.lit(p)))
        c = m.agg(F.count_if(F.col("m") & (F.col("label") == 1)), F.count_if(F.col("m") & (F.col("label") == 0)), F.count_if(~F.col("m") & (F.col("label") == 1))).first()
        assert got[s, n, p] == tuple(c)


def test_boosted():
    rng = np.random.default_rng(3)
    x = rng.normal(size=(400, 5))
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0)).astype(int)
    m = boosted.fit(x, y, 50, 2)
    assert ((m.score(x) > 0.5) == y).mean() > 0.95 and ((m.score(x) >= 0) & (m.score(x) <= 1)).all()
    assert boosted.soundex("robert") == boosted.soundex("rupert") == "R163"
    assert len(boosted.catalogue("price tag", "tag price")) == len(boosted.CATALOGUE)


def test_clusters(spark):
    rows = [("c", "s1", "a", "s2", "b", 0.9, True), ("c", "s1", "a", "s2", "c", 0.8, True), ("c", "s2", "b", "s3", "d", 0.7, True), ("c", "s1", "x", "s3", "y", 0.6, True), ("c", "s1", "x", "s2", "b", 0.2, False)]
    sim = spark.createDataFrame(rows, "cls string, source_a string, prop_a string, source_b string, prop_b string, score double, is_match boolean")
    closure = {(r["source"], r["prop"]): r["cluster_id"] for r in graph.connected_components(sim).collect()}
    assert closure == {("s1", "a"): "c/s1/a", ("s2", "b"): "c/s1/a", ("s2", "c"): "c/s1/a", ("s3", "d"): "c/s1/a", ("s1", "x"): "c/s1/x", ("s3", "y"): "c/s1/x"}
    unique = {(r["source"], r["prop"]): r["cluster_id"] for r in graph.source_unique_clusters(sim).collect()}
    assert unique["s2", "b"] == unique["s1", "a"] == unique["s3", "d"] and unique["s2", "c"] == "c/s2/c"
    assert {(r["prop"], r["other_source"]): r["partners"] for r in graph.partners(sim).collect()}["a", "s2"] == ["b", "c"]
    assert graph.keep_equal(sim).count() == 3 and graph.topk(sim, 1).where("prop = 'a'").first()["other_prop"] == "b"


def test_measures(spark):
    sim = spark.createDataFrame([("c", "a", str(i), "b", str(i), 0.9, i < 3) for i in range(5)], "cls string, source_a string, prop_a string, source_b string, prop_b string, score double, is_match boolean")
    real = spark.createDataFrame([("c", "a", str(i), "b", str(i)) for i in (0, 1, 4, 7)], "cls string, source_a string, prop_a string, source_b string, prop_b string")
    r = metrics.prf(sim, real).first()
    assert (r["tp"], r["fp"], r["fn"]) == (2, 1, 2) and r["f1"] == pytest.approx(4 / 7)
    assert metrics.prf(sim.limit(0), real).first()["f1"] == 0
    runs = spark.createDataFrame([("d", 0.5, 1.0, 0.6), ("d", 1.0, 1.0, 1.0)], "dataset string, precision double, recall double, f1 double")
    s = metrics.summarise(runs, ["dataset"]).first()
    assert s["mean_f1"] == pytest.approx(0.8) and s["q50_precision"] == 0.75 and s["f1_of_means"] == pytest.approx(2 * 0.75 / 1.75)
    assert metrics.pr_curve(sim, real).first()["recall"] == 0.75


def test_readers(spark):
    df = spark.sql("select 1 as id, array(1, 2) as xs, map('k', 2.5D) as m, named_struct('u', named_struct('v', 'w')) as st, cast(null as string) as n")
    got = {(r["prop"], r["value"]) for r in readers.flatten(df.drop("id"), "c", F.lit("s"), F.lit("e")).collect()}
    assert got == {("xs", "1"), ("xs", "2"), ("m.k", "2.50"), ("st.u.v", "w")}
    wide = readers.unpivot(spark.createDataFrame([(1, 2.0, None)], "id int, x double, y string"), "c", F.lit("s"), F.col("id"), ["x", "y"]).collect()
    assert [(r["prop"], r["value"], r["entity"]) for r in wide] == [("x", "2.00", "1")]


def test_stream_equals_batch(spark):
    from propalign.queries import stream_profile
    from propalign.streaming.profiles import instance_stream, means, sums

    batch = means(sums(instance_stream(spark.read.parquet(f"{SF}/events.parquet")), PROPERTY_KEY))
    want = {(r["source"], r["prop"]): (r["n_instances"], round(r["num"], 4)) for r in batch.collect()}
    got = {(r["source"], r["prop"]): (r["n_instances"], r["num"]) for r in stream_profile(spark, SF).collect()}
    assert got.keys() == want.keys() and all(g[0] == want[k][0] and g[1] == pytest.approx(want[k][1], abs=2e-4) for k, g in got.items())


def test_helpers(spark, small):
    a = spark.createDataFrame([(1, 1.0), (2, 5.2)], "i int, x double")
    b = spark.createDataFrame([(1, 1.9), (2, 4.1), (3, 7.0)], "j int, y double")
    assert {(r["i"], r["j"]) for r in relational.range_band_join(a, b, "x", "y", 1.2).collect()} == {(1, 1), (2, 2)}
    assert relational.cap_entities(small, 1).where("source = 's1' and cls = 'c'").select("entity").distinct().count() == 1
    assert stats.min_support(small, 2).select("prop").distinct().collect()[0][0] == "screen size"
    from propalign import sqlapi

    sqlapi.register(spark, {"small_instances": small})
    assert spark.sql("select name_similarity('Price', 'price') s").first()["s"] == 1.0
    assert spark.sql("select count(*) n from name_distances('a b', 'a c')").first()["n"] == 8


def test_sample_pairs(spark):
    prof = profile(domains.instances(spark, SF, "goods"), ex.lexicon(spark, SF)).cache()
    rows = stats.sample_features(prof, labelled(candidates(prof), domains.align_table(spark, ["goods"]))).collect()
    assert sorted(r["label"] for r in rows) == [0, 0, 1, 1]
    one, zero = ([r["levenshtein"] for r in rows if r["label"] == y] for y in (1, 0))
    assert min(one) >= 0.5 * max(zero) or min(zero) <= max(one)  # edit distance alone doesn't part them


def test_entry_without_the_corpus_operators():
    import __spark_entry__

    assert {"ppc_score", "baseline_lexical"} <= set(__spark_entry__.queries()) and "truth_pairs" in __spark_entry__.oracle_sql()


@pytest.mark.parametrize("trainer", ["minibatch", "mllib"])
def test_saved_models_answer_alike(spark, tmp_path, trainer):
    prof = profile(domains.instances(spark, SF, "event"), ex.lexicon(spark, SF)).cache()
    sample = training_pairs(labelled(candidates(prof), domains.align_table(spark, ["event"])).where("source_a < 'e04' and source_b < 'e04'")).cache()
    spec = MatcherSpec(FeatureConfig("both", "non_embedding"), aggregate="max", distinct_values=True, numeric_missing=None, trainer=trainer)
    model = PropertyPairClassifier(spec).fit_profile(prof, sample)
    model.save(str(tmp_path / "model"))
    again = type(model).load(str(tmp_path / "model"))
    assert again.spec == model.spec and again.d == model.d
    rows = lambda m: {tuple(r)[:5]: r["score"] for r in m.score(prof).collect()}
    a, b = rows(model), rows(again)
    assert a.keys() == b.keys() and all(abs(a[k] - b[k]) < 1e-9 for k in a) and 0 < sum(v > 0.5 for v in a.values()) < len(a)


def test_tiles_are_dealt_to_many_tasks(spark):
    """Tiles of one class go to tasks by their own key, and give the scores of a single tile."""
    prof = profile(domains.instances(spark, SF, "goods"), ex.lexicon(spark, SF)).cache()
    sample = training_pairs(labelled(candidates(prof), domains.align_table(spark, ["goods"])).where("source_a < 'g06' and source_b < 'g06'")).cache()
    model = PropertyPairClassifier(MatcherSpec(FeatureConfig("names", "all"))).fit_profile(prof, sample)
    sim = model.score(prof).cache()
    parts = sim.groupBy(F.spark_partition_id()).count().collect()
    assert len(parts) >= 8 and max(r["count"] for r in parts) < 0.5 * sim.count()
    rows = lambda df: {tuple(r)[:5]: r["score"] for r in df.collect()}
    one, many = rows(model.score(prof, blocks=1)), rows(sim)
    assert one.keys() == many.keys() and all(abs(one[k] - many[k]) < 1e-6 for k in one)


def test_signatures_with_few_states_at_a_time(spark, monkeypatch):
    from propalign.baselines import lsh

    rows = lsh.elements(domains.instances(spark, SF, "event")).repartition(5).cache()
    of = lambda: {tuple(r)[:3]: list(r["sig"]) for f in (lsh.minhash, lsh.projection) for r in f(rows, 20).collect()}
    whole = of()
    monkeypatch.setattr(lsh, "HELD", 3)
    assert of() == whole


def test_large_numbers(spark):
    """Plain digits of any length are numbers, as far as doubles go; those with an exponent up to a size."""
    cases = {"4006381333931": 4006381333931.0, "1" * 300: float("1" * 300), "9" * 400: -1.0, "12e5678": -1.0, "1e12": 1e12, "1e13": -1.0, "-5000000000000.5": -5000000000000.5}
    got = {r["value"]: r["x"] for r in spark.createDataFrame([(v,) for v in cases], "value string").select("value", formats.numeric(F.col("value")).alias("x")).collect()}
    assert got == cases


def test_alike_names_are_all_found(spark):
    """The equi-joins of the lexical and lattice baselines against all pairs, at several scores, on names that are near copies."""
    rnd = random.Random(11)
    names = {"", "!!", "id", "a", "unit price of the item", "x" * 300, "x" * 299 + "y"}
    while len(names) < 90:
        name = rnd.choice(sorted(names)) if rnd.random() < 0.5 else "".join(rnd.choice("abc _") for _ in range(rnd.randint(1, 16)))
        for _ in range(rnd.randint(0, 3)):
            at = rnd.randint(0, len(name))
            name = name[:at] + rnd.choice(["", "a", "b", " ", "é"]) + name[at + rnd.randint(0, 1) :]
        names.add(name)
    props = spark.createDataFrame([(rnd.choice("cd"), f"s{rnd.randint(0, 3)}", n) for n in sorted(names) for _ in range(2)], "cls string, source string, prop string").distinct()
    told = lambda df: {tuple(r[c] for c in PAIR_KEY): (round(r["score"], 8), r["is_match"]) for r in df.collect()}
    props = graph.checkpointed(props)
    whole = told(lexical.match(props, cardinality="n:m", least=0))
    for least in (0.4, 0.75):
        want = {k: v for k, v in whole.items() if v[0] >= least}
        assert want and told(lexical.match(props, cardinality="n:m", least=least)) == want
    whole = told(lattice.match(props, every_pair=True))
    some = told(lattice.match(props))
    assert some == {k: v for k, v in whole.items() if v[0] > 0} and any(v[1] for v in some.values())
    assert told(lattice.match(props.where("false"))) == {}


def test_band_sweep_plans_one_join(spark):
    """All band sizes share one explode and one join, and both variants one pass over the words: the driver's plan stays small."""
    from propalign.baselines import lsh

    words = lsh.occurrences(domains.instances(spark, SF, "event"))
    sizes = {"minhash": 20, "projection": 30}
    states = lsh.signatures(words, sizes).cache()
    for variant, alone in (("minhash", lsh.minhash), ("projection", lsh.projection)):
        sig = lsh.signature_of(states, variant, sizes)
        of = lambda df: {tuple(r)[:3]: list(r["sig"]) for r in df.collect()}
        assert of(sig) == of(alone(lsh.elements(domains.instances(spark, SF, "event")), sizes[variant]))
        both = lsh.banded(sig, [1, 5, 10], sizes[variant])
        plan = both._jdf.queryExecution().optimizedPlan().toString()
        assert plan.count("Join Inner") == 1 and "Union" not in plan
        for r in (1, 5, 10):
            one = lsh.banded(sig, [r], sizes[variant])
            assert both.where(F.col("band") == r).exceptAll(one).isEmpty() and one.count() == both.where(F.col("band") == r).count()
