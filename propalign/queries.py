"""The registered queries of the matcher: each method, variant, baseline, measure and workload on the given tables."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from propalign.baselines import boosted, cosine, lattice, lexical, lsh, semgraph
from propalign.functions import formats, strings
from propalign.model import CONFIGS, PAIR_KEY, PROPERTY_KEY, FeatureConfig
from propalign.operators import graph
from propalign.operators.classifier import MatcherSpec, PropertyPairClassifier, PropertyPairModel
from propalign.operators.pairs import assemble, candidates, combine
from propalign.operators.profile import meta_profile, name_embedding, profile, value_embedding, value_word_weights
from propalign.operators.sampling import labelled, training_pairs, truth
from propalign.plans import experiments as ex
from propalign.plans import metrics, splits, stats
from propalign.sources.domains import DOMAINS, align_table, instances, source_name

ALL = tuple(DOMAINS)


def every(spark: SparkSession, sf: str, domains: tuple[str, ...] = ALL) -> DataFrame:
    return reduce(DataFrame.unionByName, [instances(spark, sf, c) for c in domains])


def properties(spark: SparkSession, sf: str, domains: tuple[str, ...] = ALL) -> DataFrame:
    """A row for each property; kept once, since matchers read both sides of their pairs from it."""
    return graph.checkpointed(every(spark, sf, domains).select(*PROPERTY_KEY).distinct())


def _rounded(df: DataFrame, columns: list[str], digits: int = 4) -> DataFrame:
    return df.withColumns({c: F.round(F.col(c), digits) for c in columns})


# --- data


def instances_of(cls: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf: instances(spark, sf, cls)


def property_catalog(spark, sf):
    return stats.property_catalog(every(spark, sf))


def dataset_statistics(spark, sf):
    return stats.dataset_stats(every(spark, sf), truth(align_table(spark)))


def source_statistics(spark, sf):
    return stats.source_stats(every(spark, sf))


def entity_cap(spark, sf):
    return instances(spark, sf, "goods").groupBy("source").agg(F.count_distinct("entity").alias("n_entities"))


# --- features


def char_features(spark, sf):
    values = every(spark, sf).select("value").distinct()
    meta = formats.with_meta(values)
    return meta.select("value", *[F.col(f"n_{n}").cast("int").alias(f"n_{n}") for n in formats.CHAR_NAMES], F.round("share_letter", 4).alias("share_letter"), F.round("share_number", 4).alias("share_number"))


def token_features(spark, sf):
    meta = formats.with_meta(every(spark, sf).select("value").distinct())
    return meta.select("value", *[F.col(f"n_token_{n}").cast("int").alias(f"n_{n}") for n in formats.TOKEN_NAMES], F.round("share_token_numeric", 4).alias("share_numeric"))


def numeric_feature(spark, sf):
    return every(spark, sf).select("value").distinct().select("value", F.round(formats.numeric(F.col("value")), 4).alias("num"))


def word_weights(spark, sf):
    return _rounded(value_word_weights(every(spark, sf)), ["weight"]).withColumn("word", F.coalesce("word", F.lit("")))


def _vector_digest(df: DataFrame, name: str) -> DataFrame:
    norm = F.sqrt(F.aggregate(name, F.lit(0.0), lambda s, x: s + x * x))
    return df.select(*PROPERTY_KEY, F.round(F.col(name)[0], 4).alias("first"), F.round(F.element_at(name, -1), 4).alias("last"), F.round(norm, 4).alias("norm"))


def value_vectors(spark, sf):
    return _vector_digest(value_embedding(every(spark, sf), ex.lexicon(spark, sf)), "val_emb")


def name_vectors(spark, sf):
    return _vector_digest(name_embedding(properties(spark, sf), ex.lexicon(spark, sf)), "name_emb")


def property_profile(spark, sf):
    meta = meta_profile(every(spark, sf))
    return meta.select(*PROPERTY_KEY, "n_instances", *[F.round(F.col("meta")[i], 4).alias(f"m{i}") for i in range(28)], F.round("num", 4).alias("num"))


def profile_variant(agg: str, distinct: bool = False) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark, sf):
        out = profile(every(spark, sf), ex.lexicon(spark, sf), agg, distinct)
        return out.select(*PROPERTY_KEY, "n_instances", *[F.round(F.col("meta")[i], 4).alias(f"m{i}") for i in range(28)], F.round("num", 4).alias("num"))

    return query


# --- pairs


def candidate_pairs(spark, sf):
    return candidates(properties(spark, sf))


def candidate_pairs_blocks(spark, sf):
    return candidates(properties(spark, sf), strategy="blocks", blocks=5)


def truth_pairs(spark, sf):
    """Pairs of properties that occur in the tables."""
    found = every(spark, sf).select(*PROPERTY_KEY).distinct()
    return truth(align_table(spark).join(found, PROPERTY_KEY, "left_semi"))


def pair_combination(mode: str) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark, sf):
        meta = meta_profile(every(spark, sf)).withColumn("v", F.concat("meta", F.array("num")))
        pairs = candidates(meta, ["v"]).withColumn("x", combine(F.col("v_a"), F.col("v_b"), mode))
        total = F.aggregate("x", F.lit(0.0), lambda s, x: s + x)
        # Numbers of values are large; a logarithm keeps as many digits of each as two engines agree in.
        told = lambda c: F.round(F.signum(c) * F.log1p(F.abs(c)), 6) + F.lit(0.0)  # noqa: E731  no negative zeros
        return pairs.select(*PAIR_KEY, F.size("x").alias("width"), told(F.col("x")[0]).alias("first"), told(F.element_at("x", -1)).alias("last"), told(total).alias("total"))

    return query


def name_distance(kind: str) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark, sf):
        pairs = candidates(properties(spark, sf)).select("prop_a", "prop_b").distinct()
        return strings.distances(pairs, [kind]).select("prop_a", "prop_b", F.round(f"dist_{kind}", 6).alias("dist"))

    return query


# --- splits and samples


def sd_splits(spark, sf):
    """Splits of the sources that occur in the tables."""
    found = every(spark, sf).select("cls", "source").distinct().collect()  # a few dozen
    # A pair takes two sources.
    of = {c: sorted(r["source"] for r in found if r["cls"] == c) for c in ALL}
    return reduce(DataFrame.unionByName, [splits.splits(spark, c, of[c] if len(of[c]) > 1 else []) for c in ALL])


def _labelled(spark, sf, domains=ALL):
    return labelled(candidates(properties(spark, sf, domains)), align_table(spark, list(domains)))


def labelled_pairs(spark, sf):
    return _labelled(spark, sf)


def negative_sample(spark, sf):
    return training_pairs(_labelled(spark, sf)).where("label = 0")


def sample_of_pairs(spark, sf):
    return training_pairs(_labelled(spark, sf))


def split_pairs(spark, sf):
    """Training and test pairs of every run of every dataset."""
    dealt = splits.deal(_labelled(spark, sf), sd_splits(spark, sf))
    return dealt.groupBy("dataset", "fraction", "run").agg(
        F.count_if("in_train").alias("n_train"), F.count_if(F.col("in_train") & (F.col("label") == 1)).alias("n_train_matches"),
        F.count_if(~F.col("in_train")).alias("n_test"), F.count_if(~F.col("seen")).alias("n_unseen"),
    )


def tl_combinations(spark, sf):
    """Combinations of the datasets that occur in the tables."""
    found = {r["cls"] for r in every(spark, sf).select("cls").distinct().collect()}
    return spark.createDataFrame(splits.transfer_combinations(tuple(c for c in ALL if c in found)), "train_set string, target string")


# --- baselines


def baseline_lexical(spark, sf):
    return lexical.match(properties(spark, sf), least=0)


def baseline_lexical_many(spark, sf):
    return lexical.match(properties(spark, sf), cardinality="n:m", least=0)


def lexical_alike(spark, sf):
    """The pairs that reach the threshold, by equi-joins: no other pair is made."""
    return lexical.match(properties(spark, sf))


def lexical_alike_many(spark, sf):
    return lexical.match(properties(spark, sf), cardinality="n:m")


def baseline_lexical_synonyms(spark, sf):
    from propalign.functions.lexicon import word_concepts

    concepts = spark.createDataFrame([(w, f"concept{c}") for w, c, _ in word_concepts()], "word string, concept string")
    return lexical.match(properties(spark, sf), synonyms=concepts, least=0)


def baseline_lattice(spark, sf):
    return lattice.match(properties(spark, sf), every_pair=True)


def lattice_sharing(spark, sf):
    """The pairs that share a word, by an equi-join."""
    return lattice.match(properties(spark, sf))


def baseline_semgraph(spark, sf):
    return semgraph.match(properties(spark, sf), ex.lexicon(spark, sf))


def semgraph_sweep(spark, sf):
    return _rounded(ex.semgraph_grid(spark, sf), ["mean_f1"])


def baseline_minhash(spark, sf):
    return lsh.match(every(spark, sf))


def baseline_projection(spark, sf):
    return lsh.match(every(spark, sf), "projection", band=20)


def lsh_sweep(spark, sf):
    return _rounded(ex.lsh_grid(spark, sf), ["mean_f1"])


def baseline_cosine(spark, sf):
    return cosine.match(name_embedding(properties(spark, sf), ex.lexicon(spark, sf)), least=-1)


def cosine_alike(spark, sf):
    return cosine.match(name_embedding(properties(spark, sf), ex.lexicon(spark, sf)))


def flat_baselines(spark, sf):
    return _rounded(ex.flat_baselines(spark, sf), ["precision", "recall", "f1"])


# --- the classifier


def _prepared(spark, sf, cls):
    """A dataset's profiles, and a sample of the labelled pairs between the first half of its sources."""
    prof = graph.checkpointed(profile(instances(spark, sf, cls), ex.lexicon(spark, sf)))
    half = source_name(DOMAINS[cls], DOMAINS[cls].sources // 2)
    given = labelled(candidates(prof), align_table(spark, [cls])).where((F.col("source_a") < half) & (F.col("source_b") < half))
    return prof, graph.checkpointed(training_pairs(given))


def _ppc(spark, sf, domains=ALL, configs=(FeatureConfig(),), mode="abs_diff", trainer="minibatch", **score):
    """Trains on a sample of the pairs between the first half of the sources of each dataset, scores all its others."""
    parts = []
    for cls in domains:
        prof, sample = _prepared(spark, sf, cls)
        for c in configs:
            model = PropertyPairClassifier(MatcherSpec(c, mode=mode, trainer=trainer)).fit_profile(prof, sample)
            parts.append(model.score(exclude=sample, **score).withColumn("config", F.lit(c.name)))
    return reduce(DataFrame.unionByName, parts)


def ppc_score(spark, sf):
    """The classifier on the largest dataset; ppc_all_pairs has all of them."""
    return _ppc(spark, sf, ("goods",)).drop("config")


def ppc_all_pairs(spark, sf):
    return _ppc(spark, sf, include_labelled=True).drop("config")


def ppc_mode(mode: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf: _ppc(spark, sf, mode=mode).drop("config")


def ppc_mllib(spark, sf):
    return _ppc(spark, sf, trainer="mllib").drop("config")


def ppc_configs(spark, sf):
    return _ppc(spark, sf, configs=CONFIGS)


def ppc_fixed(spark, sf):
    """Scores of a network whose weights come from a rule, so that other engines can compute them too: on all datasets."""
    prof = graph.checkpointed(profile(every(spark, sf), ex.lexicon(spark, sf)))
    d = prof.select(F.size("name_emb")).first()[0]
    model = PropertyPairModel(MatcherSpec(), ex.ruled_network(29 + 2 * d + 8), d, prof)
    return _rounded(model.score(), ["score"], 5).drop("is_match")


def assembled_features(spark, sf):
    """Pairs with their combined features and the eight name distances, as ML pipelines get them."""
    prof = graph.checkpointed(profile(every(spark, sf), ex.lexicon(spark, sf)))
    rows = assemble(prof)
    at = lambda i: F.round(F.element_at("features", i), 9)
    return rows.select(*PAIR_KEY, F.size("features").alias("width"), at(2).alias("letter_share"), F.round(F.log1p(F.element_at("features", 29)), 6).alias("number"), *[F.round(F.element_at("features", i - 8), 6).alias(f"dist_{k}") for i, k in enumerate(strings.DISTANCES)])


def boosted_score(spark, sf):
    parts = []
    for cls in ALL:
        rows = graph.checkpointed(_labelled(spark, sf, (cls,)))
        half = source_name(DOMAINS[cls], DOMAINS[cls].sources // 2)
        sample = training_pairs(rows.where((F.col("source_a") < half) & (F.col("source_b") < half)))
        parts.append(boosted.fit_pairs(sample).score_pairs(rows.join(sample.select(*PAIR_KEY), PAIR_KEY, "left_anti")))
    return reduce(DataFrame.unionByName, parts)


def run_sizes(spark, sf):
    """Pairs and matches in the test of every training of the single-domain grid (names' vectors), as the trained runs count them."""
    data = ex.prepare(spark, sf)
    runs = ex.run_grid(spark, data, ex.single_domain_grid(data, configs=[FeatureConfig("names", "embedding")], boosted_too=False), "single_domain")
    return runs.select("dataset", "fraction", "run", (F.col("tp") + F.col("fp") + F.col("fn") + F.col("tn")).alias("n_test"), (F.col("tp") + F.col("fn")).alias("n_test_matches"))


def sd_results(spark, sf):
    """All nine configurations and the supervised baseline, at four fractions with 25 runs each, on every dataset."""
    data = ex.prepare(spark, sf)
    return ex.run_grid(spark, data, ex.single_domain_grid(data), "single_domain")


def sd_summary(spark, sf):
    """Distributions over the 25 runs of every fraction and dataset: origin both, three kinds."""
    data = ex.prepare(spark, sf)
    grid = ex.single_domain_grid(data, configs=[FeatureConfig("both", k) for k in ("embedding", "non_embedding", "all")], boosted_too=False)
    return metrics.summarise(ex.run_grid(spark, data, grid, "single_domain"), ["dataset", "fraction", "config"])


def tl_results(spark, sf):
    """All 28 combinations, each with the nine configurations and the supervised baseline."""
    data = ex.prepare(spark, sf)
    return ex.transfer_flags(ex.run_grid(spark, data, ex.transfer_grid(data), "transfer"))


def network_sensitivity(spark, sf):
    data = ex.prepare(spark, sf)
    return ex.run_grid(spark, data, ex.network_grid(data), "network")


def anonymous_names(spark, sf):
    """Names that mean nothing: only values can tell. The whole single-domain grid."""
    data = ex.prepare(spark, sf, anonymous=True)
    return ex.run_grid(spark, data, ex.single_domain_grid(data), "anonymous")


def lexicon_control(spark, sf):
    """The whole grid with vectors of a given list of concepts, with some that mean nothing, and with some learned from the values
    beside each name."""
    return ex.lexicon_runs(spark, sf)


# --- measures and graphs


def metrics_prf(spark, sf):
    real = truth(align_table(spark))
    rows = [metrics.prf(m, real).withColumn("method", F.lit(n)) for n, m in (("lexical", lexical_alike(spark, sf)), ("lattice", lattice_sharing(spark, sf)), ("semgraph", baseline_semgraph(spark, sf)))]
    return _rounded(reduce(DataFrame.unionByName, rows), ["precision", "recall", "f1"])


def best_config(spark, sf):
    return metrics.best(metrics_prf(spark, sf), ["cls"], "f1")


def f1_gap(spark, sf):
    return _rounded(metrics.gap(metrics_prf(spark, sf), "semgraph", ["cls"], measure="f1"), ["gap_points"], 2)


def metrics_cube(spark, sf):
    return metrics.cube(metrics_prf(spark, sf), ["cls", "method"])


def pr_curve(spark, sf):
    return _rounded(metrics.pr_curve(baseline_lexical_many(spark, sf), truth(align_table(spark))), ["precision", "recall"])


def similarity_graph(spark, sf):
    return graph.similarity_graph(lexical.match(properties(spark, sf), cardinality="n:m", least=0.5), 0.5)


def one_to_many(spark, sf):
    """An order's date in one source and its year and month in others: one property with several partners."""
    real = truth(align_table(spark, ["order"])).withColumns({"score": F.lit(1.0), "is_match": F.lit(True)})
    found = properties(spark, sf, ("order",))
    rows = graph.partners(real).join(found, PROPERTY_KEY, "left_semi").where("n_partners > 1")
    return rows.withColumn("partners", F.concat_ws("|", "partners"))


def clusters_transitive(spark, sf):
    return graph.connected_components(lattice_sharing(spark, sf))


def clusters_source_unique(spark, sf):
    return graph.source_unique_clusters(baseline_semgraph(spark, sf))


def partners_topk(spark, sf):
    return graph.topk(baseline_cosine(spark, sf))


def partners_many(spark, sf):
    out = graph.partners(lattice_sharing(spark, sf))
    return out.withColumn("partners", F.concat_ws("|", "partners"))


def equal_matches(spark, sf):
    return graph.keep_equal(lexical_alike_many(spark, sf))


def fused_values(spark, sf):
    goods = instances(spark, sf, "goods")
    return graph.fuse_values(goods, graph.connected_components(lattice.match(properties(spark, sf, ("goods",)))))


def sample_features(spark, sf):
    prof = profile(instances(spark, sf, "goods"), ex.lexicon(spark, sf))
    return _rounded(stats.sample_features(prof, labelled(candidates(prof), align_table(spark, ["goods"]))), ["letter_share", "number", "value_vector_4", "name_vector_2"])


def stream_profile(spark, sf):
    """Profiles from a stream over the events file, kept as sums by day and merged."""
    from propalign.streaming.profiles import instance_stream, means, profile_stream

    path = f"{sf}/events.parquet"
    schema = spark.read.parquet(path).schema
    stream = spark.readStream.schema(schema).parquet(path + "*" if not path.endswith("*") else path)
    name = f"profiles_{uuid.uuid4().hex}"
    root = spark.conf.get("spark.checkpoint.dir", None) or os.path.join(tempfile.gettempdir(), "propalign-checkpoints")
    sink = f"{root}/{name}"
    query = profile_stream(instance_stream(stream), "1 hour").writeStream.foreachBatch(lambda df, i: df.write.mode("overwrite").parquet(f"{sink}/rows/batch={i}")).option("checkpointLocation", f"{sink}/state").outputMode("update").trigger(availableNow=True).start()
    query.awaitTermination()
    rows = spark.read.parquet(f"{sink}/rows")
    # An update replaces what an earlier batch said about the same property and window.
    last = rows.groupBy(*PROPERTY_KEY, "win").agg(F.max_by(F.struct(*[c for c in rows.columns if c == "n" or c.startswith("s_")]), "batch").alias("x"))
    out = means(last.select(*PROPERTY_KEY, "x.*"))
    return out.select(*PROPERTY_KEY, "n_instances", *[F.round(F.col("meta")[i], 4).alias(f"m{i}") for i in range(28)], F.round("num", 4).alias("num"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    **{f"instances_{c}": instances_of(c) for c in (*ALL, "text")},
    **{
        f.__name__: f
        for f in (
            property_catalog, dataset_statistics, source_statistics, entity_cap, char_features, token_features, numeric_feature,
            property_profile, candidate_pairs, candidate_pairs_blocks, truth_pairs, labelled_pairs, sd_splits, negative_sample, split_pairs, tl_combinations,
            baseline_lexical, baseline_lexical_many, baseline_lexical_synonyms, baseline_lattice, lexical_alike, lexical_alike_many, lattice_sharing, cosine_alike, baseline_semgraph, semgraph_sweep, baseline_minhash,
            baseline_projection, lsh_sweep, baseline_cosine, flat_baselines, ppc_score, ppc_all_pairs, ppc_mllib, ppc_configs, ppc_fixed, assembled_features, boosted_score, sd_results, run_sizes,
            sd_summary, tl_results, network_sensitivity, anonymous_names, lexicon_control, metrics_prf, best_config, f1_gap, metrics_cube, pr_curve, similarity_graph, one_to_many, clusters_transitive,
            clusters_source_unique, partners_topk, partners_many, equal_matches, fused_values, sample_features, stream_profile,
        )
    },
    "value_word_weights": word_weights, "value_embedding": value_vectors, "name_embedding": name_vectors, "training_pairs": sample_of_pairs,
    **{f"pair_{m}": pair_combination(m) for m in ("abs_diff", "diff", "mean", "concat")},
    **{f"ppc_{m}": ppc_mode(m) for m in ("diff", "mean", "concat")},
    **{f"dist_{k}": name_distance(k) for k in strings.DISTANCES},
    **{f"profile_{a}": profile_variant(a) for a in ("median", "min", "max", "stddev")},
    "profile_distinct": profile_variant("mean", True),
}
