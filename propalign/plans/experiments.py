"""The experiments: training fractions of one domain, transfer between domains, baselines, ablations and sweeps.

Every training is a row of a grid and a task of its own. The profiles of the experiment's datasets (a vector for each
property: some hundred kB) are checked in size and broadcast; a task forms the pairs it needs, trains, and returns counts.
No score is stored. Similarities of names, which trainings share, are made once, in tasks, and broadcast too.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import replace
from functools import reduce

import numpy as np
import pandas as pd
from pyspark import InheritableThread
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from propalign.baselines import boosted, cosine, lattice, lexical, lsh, semgraph
from propalign.functions.lexicon import blended, hashed
from propalign.functions.strings import DISTANCES, all_eight, normal_py
from propalign.model import CONFIGS, PAIR_KEY, PROPERTY_KEY, RUNMETRIC, FeatureConfig
from propalign.operators.graph import checkpointed
from propalign.operators.network import Network, NetworkSpec, fit
from propalign.operators.profile import meta_profile, name_embedding, value_embedding, vector_of
from propalign.operators.sampling import labelled, truth
from propalign.plans.metrics import prf, with_scores
from propalign.plans.splits import FRACTIONS, RUNS, training_sources, transfer_combinations
from propalign.sources.domains import DOMAINS, align_table, instances

DATASETS = tuple(DOMAINS)
#: The most properties of a dataset whose vectors experiments broadcast (about 3 kB each).
MOST_PROPERTIES = 20_000
#: The most different pairs of names whose similarities are broadcast (160 bytes each); beyond, each worker makes those that it meets.
SHARED_NAMES = 500_000
#: Pairs of names of a chunk.
NAMES_AT_ONCE = 500


def lexicon(spark: SparkSession, sf_dir: str, kind: str = "blended") -> DataFrame:
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding")
    if kind == "trained":
        from propalign.functions.lexicon import trained

        # A name among the values that stand beside it: names of like values get like vectors, without any list of concepts.
        parts = [instances(spark, sf_dir, c) for c in DATASETS]
        return trained(reduce(DataFrame.unionByName, parts).select(F.concat_ws(" ", "prop", "value", "prop").alias("text")))
    return {"blended": blended, "hashed": hashed}[kind](spark, vectors)


def ruled_network(width: int, hidden: tuple[int, ...] = (8, 4)) -> Network:
    """A network with weights from a rule: multiples of 1/1000 that other engines can write down."""
    sizes = [width, *hidden, 2]
    weight = lambda k, i, j: ((i * 37 + j * 101 + k * 53) % 41 - 20) / 1000
    weights = [np.array([[weight(k, i, j) for j in range(b)] for i in range(a)]) for k, (a, b) in enumerate(zip(sizes, sizes[1:], strict=False))]
    return Network(NetworkSpec(hidden=hidden, scale="none"), np.zeros(width), np.ones(width), weights, [np.full(b, 0.01) for b in sizes[1:]])


class Dataset:
    """Vectors, names, sources and reference properties of one dataset, as arrays; pairs are made when they are needed."""

    def __init__(self, rows: pd.DataFrame):
        rows = rows.sort_values(["source", "prop"]).reset_index(drop=True)
        self.source, self.prop = rows["source"].to_numpy(), rows["prop"].tolist()
        self.ref = rows["ref_prop"].tolist()
        self.vec = np.stack(rows["vec"].map(lambda v: np.asarray(v, dtype=np.float32))) if len(rows) else np.zeros((0, 29), dtype=np.float32)
        a, b = np.triu_indices(len(rows), 1)
        ok = self.source[a] != self.source[b]
        self.a, self.b = a[ok], b[ok]
        refs = {r: i for i, r in enumerate(sorted({r for r in self.ref if isinstance(r, str)}))}
        code = np.array([refs.get(r, -1) for r in self.ref])
        self.label = ((code[self.a] == code[self.b]) & (code[self.a] >= 0)).astype(int)
        norm = [normal_py(p) for p in self.prop]
        self.names = sorted(set(norm))
        place = {n: i for i, n in enumerate(self.names)}
        code = np.array([place[n] for n in norm], dtype=int)
        # Different pairs of normal names, by number, and which of them each pair of properties has.
        self.named, self.name_at = np.unique(code[self.a] * len(self.names) + code[self.b], return_inverse=True)
        self.alike: np.ndarray | None = None  # of named, if shared

    def name_pair(self, i: int) -> tuple[str, str]:
        a, b = divmod(int(self.named[i]), len(self.names))
        return self.names[a], self.names[b]

    def _of_names(self, at: np.ndarray, f, width: int) -> np.ndarray:
        if self.alike is not None:
            return self.alike[self.name_at[at], :width]
        ids, back = np.unique(self.name_at[at], return_inverse=True)
        return np.array([f(*self.name_pair(i)) for i in ids], dtype=float).reshape(-1, width)[back]

    def features(self, at: np.ndarray, config: FeatureConfig = FeatureConfig()) -> np.ndarray:
        """A configuration's columns of what pair_matrix() makes of these pairs."""
        end = self.vec.shape[1]
        slices = config.slices((end - 29) // 2)
        columns = np.concatenate([np.arange(x, y) for x, y in slices])
        vec = self.vec[:, columns[columns < end]].astype(float)
        parts = [np.abs(vec[self.a[at]] - vec[self.b[at]])]
        if columns[-1] >= end:
            parts.append(self._of_names(at, all_eight, len(DISTANCES)))
        return np.concatenate(parts, 1)

    def catalogue(self, at: np.ndarray) -> np.ndarray:
        return self._of_names(at, boosted.catalogue, len(boosted.CATALOGUE))

    def sample(self, within: np.ndarray, ratio: int, seed: str) -> np.ndarray:
        """Places of all matches within, and ratio times as many others, at random by the seed."""
        pos = within[self.label[within] == 1]
        neg = within[self.label[within] == 0]
        rng = np.random.default_rng(int(hashlib.md5(seed.encode()).hexdigest()[:8], 16))
        take = min(len(neg), ratio * len(pos))
        return np.sort(np.concatenate([pos, rng.choice(neg, take, replace=False) if take else neg[:0]]))


def _spread(spark: SparkSession, sf_dir: str, datasets: tuple[str, ...]) -> DataFrame:
    """Instances of all datasets, by all cores even where a table is a single small file."""
    tasks = spark.sparkContext.defaultParallelism
    return reduce(DataFrame.unionByName, [instances(spark, sf_dir, cls, tasks) for cls in datasets])


def _fetched(rows: DataFrame, align: DataFrame, datasets: tuple[str, ...]) -> dict[str, Dataset]:
    """rows: (property, vec), of all datasets."""
    got = rows.join(align, PROPERTY_KEY, "left").limit(len(datasets) * MOST_PROPERTIES + 1).toPandas()
    out = {}
    for cls in datasets:
        part = got[got["cls"] == cls]
        if len(part) > MOST_PROPERTIES or len(got) > len(datasets) * MOST_PROPERTIES:
            raise ValueError(f"{cls if len(part) > MOST_PROPERTIES else 'a dataset'} has more than {MOST_PROPERTIES} properties; the matcher itself takes any number")
        out[cls] = Dataset(part)
    return out


def prepare(spark: SparkSession, sf_dir: str, datasets: tuple[str, ...] = DATASETS, lex: str = "blended", anonymous: bool = False) -> dict[str, Dataset]:
    """The datasets of an experiment, profiled together. anonymous: names become meaningless identifiers."""
    words = lexicon(spark, sf_dir, lex)
    inst, align = _spread(spark, sf_dir, datasets), align_table(spark, list(datasets))
    if anonymous:
        inst, align = (x.withColumn("prop", F.md5(F.concat_ws("|", "source", "prop"))) for x in (inst, align))
    meta = checkpointed(meta_profile(inst))
    prof = meta.join(value_embedding(inst, words), PROPERTY_KEY).join(name_embedding(meta, words), PROPERTY_KEY)
    return _fetched(prof.select(*PROPERTY_KEY, vector_of(prof).alias("vec")), align, datasets)


def lexicon_runs(spark: SparkSession, sf_dir: str, kinds: tuple[str, ...] = ("blended", "hashed", "trained"), datasets: tuple[str, ...] = DATASETS) -> DataFrame:
    """The single-domain grid of names' vectors for each kind of lexicon. No other feature enters, so properties are listed once
    and meet each lexicon. Learning vectors is a long row of short jobs; the other kinds are trained beside it."""
    config = FeatureConfig("names", "embedding")
    align = align_table(spark, list(datasets))
    learned: list[DataFrame | BaseException] = []

    def learn() -> None:
        try:
            learned.append(lexicon(spark, sf_dir, "trained"))
        except BaseException as e:  # noqa: BLE001  it is raised where the vectors are needed
            learned.append(e)

    thread = InheritableThread(target=learn) if "trained" in kinds else None
    if thread:
        thread.start()
    props = checkpointed(_spread(spark, sf_dir, datasets).select(*PROPERTY_KEY).distinct())

    def runs(kind: str, words: DataFrame) -> DataFrame:
        # In a profile's vector, zeros for what the configuration leaves out.
        vec = F.concat(F.array_repeat(F.lit(0.0), 29 + F.size("name_emb")), F.col("name_emb").cast("array<double>"))
        data = _fetched(name_embedding(props, words).select(*PROPERTY_KEY, vec.alias("vec")), align, datasets)
        return run_grid(spark, data, single_domain_grid(data, configs=[config], boosted_too=False), f"lexicon_{kind}")

    parts = {k: checkpointed(runs(k, lexicon(spark, sf_dir, k))) for k in kinds if k != "trained"}
    if thread:
        thread.join()
        if isinstance(learned[0], BaseException):
            raise learned[0]
        parts["trained"] = runs("trained", learned[0])
    return reduce(DataFrame.unionByName, [parts[k] for k in kinds])


def _counts(data: Dataset, test: np.ndarray, predict, cost: int = 2_000) -> tuple[int, int, int, int]:
    tp = fp = fn = tn = 0
    for at in range(0, len(test), cost):
        rows = test[at : at + cost]
        p, y = predict(rows) > 0.5, data.label[rows] == 1
        tp, fp, fn, tn = tp + int((p & y).sum()), fp + int((p & ~y).sum()), fn + int((~p & y).sum()), tn + int((~p & ~y).sum())
    return tp, fp, fn, tn


def _train_and_count(data: dict[str, Dataset], row: dict, ratio: int, eval_negatives: str | int, test_scope: str) -> tuple[int, int, int, int]:
    target = data[row["dataset"]]
    every = np.arange(len(target.a))
    seed = f"{row['dataset']}|{row['fraction']}|{row['run']}"
    if row["sources"]:
        chosen = np.isin(target.source, row["sources"].split(","))
        both, one = chosen[target.a] & chosen[target.b], chosen[target.a] | chosen[target.b]
        train = [(target, target.sample(every[both], ratio, seed))]
        test = every[~one] if test_scope == "unseen_only" else every[~both]
    else:
        train = [(data[d], data[d].sample(np.arange(len(data[d].a)), ratio, f"{d}|{row['train_set']}")) for d in row["train_set"].split("+")]
        test = every
    if eval_negatives != "all":
        test = target.sample(test, int(eval_negatives), seed + "|test")
    y = np.concatenate([d.label[at] for d, at in train])
    if row["method"] == "boosted_catalogue":
        model = boosted.fit(np.concatenate([d.catalogue(at) for d, at in train]), y)
        return _counts(target, test, lambda rows: model.score(target.catalogue(rows)))
    config = FeatureConfig(*row["config"].split("/"))
    hidden = tuple(map(int, row["hidden"].split("-")))
    x = np.concatenate([d.features(at, config) for d, at in train])
    net = fit(x, y, replace(NetworkSpec(), hidden=hidden))
    return _counts(target, test, lambda rows: net.score(target.features(rows, config)))


def share_names(spark: SparkSession, data: dict[str, Dataset]) -> None:
    """The similarities of the different pairs of names, made in tasks, for all trainings."""
    todo = {k: d for k, d in data.items() if d.alike is None and 0 < len(d.named) <= SHARED_NAMES}
    chunks = [(k, at) for k, d in todo.items() for at in range(0, len(d.named), NAMES_AT_ONCE)]
    if not chunks:
        return
    shared = spark.sparkContext.broadcast((todo, chunks))

    def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        given, parts = shared.value
        for b in batches:
            for i in b["id"]:
                d, at = given[parts[i][0]], parts[i][1]
                rows = [boosted.catalogue(*d.name_pair(j)) for j in range(at, min(at + NAMES_AT_ONCE, len(d.named)))]
                yield pd.DataFrame({"id": [i], "rows": [np.array(rows, dtype=float).tobytes()]})

    tasks = min(len(chunks), 4 * spark.sparkContext.defaultParallelism)
    got = {r["id"]: r["rows"] for r in spark.range(0, len(chunks), 1, tasks).mapInPandas(work, "id long, rows binary").collect()}
    shared.unpersist()
    for k, d in todo.items():
        d.alike = np.concatenate([np.frombuffer(got[i]).reshape(-1, len(boosted.CATALOGUE)) for i, c in enumerate(chunks) if c[0] == k])


def _work_of(data: dict[str, Dataset], row: dict) -> float:
    """About how many matches a training learns from."""
    if not row["sources"]:
        return float(sum(data[d].label.sum() for d in row["train_set"].split("+")))
    d = data[row["dataset"]]
    return float(((row["sources"].count(",") + 1) / len(set(d.source))) ** 2 * d.label.sum())


def run_grid(spark: SparkSession, data: dict[str, Dataset], grid: list[dict], experiment: str, ratio: int = 2, eval_negatives: str | int = "all", test_scope: str = "rest") -> DataFrame:
    """RUNMETRIC rows, one for each row of the grid, each trained in a task."""
    rows = [{"dataset": g.get("dataset"), "method": g.get("method", "ppc"), "config": g.get("config", "both/all"), "fraction": float(g.get("fraction", 0.0)), "run": int(g.get("run", 0)), "train_set": g.get("train_set", ""), "sources": g.get("sources", ""), "hidden": g.get("hidden", "128-64")} for g in grid]
    if any(r["method"] == "boosted_catalogue" or not r["config"].startswith("instances") and not r["config"].endswith("/embedding") for r in rows):
        share_names(spark, data)
    # Long and short trainings are dealt out evenly.
    tasks = min(len(rows), 8 * spark.sparkContext.defaultParallelism) or 1
    work_of = {k: _work_of(data, r) for k, r in {(r["dataset"], r["train_set"], r["sources"]): r for r in rows}.items()}
    rows.sort(key=lambda r: -work_of[r["dataset"], r["train_set"], r["sources"]])
    rows = [r for k in range(tasks) for r in rows[k::tasks]]
    shared = spark.sparkContext.broadcast((data, rows))

    def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        given, todo = shared.value
        for b in batches:
            out = []
            for i in b["id"]:
                r = todo[i]
                out.append((experiment, r["dataset"], r["method"], r["config"] + ("" if r["hidden"] == "128-64" else f"@{r['hidden']}"), r["fraction"], r["run"], r["train_set"], *_train_and_count(given, r, ratio, eval_negatives, test_scope)))
            yield pd.DataFrame(out, columns=["experiment", "dataset", "method", "config", "fraction", "run", "train_set", "tp", "fp", "fn", "tn"])

    counted = spark.range(0, len(rows), 1, tasks).mapInPandas(work, ", ".join(x for x in RUNMETRIC.split(", ") if x.split()[0] not in ("precision", "recall", "f1")))
    return with_scores(counted)


def single_domain_grid(data: dict[str, Dataset], fractions: tuple[float, ...] = FRACTIONS, runs: int = RUNS, configs: list[FeatureConfig] = CONFIGS, boosted_too: bool = True, seed: int = 7) -> list[dict]:
    out = []
    for name, d in data.items():
        for f in fractions:
            for run, chosen in enumerate(training_sources(sorted(set(d.source)), f, runs, seed)):
                row = {"dataset": name, "fraction": f, "run": run, "sources": ",".join(chosen)}
                out += [row | {"config": c.name} for c in configs]
                if boosted_too:
                    out.append(row | {"method": "boosted_catalogue", "config": "names"})
    return out


def transfer_grid(data: dict[str, Dataset], configs: list[FeatureConfig] = CONFIGS, boosted_too: bool = True) -> list[dict]:
    out = []
    for train_set, target in transfer_combinations(tuple(data)):
        out += [{"dataset": target, "train_set": train_set, "config": c.name} for c in configs]
        if boosted_too:
            out.append({"dataset": target, "train_set": train_set, "method": "boosted_catalogue", "config": "names"})
    return out


def transfer_flags(runs: DataFrame) -> DataFrame:
    """runs with whether the large dataset is among the training sets, or the target."""
    return runs.withColumns({"has_goods_train": F.array_contains(F.split("train_set", r"\+"), "goods"), "goods_is_target": F.col("dataset") == "goods"})


def network_grid(data: dict[str, Dataset], fraction: float = 0.4, runs: int = 3, layers: tuple[str, ...] = ("64-32", "128-64", "256-128")) -> list[dict]:
    """The sensitivity to layer sizes."""
    return [g | {"hidden": h} for g in single_domain_grid(data, (fraction,), runs, [FeatureConfig()], False) for h in layers]


def flat_baselines(spark: SparkSession, sf_dir: str, datasets: tuple[str, ...] = DATASETS, lex: str = "blended") -> DataFrame:
    """Measures of the unsupervised methods on all pairs: lines that no training moves."""
    words, real = lexicon(spark, sf_dir, lex), truth(align_table(spark, list(datasets)))
    inst = reduce(DataFrame.unionByName, [instances(spark, sf_dir, cls) for cls in datasets])
    props = checkpointed(inst.select(*PROPERTY_KEY).distinct())
    # All methods look at one class at a time, so datasets go together.
    found = {
        "lexical_onto": lexical.match(props), "concept_lattice": lattice.match(props), "semantic_graph": semgraph.match(props, words),
        "lsh_instances": lsh.match(inst), "cosine": cosine.match(name_embedding(props, words)),
    }
    rows = [prf(sim, real).select(F.col("cls").alias("dataset"), F.lit(method).alias("method"), "tp", "fp", "fn", "precision", "recall", "f1") for method, sim in found.items()]
    return reduce(DataFrame.unionByName, rows)


def semgraph_grid(spark: SparkSession, sf_dir: str, datasets: tuple[str, ...] = DATASETS) -> DataFrame:
    """All 64 threshold combinations, by their mean F1 over the datasets."""
    words, rows = lexicon(spark, sf_dir), None
    for cls in datasets:
        props = instances(spark, sf_dir, cls).select(*PROPERTY_KEY).distinct()
        part = labelled(semgraph.scores(props, words), align_table(spark, [cls])).select(F.lit(cls).alias("dataset"), "syn", "coherence", "label")
        rows = part if rows is None else rows.unionByName(part)
    counts = with_scores(semgraph.sweep(rows, spark))
    return counts.groupBy("syn_t", "neg_t", "pos_t").agg(F.avg("f1").alias("mean_f1"))


def lsh_grid(spark: SparkSession, sf_dir: str, datasets: tuple[str, ...] = DATASETS, bands: list[int] = lsh.BANDS, variants: tuple[str, ...] = ("minhash", "projection"), hashes: dict[str, int] = lsh.HASHES) -> DataFrame:
    """Both variants and all band sizes, by their mean F1 over the datasets. The signatures of all datasets are made once and
    kept (a row for each property), so the driver never plans more than one variant's join at a time."""
    words = lsh.occurrences(reduce(DataFrame.unionByName, [instances(spark, sf_dir, cls) for cls in datasets]))
    real = checkpointed(truth(align_table(spark, list(datasets))))
    n_true = real.groupBy("cls").agg(F.count("*").alias("n_true"))
    sizes = {v: hashes[v] for v in variants}
    states = checkpointed(lsh.signatures(words, sizes))
    out = None
    for variant in variants:
        pairs = lsh.banded(lsh.signature_of(states, variant, sizes), bands, sizes[variant])
        hit = pairs.join(real.withColumn("_t", F.lit(1)), PAIR_KEY, "left").groupBy("cls", "band").agg(F.count("_t").alias("tp"), F.count("*").alias("n"))
        rows = hit.join(n_true, "cls").select(F.lit(variant).alias("variant"), "band", "tp", (F.col("n") - F.col("tp")).alias("fp"), (F.col("n_true") - F.col("tp")).alias("fn"))
        out = rows if out is None else out.unionByName(rows)
    # A band size at which a dataset has no pair has an F1 of 0 there.
    return with_scores(out).groupBy("variant", "band").agg((F.sum("f1") / len(datasets)).alias("mean_f1"))
