"""The registered workloads take their whole grids and all domains."""

from collections import Counter
from types import SimpleNamespace

import pytest

from propalign import queries
from propalign.model import CONFIGS
from propalign.plans import experiments as ex
from propalign.sources.domains import DOMAINS, source_name


@pytest.fixture
def asked(monkeypatch):
    """What a query gives to run_grid, without training."""
    got = []

    def prepare(spark, sf, datasets=ex.DATASETS, lex="blended", anonymous=False):
        return {c: SimpleNamespace(source=[source_name(DOMAINS[c], i) for i in range(DOMAINS[c].sources)]) for c in datasets}

    monkeypatch.setattr(ex, "prepare", prepare)
    monkeypatch.setattr(ex, "run_grid", lambda spark, data, grid, name, **k: got.extend(grid))
    monkeypatch.setattr(ex, "transfer_flags", lambda runs: runs)
    monkeypatch.setattr(queries.metrics, "summarise", lambda runs, by: runs)
    return got


@pytest.mark.parametrize("name, kinds", [("sd_results", len(CONFIGS) + 1), ("sd_summary", 3), ("anonymous_names", len(CONFIGS) + 1)])
def test_single_domain_grids_are_whole(asked, name, kinds):
    queries.QUERIES[name](None, "")
    cells = Counter((g["dataset"], g["fraction"], g["run"]) for g in asked)
    assert set(cells) == {(c, f, r) for c in DOMAINS for f in (0.2, 0.4, 0.6, 0.8) for r in range(25)} and set(cells.values()) == {kinds}
    assert len({(g["dataset"], g["fraction"], g["sources"]) for g in asked}) == 400


def test_transfer_grid_is_whole(asked):
    queries.QUERIES["tl_results"](None, "")
    cells = Counter((g["train_set"], g["dataset"]) for g in asked)
    assert len(cells) == 28 and set(cells.values()) == {len(CONFIGS) + 1}


def test_network_grid_has_every_dataset(asked):
    queries.QUERIES["network_sensitivity"](None, "")
    assert Counter(g["dataset"] for g in asked) == {c: 9 for c in DOMAINS}


def test_splits_follow_the_tables(spark, tmp_path):
    """Splits, combinations and true pairs are those of the sources, datasets and properties that occur."""
    import shutil

    import duckdb

    from __spark_entry__ import oracle_sql
    from propalign.queries import QUERIES

    src = "/root/testdata/sf0.001"
    for f in __import__("pathlib").Path(src).glob("*.parquet"):
        if f.stem not in ("events", "supplier"):
            shutil.copy(f, tmp_path / f.name)
    for t in ("events", "supplier"):
        duckdb.sql(f"COPY (SELECT * FROM '{src}/{t}.parquet' LIMIT 0) TO '{tmp_path}/{t}.parquet'")
    for folder in (src, str(tmp_path)):
        con = duckdb.connect()
        for f in __import__("pathlib").Path(folder).glob("*.parquet"):
            con.execute(f"CREATE VIEW {f.stem} AS SELECT * FROM '{f}'")
        for name in ("sd_splits", "tl_combinations", "truth_pairs"):
            got = sorted(tuple(r) for r in QUERIES[name](spark, folder).collect())
            assert got == sorted(con.execute(oracle_sql()[name]).fetchall()), (folder, name)
            assert len(got) > 0
    assert "event" not in {r["dataset"] for r in QUERIES["sd_splits"](spark, str(tmp_path)).collect()}


def _plain_dataset(n=14, d=3):
    import numpy as np
    import pandas as pd

    rng = np.random.default_rng(1)
    names = ["price", "Price tag", "list-cost", "", "brand", "maker", "price"]
    rows = pd.DataFrame({"source": [f"s{i % 4}" for i in range(n)], "prop": [names[i % len(names)] + str(i // 7) * (i % 2) for i in range(n)], "ref_prop": [["a", "b", None][i % 3] for i in range(n)]})
    return ex.Dataset(rows.assign(vec=list(rng.normal(size=(n, 29 + 2 * d)))))


def test_trainings_share_similarities_of_names(spark, monkeypatch):
    """Columns of each configuration are those of the whole pair features, and no training makes a similarity of its own."""
    import numpy as np

    from propalign.baselines import boosted
    from propalign.operators.pairs import pair_matrix

    data = _plain_dataset()
    at = np.arange(len(data.a))[::-1]
    a, b = data.a[at], data.b[at]
    sides = [data.prop[i] for i in a], [data.prop[i] for i in b]
    whole = pair_matrix(data.vec[a].astype(float), data.vec[b].astype(float), *sides)
    names = boosted.catalogue_matrix(*sides)
    for shared in (False, True):
        if shared:
            ex.share_names(spark, {"x": data, "none": ex.Dataset(__import__("pandas").DataFrame({c: [] for c in ("source", "prop", "ref_prop", "vec")}))})
            monkeypatch.setattr(ex, "all_eight", None)
            monkeypatch.setattr(boosted, "catalogue", None)
        assert np.array_equal(data.catalogue(at), names)
        for c in CONFIGS:
            assert np.array_equal(data.features(at, c), np.concatenate([whole[:, x:y] for x, y in c.slices(3)], 1))


def test_small_tables_go_to_all_cores(spark):
    """A table in one small file is still worked on by as many tasks as asked for, with the same rows."""
    from propalign.sources.domains import instances

    sf = "/root/testdata/sf0.001"
    for cls in ("order", "event", "party"):
        spread, plain = instances(spark, sf, cls, 3), instances(spark, sf, cls)
        assert spread.rdd.getNumPartitions() >= 3
        assert sorted(map(tuple, spread.collect())) == sorted(map(tuple, plain.collect()))


def test_training_takes_plain_steps():
    """The network is that of the plain form of the optimiser, which updates each array by itself."""
    import numpy as np

    from propalign.operators.network import NetworkSpec, fit

    rng = np.random.default_rng(2)
    x = rng.normal(size=(75, 6))
    y = (x[:, 0] + x[:, 1] > 0).astype(int)
    spec = NetworkSpec(hidden=(5, 4), schedule=((3, 1e-2), (2, 1e-3)))
    net = fit(x, y, spec)
    rng, sizes = np.random.default_rng(spec.seed), [6, 5, 4, 2]
    params = [(rng.normal(size=s) * np.sqrt(2 / s[0])).astype(np.float32) for s in zip(sizes, sizes[1:], strict=False)] + [np.zeros(s, dtype=np.float32) for s in sizes[1:]]
    data = ((x - x.mean(0)) / x.std(0)).astype(np.float32)
    m, v, t = [0 * p for p in params], [0 * p for p in params], 0
    for epochs, rate in spec.schedule:
        for _ in range(epochs):
            order = rng.permutation(len(data))
            for at in range(0, len(data), spec.batch):
                rows = order[at : at + spec.batch]
                h = [data[rows]]
                for i in range(3):
                    z = h[-1] @ params[i] + params[3 + i]
                    h.append(np.maximum(z, 0) if i < 2 else z)
                z = np.exp(z - z.max(1, keepdims=True))
                delta = z / z.sum(1, keepdims=True)
                delta[np.arange(len(rows)), y[rows]] -= 1
                delta /= len(rows)
                grads = [None] * 6
                for i in (2, 1, 0):
                    grads[i], grads[3 + i] = h[i].T @ delta, delta.sum(0)
                    delta = (delta @ params[i].T) * (h[i] > 0)
                t += 1
                for i, g in enumerate(grads):
                    m[i] = 0.9 * m[i] + 0.1 * g
                    v[i] = 0.999 * v[i] + 0.001 * g * g
                    params[i] = params[i] - rate / (1 - 0.9**t) * m[i] / (np.sqrt(v[i] / (1 - 0.999**t)) + 1e-8)
    for got, want in zip([*net.weights, *net.biases], params, strict=True):
        assert got.dtype == np.float32 and np.allclose(got, want, rtol=1e-4, atol=1e-6)


def test_lexicon_control_lists_properties_once(spark, monkeypatch):
    """Every kind has its whole grid and the vectors of names that a whole profile has; properties come from one pass over the tables;
    what fails beside the trainings is raised."""
    import numpy as np
    from pyspark.sql import functions as F

    sf, got, passes, plain = "/root/testdata/sf0.001", {}, [], ex.instances
    whole = ex.prepare(spark, sf)
    monkeypatch.setattr(ex, "instances", lambda spark, sf, cls, tasks=0: passes.append((cls, tasks)) or plain(spark, sf, cls, tasks))
    monkeypatch.setattr(ex, "run_grid", lambda spark, data, grid, name: got.update({name: (data, grid)}) or spark.range(1).select(F.lit(name).alias("experiment")))
    rows = queries.QUERIES["lexicon_control"](spark, sf).collect()
    assert [r["experiment"] for r in rows] == ["lexicon_blended", "lexicon_hashed", "lexicon_trained"]
    # Once for properties, and once for what trained vectors learn from.
    assert Counter(c for c, tasks in passes if tasks) == Counter(list(DOMAINS)) and len(passes) == 2 * len(DOMAINS)
    for data, grid in got.values():
        assert Counter((g["dataset"], g["fraction"]) for g in grid) == {(c, f): 25 for c in DOMAINS for f in (0.2, 0.4, 0.6, 0.8)}
        assert {g["config"] for g in grid} == {"names/embedding"}
        for c in DOMAINS:
            assert (data[c].prop, data[c].ref, list(data[c].source)) == (whole[c].prop, whole[c].ref, list(whole[c].source))
    for c in DOMAINS:
        assert np.allclose(got["lexicon_blended"][0][c].vec[:, -64:], whole[c].vec[:, -64:], atol=1e-6)
    monkeypatch.setattr("propalign.functions.lexicon.trained", lambda texts: 1 / 0)
    with pytest.raises(ZeroDivisionError):
        ex.lexicon_runs(spark, sf, ("trained",))
