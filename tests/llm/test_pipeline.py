"""The pipeline's stages against plain versions, one after the other, and on awkward rows."""

import re
from collections import Counter

import numpy as np
import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")

from propalign.llm.nnpu import text_features, train  # noqa: E402
from tests.llm.test_brute import brute_components, brute_spans, check_packing  # noqa: E402

SF = "/root/testdata/sf0.001"


def rows_of(df):
    return [tuple(r) for r in df.collect()]


def test_stages_against_plain_versions(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    stages, whole, names = dict(corpus_pipeline.STAGES), rows_of(docs), docs.columns
    assert list(stages) == ["quality_classifier", "near_dedup", "personal_data", "mixing", "packing"]
    t = names.index("text")

    good = stages["quality_classifier"](spark, docs, SF).cache()
    m = train(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    z = [float(np.clip((text_features(r[t]).astype(float) - m["mean"]) / m["scale"], -8, 8) @ m["weights"][:-1] + m["weights"][-1]) for r in whole]
    assert sorted(rows_of(good), key=repr) == sorted([r for r, v in zip(whole, z, strict=True) if v >= 0], key=repr)
    assert 0 < len(whole) - good.count() < len(whole) / 2

    left = sorted(rows_of(good))
    part = brute_components([r[t] for r in left])
    unique = stages["near_dedup"](spark, good, SF).cache()
    assert sorted(rows_of(unique)) == [r for i, r in enumerate(left) if part[i][1] == i] and unique.count() < len(left)

    clean = stages["personal_data"](spark, unique, SF).cache()
    before, after = {r[0]: r[t] for r in rows_of(unique)}, {r["doc_id"]: r for r in clean.collect()}
    assert set(before) == set(after) and clean.columns == names
    for i, x in before.items():
        text, spans = after[i]["text"], brute_spans(x)
        assert after[i]["n_chars"] == len(text)
        if "=" in x or ":" in x:
            assert not brute_spans(text)
            continue
        parts, at = [], 0
        for kind, s, e in sorted(spans, key=lambda v: (v[1], -v[2])):
            if s >= at:
                parts += [x[at:s], f"<{kind.upper()}>"]
            at = max(at, e)
        assert text == "".join(parts) + x[at:], i

    mixed = stages["mixing"](spark, clean, SF).cache()
    taken, known = Counter(rows_of(mixed)), set(rows_of(clean))
    assert set(taken) <= known and max(taken.values()) <= 3 and mixed.columns == names
    size = lambda r: len(re.findall(r"[^\x20\x09-\x0D]+", r[t]))
    s = names.index("source")
    total = sum(map(size, known))
    assert abs(sum(size(r) * k for r, k in taken.items()) / total - 1) < 0.2
    assert len({r[s] for r in taken}) > 0.8 * len({r[s] for r in known})

    packed = stages["packing"](spark, mixed, SF).collect()
    check_packing(packed, 1024)
    assert Counter(r["doc_id"] for r in packed if r["piece"] == 0) == Counter({i: k for i, k in Counter(r[0] for r in taken.elements()).items()})


def test_stages_on_awkward_rows(spark, tmp_path):
    """Null and empty values everywhere, repeated rows, long texts, columns called like the operators' own, and no rows."""
    text = "plain words of some length " * 3
    rows = [(None, None, None, None, None), (1, None, "en", "a", 0), (1, "", None, None, None), (2, text, "en", "a", 5), (2, text, "en", "a", 5), (3, text + "mail x@y.org", None, "b", 1), (None, text, "en", "b", 2), (4, "w " * 70_000, "en", "b", 3)]
    more = "score double, row int, base string, spans int, kept boolean, pipeline_score int, uid int, mix_copies int, _band int"
    docs = spark.createDataFrame([(*r, 0.1, 1, "b", 2, True, 3, 4, 5, 6) for r in rows], f"doc_id long, text string, lang string, source string, n_chars long, {more}")
    spark.createDataFrame([(2, 1), (9, 0), (None, 1), (3, None)], "doc_id long, quality int").write.parquet(str(tmp_path / "labels.parquet"))
    for d in (docs, docs.limit(0)):
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, d, str(tmp_path)).cache()
            assert name == "packing" or out.columns == docs.columns, name
            assert out.count() == 0 if d is not docs else out.count() > 0
    emails = {r["doc_id"]: r["text"] for r in dict(corpus_pipeline.STAGES)["personal_data"](spark, docs, str(tmp_path)).collect()}
    assert emails[3] == text + "mail <EMAIL>" and emails[4] == "w " * 70_000
    one = Counter(r["doc_id"] for r in dict(corpus_pipeline.STAGES)["near_dedup"](spark, docs, str(tmp_path)).collect())
    assert one == {None: 1, 1: 2, 2: 1, 3: 1, 4: 1} or one == {None: 1, 1: 2, 2: 1, 4: 1}


def test_workers_get_few_rows_and_the_session_keeps_its_setting(spark):
    """Texts make rows large, so stages hand workers few of them at a time, and each text once."""
    import pyarrow as pa

    from propalign.llm import nnpu, tables

    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    rows_of = lambda it: (pa.RecordBatch.from_pydict({"id": [b.num_rows]}) for b in it)
    sizes = spark.range(0, 5000, 1, 1).mapInArrow(rows_of, "id long")
    assert max(r["id"] for r in tables.materialise(sizes).collect()) <= tables.BATCH_ROWS and spark.conf.get(name) == before
    docs = spark.createDataFrame([(1, "a b"), (2, None), (3, "")], "doc_id long, Text string")
    out = nnpu.score(docs, {"prior": 0.25, "weights": None}, text="text")
    assert {tuple(r) for r in out.collect()} == {(1, "a b", 0.25), (2, None, 0.25), (3, "", 0.25)}
    taken = nnpu.score(docs, {"prior": 0.25, "weights": None}, text="text", name="text")
    assert {tuple(r) for r in taken.collect()} == {(1, 0.25), (2, 0.25), (3, 0.25)}
