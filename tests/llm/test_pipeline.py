"""The pipeline, stage by stage, against brute force on its own inputs."""

import re

import pytest

import corpus_pipeline
from motifloom.llm import toxicity
from motifloom.llm.common import table
from test_operators import brute_near, lower

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("stages"))
    docs = table(spark, SF, "documents")
    out = [docs]
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, SF).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        out.append(docs)
    return out


def ids(df):
    return sorted(r["doc_id"] for r in df.select("doc_id").collect())


def test_stages_keep_the_columns(stages):
    assert [name for name, _ in corpus_pipeline.STAGES] == ["toxicity", "exact_dedup", "near_dedup", "decontaminate", "mixing"]
    for df in stages[1:-1]:
        assert df.columns == list(corpus_pipeline.COLUMNS)


def test_toxicity_stage(spark, stages):
    docs = stages[0]
    scores = toxicity.score(docs, toxicity.train(docs, table(spark, SF, "labels")))
    assert ids(stages[1]) == ids(scores.where("predicted = 0"))


def test_exact_stage(stages):
    first = {}
    for r in sorted(stages[1].collect(), key=lambda r: r["doc_id"]):
        first.setdefault(lower(r["text"] or ""), r["doc_id"])
    assert ids(stages[2]) == sorted(first.values())


def test_near_stage(stages):
    texts = {r["doc_id"]: r["text"] for r in stages[2].collect()}
    assert ids(stages[3]) == sorted(i for i, (_, c) in brute_near(texts).items() if i == c)


def test_decontaminate_stage(spark, stages):
    items = [re.findall(r"[a-z0-9\u0080-\U0010ffff]+", lower(r["text"])) for r in table(spark, SF, "benchmark").collect()]
    kept = set(ids(stages[4]))
    for r in stages[3].collect():
        words = " ".join(re.findall(r"[a-z0-9\u0080-\U0010ffff]+", lower(r["text"] or "")))
        if any(" ".join(i) in words for i in items):
            assert r["doc_id"] not in kept
        elif not any(" ".join(i[k : k + 5]) in words for i in items for k in range(len(i) - 4)):
            assert r["doc_id"] in kept


def test_mixing_stage(stages):
    assert ids(stages[5]) == ids(stages[4])


def test_run_gives_the_last_stage(spark, stages):
    got = corpus_pipeline.run(spark, SF)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, stages[5].collect()))


def odd_documents(spark, rows):
    kind = "doc_id long, text string, lang string, source string, n_chars long, body string, row int, toxic int"
    return spark.createDataFrame([(i, t, "en", s, len(t or ""), "x", 1, 7) for i, t, s in rows], kind)


def test_stages_on_nulls_repeated_rows_and_clashing_columns(spark):
    text = " ".join(f"word{i}" for i in range(40))
    rows = [(1, None, None), (2, "", "a"), (3, text, "a"), (3, text, "a"), (4, text.upper(), None), (None, "alone here", "b"), (5, text + " more", "b"), (6, "long " * 20_000, "c"), (7, "same id", "c"), (7, "other text", "c")]
    docs = odd_documents(spark, rows)
    clean, exact, near, decontaminated, mixed = (stage for _, stage in corpus_pipeline.STAGES)
    kept = clean(spark, docs, SF)
    assert kept.columns == list(corpus_pipeline.COLUMNS) and kept.count() == len(rows)
    # equal texts: the smallest id stays; rows of one id and one text are the same document and both stay
    once = sorted(((r["doc_id"] is None, r["doc_id"], r["text"]) for r in exact(spark, docs, SF).collect()), key=str)
    assert [r[1] for r in once if r[1] is not None] == [1, 3, 3, 5, 6, 7, 7] and (True, None, "alone here") in once
    groups = near(spark, docs, SF)
    assert sorted(r["doc_id"] for r in groups.where("doc_id is not null").collect()) == [1, 2, 3, 3, 6, 7, 7]
    assert decontaminated(spark, docs, SF).count() == len(rows)
    out = mixed(spark, docs, SF).collect()
    assert len(out) == len(rows) and all(0 <= r["taken"] <= 3 * r["size"] for r in out)


def test_stages_on_an_empty_table(spark):
    docs = odd_documents(spark, []).limit(0)
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, SF).count() == 0, name
