import pytest

import corpus_pipeline as P
from rankscan.llm import common, decontaminate, ngramjoin
from tests.conftest import TINY


def test_stages_take_effect(spark):
    docs = spark.read.parquet(f"{TINY}/documents.parquet")
    for name, stage in P.STAGES[:-1]:
        before, docs = docs, stage(spark, docs, TINY).cache()
        assert docs.columns == before.columns, name
        if name == "ngram_jaccard_join":
            out = ngramjoin.jaccard_join(docs)
            assert out.select("leader").distinct().count() == docs.count() == before.join(ngramjoin.jaccard_join(before).select("component_id").distinct(), before["doc_id"] == before["doc_id"]).select("component_id").distinct().count()
        if name == "decontamination":
            assert decontaminate.contamination(docs, spark.read.parquet(f"{TINY}/benchmark.parquet")).where("contaminated").count() == 0
    tokens = P.STAGES[-1][1](spark, docs, TINY)
    assert tokens.count() == docs.count()


def test_repeated_rows_leave_one(spark):
    docs = spark.createDataFrame([(1, "a b c d"), (1, "a b c d"), (2, "a b c d"), (3, "e f g"), (4, None), (4, None)], "doc_id bigint, text string")
    kept = P.ngram_stage(spark, docs, TINY)
    assert sorted(r[0] for r in kept.collect()) == [1, 3, 4]


def test_near_copies_with_two_percent_of_words_changed_leave_one(spark):
    words = [f"w{i}" for i in range(500)]
    near = ["other" if i % 50 == 25 else w for i, w in enumerate(words)]  # 10 of 500: above 0.8 on five words, below 0.9 on three
    far = ["other" if i % 20 == 10 else w for i, w in enumerate(words)]
    docs = spark.createDataFrame([(1, " ".join(words)), (2, " ".join(near)), (3, " ".join(far))], "doc_id bigint, text string")
    assert sorted(r[0] for r in P.ngram_stage(spark, docs, TINY).collect()) == [1, 3]


@pytest.mark.parametrize("n", [0])
def test_empty_documents(spark, n):
    docs = spark.read.parquet(f"{TINY}/documents.parquet").limit(n)
    for _, stage in P.STAGES:
        assert stage(spark, docs, TINY).count() == 0


def test_executors_give_memory_back_before_token_files(spark):
    def collected():
        beans = spark._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans()
        return sum(b.getCollectionCount() for b in beans if "Old" in b.getName() or "MarkSweep" in b.getName())

    docs = spark.createDataFrame([(1, "a b c d"), (2, None)], "doc_id bigint, text string")
    before = collected()
    assert P.token_stage(spark, docs, TINY).count() == 2
    assert collected() > before


def test_near_duplicate_stage_runs_the_join_once(spark, monkeypatch):
    """What the stage reads three times is materialised: no shuffle of the join is left in its plan."""
    plans, held = [], ngramjoin.one_of_each

    def one_of_each(joined):
        plans.append(joined._jdf.queryExecution().executedPlan().toString())
        return held(joined)

    monkeypatch.setattr(ngramjoin, "one_of_each", one_of_each)
    docs = spark.createDataFrame([(1, "a b c d"), (2, "a b c d"), (3, "e f g")], "doc_id bigint, text string")
    assert sorted(r[0] for r in P.ngram_stage(spark, docs, TINY).collect()) == [1, 3]
    assert len(plans) == 1 and "Exchange" not in plans[0]


def test_the_driver_gives_freed_native_memory_back_in_each_stage(spark, monkeypatch):
    given, trim = [], common.trim_driver
    monkeypatch.setattr(common, "trim_driver", lambda session: given.append(trim(session)))
    docs = spark.createDataFrame([(1, "a b c d", "x"), (2, None, "y")], "doc_id bigint, text string, source string")
    for name, stage in P.STAGES:
        given.clear()
        stage(spark, docs, TINY).count()
        assert given and all(given), name
