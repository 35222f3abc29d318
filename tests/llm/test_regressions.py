"""Faults once found: one test each."""

import itertools
import math
import random
from fractions import Fraction

import numpy as np
from pyspark.sql import functions as F

import corpus_pipeline as P
from rankscan.llm import bitslice, mixture, toxicity, transcripts, warcaudit
from rankscan.llm.common import held_out
from tests.conftest import SMALL, TINY


# ---- op3 --------------------------------------------------------------------------------------------------------------
def test_large_components_and_scores_beyond_a_long(spark):
    rows = [(0, [1e7, -3e8]), (1, [2e9, 1.0]), (2, [0.5, -1e9]), (50, [1e13, 1e13]), (3, [-1e13, -1e13]), (4, [1e30, 0.0])]
    got = {}
    for r in bitslice.top_k(spark.createDataFrame(rows, "vec_id bigint, embedding array<double>"), width=2).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    good = {i: [math.floor(256 * x) for x in v] for i, v in rows if i != 4}
    for q in (0, 50):
        held = {i: max(-(1 << 63), min((1 << 63) - 1, sum(a * b for a, b in zip(good[q], v)))) for i, v in good.items() if i != q}
        assert sorted(got[q]) == [(k + 1, i, s) for k, (i, s) in enumerate(sorted(held.items(), key=lambda x: (-x[1], x[0])))]


def test_query_rows_of_one_id_are_answered_each(spark):
    rows = [(50, [1.0, 0.0]), (50, [0.0, 1.0]), (1, [1.0, 0.1]), (2, [0.2, 1.0]), (3, [0.5, 0.5])]
    got = bitslice.top_k(spark.createDataFrame(rows, "vec_id bigint, embedding array<double>"), k=2).collect()
    lists = sorted((r["rank"], r["vec_id"]) for r in got)
    assert lists == [(1, 1), (1, 2), (2, 3), (2, 3)]


# ---- op2 --------------------------------------------------------------------------------------------------------------
def test_rows_equal_but_for_the_source_keep_their_own(spark):
    rows = [(1, "a b c", "x"), (1, "a b c", "y"), (2, "long " * 30_000, "x"), (3, "d e", "y"), (3, "d e", "y")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, source string")
    mixed = mixture.mix(df).cache()
    docs = mixture.mixed_documents(df, mixed)
    count = lambda d: sorted(map(tuple, d.groupBy("doc_id", "source").count().collect()))
    assert docs.columns == df.columns and count(docs) == count(mixed)


def test_mixture_uses_no_python(spark):
    df = spark.read.parquet(f"{TINY}/documents.parquet")
    plan = mixture.mix(df)._jdf.queryExecution().toString()
    assert "Python" not in plan and "InArrow" not in plan and "InPandas" not in plan


# ---- op8 --------------------------------------------------------------------------------------------------------------
def _decoded(spark, rows, kind="conv_id bigint, turn bigint, role string, text string", chunk=256):
    lines = transcripts.transcript_lines(spark.createDataFrame(rows, kind))
    model = transcripts.train(transcripts.transcript_lines(spark.read.parquet(f"{SMALL}/conversations.parquet")))
    return transcripts.decode(lines, model, chunk_turns=chunk)


def test_lines_of_equal_turns_do_not_interleave(spark):
    rows = [(1, 0, "user", "a1\na2\na3"), (1, 0, "user", "b1\nb2\nb3")]
    text = "\n".join(r["content"] for r in transcripts.render(_decoded(spark, rows)).orderBy("seq").collect())
    assert text.replace("\n", " ") in ("a1 a2 a3 b1 b2 b3", "b1 b2 b3 a1 a2 a3")


def test_ids_and_turns_of_other_types(spark):
    rows = [("x", "0", "user", "hi"), ("x", "1", "assistant", "yo"), (None, None, "user", "z")]
    out = transcripts.render(_decoded(spark, rows, "conv_id string, turn string, role string, text string")).collect()
    assert {r["conv_id"] for r in out} == {"x", None}
    dated = spark.createDataFrame(rows[:2], "conv_id string, turn string, role string, text string").select(F.lit("2024-01-01").cast("date").alias("conv_id"), F.col("turn").cast("smallint").alias("turn"), "role", "text")
    lines = transcripts.transcript_lines(dated)
    assert transcripts.render(transcripts.decode(lines, transcripts.train(lines))).count() == 2


def test_chunks_leave_no_seams(spark):
    rows = [(1, t, ["user", "assistant"][t % 2], f"turn {t}\ngoes on\nand on") for t in range(40)] + [(2, t, "user", "x") for t in range(3)]
    outs = [sorted(map(tuple, transcripts.render(_decoded(spark, rows, chunk=c)).collect())) for c in (1, 3, 256)]
    assert outs[0] == outs[1] == outs[2]


def test_viterbi_equals_all_paths():
    rng = np.random.default_rng(1)
    with np.errstate(divide="ignore"):
        for _ in range(20):
            first, step, emit = np.log(rng.random(6)), np.log(rng.random((6, 6))), np.log(rng.random((4, 6)))
            best = max(itertools.product(range(6), repeat=4), key=lambda p: first[p[0]] + sum(step[a, b] for a, b in zip(p, p[1:])) + sum(emit[i, s] for i, s in enumerate(p)))
            assert transcripts._viterbi(step, emit, first, None) == list(best)


def test_roles_of_conversations_not_learned_from(spark):
    lines = transcripts.transcript_lines(spark.read.parquet(f"{SMALL}/conversations.parquet"))
    out = transcripts.decode(lines, transcripts.train(lines.where(~held_out(F.col("conv_id"))))).where(held_out(F.col("conv_id")))
    right = out.agg(F.avg((F.floor(F.col("state") / 2) == F.floor(F.col("true_state") / 2)).cast("int"))).first()[0]
    assert right > 0.95


# ---- op9 --------------------------------------------------------------------------------------------------------------
def test_records_moved_to_other_files_are_seen(spark):
    rows = [(i, f"http://h/{i}", "b" * (i % 9)) for i in range(600)] + [(700, "u", "long body " * 50_000)]
    leaves = warcaudit.records(spark.createDataFrame(rows, "page_id bigint, url string, html string")).cache()
    moved = leaves.withColumn("file", F.col("file") + 16)
    assert warcaudit.audit(leaves, leaves).count() == 0
    assert warcaudit.audit(leaves, moved).count() == 2 * leaves.count()
    later = leaves.withColumn("offset", F.col("offset") + 7)
    roots = [warcaudit.tree(x).orderBy(F.desc("level")).first()["digest"] for x in (leaves, moved, later)]
    assert len(set(roots)) == 3


# ---- op5 --------------------------------------------------------------------------------------------------------------
def test_toxicity_of_rows_not_learned_from(spark):
    d, lab = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    out = toxicity.score(d, toxicity.train(d, lab)).join(lab, "doc_id").where(held_out(F.col("doc_id")))
    rate = {r[0]: r[1] for r in out.groupBy("toxic").agg(F.avg((F.col("score") >= 0.5).cast("int"))).collect()}
    assert rate[1] >= 0.8 and rate[0] <= 0.01


# ---- pipeline -----------------------------------------------------------------------------------------------------------
def test_near_duplicate_and_decontamination_stages_against_brute_force(spark):
    r = random.Random(3)
    vocab, item = [f"w{i}" for i in range(150)], [f"q{i}" for i in range(30)]
    docs = []
    for i in range(40):
        base = [r.choice(vocab) for _ in range(r.choice([3, 60, 120]))]
        docs.append((2 * i, " ".join(base)))
        if i % 3 == 0:
            base[r.randrange(len(base))] = "changed"
            docs.append((2 * i + 1, " ".join(base)))
    docs += [(200, " ".join(item + docs[0][1].split())), (201, None), (202, ""), (203, " ".join(vocab * 400)), (204, docs[3][1]), (204, docs[3][1])]
    df = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in docs], "doc_id bigint, text string, lang string, source string, n_chars bigint")

    def shingles(t):
        w = (t or "").split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    rows = sorted(set(docs), key=lambda x: x[0])
    sets, root = [shingles(t) for _, t in rows], list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, j in itertools.combinations(range(len(rows)), 2):
        both = len(sets[i] & sets[j])
        if both and both >= Fraction(4, 5) * (len(sets[i]) + len(sets[j]) - both):
            root[max(find(i), find(j))] = min(find(i), find(j))
    kept = [rows[i][0] for i in range(len(rows)) if find(i) == i]
    stage = P.ngram_stage(spark, df, TINY)
    assert sorted(x[0] for x in stage.collect()) == kept and stage.columns == df.columns

    bench = [x[0] for x in spark.read.parquet(f"{TINY}/benchmark.parquet").select("text").collect()]
    planted = spark.createDataFrame([(900, bench[0], "en", "s", 0), (901, "nothing of the kind " * 5, "en", "s", 0), (902, None, "en", None, 0)], df.schema)
    left = {x[0] for x in P.decontamination_stage(spark, planted, TINY).collect()}
    assert left == {901, 902}
