import random
from collections import Counter
from fractions import Fraction

import pytest

from rankscan.llm import ngramjoin as J
from rankscan.llm.components import components


def shingles(text, k):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    w = [x for x in __import__("re").split("[\x20\x09-\x0d]+", low) if x]
    return frozenset(tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))) if w else frozenset()


def brute(docs, k=3, t=Fraction(9, 10)):
    sets = [shingles(t, k) for _, t, *_ in docs]
    root = list(range(len(docs)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    links = Counter()
    for i in range(len(docs)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if sets[i] and sets[j] and both >= t * (len(sets[i]) + len(sets[j]) - both):
                links[i] += 1
                links[j] += 1
                root[find(i)] = find(j)
    out = []
    for i, (d, *_) in enumerate(docs):
        ids = [docs[j][0] for j in range(len(docs)) if find(j) == find(i) and docs[j][0] is not None]
        out.append((d, len(sets[i]), min(ids) if ids else None, links[i]))
    return sorted(out, key=repr)


def corpus(seed, n=60):
    r = random.Random(seed)
    vocab = [f"w{i}" for i in range(300)]
    base = [[r.choice(vocab) for _ in range(r.choice([40, 80, 200]))] for _ in range(6)]
    docs = []
    for i in range(n):
        w = list(r.choice(base)) if r.random() < 0.8 else [r.choice(vocab) for _ in range(r.randint(1, 60))]
        for _ in range(r.choice([0, 0, 1, 1, 2, 3])):
            w[r.randrange(len(w))] = r.choice(vocab)
        docs.append((i, r.choice([" ", "\n", "\t "]).join(w)))
    return docs


def rows(spark, docs, k=3, t=Fraction(9, 10)):
    d = spark.createDataFrame([(a, b, "x", 1) for a, b in docs], "doc_id bigint, text string, token string, n int")
    return sorted(map(tuple, J.jaccard_join(d, k=k, threshold=t).select("doc_id", "n_shingles", "component_id", "n_links").collect()), key=repr)


EDGES = [(100, None), (101, ""), (102, " \n "), (103, "one"), (104, "ONE"), (105, "one two"), (106, "one two three"), (107, "Él a b"), (108, "él a b"), (5, "one"), (5, "one"), (None, "one two"), (None, None), (110, "a\xa0b c d e"), (111, "big " * 50_000)]


@pytest.mark.parametrize("seed", [1, 2])
def test_matches_brute_force(spark, seed):
    docs = corpus(seed) + (EDGES if seed == 1 else [])
    assert rows(spark, docs) == brute(docs)


def test_five_words_and_four_fifths_are_the_rule_unless_told_otherwise(spark):
    docs = corpus(4)
    d = spark.createDataFrame(docs, "doc_id bigint, text string")
    got = sorted(map(tuple, J.jaccard_join(d).select("doc_id", "n_shingles", "component_id", "n_links").collect()), key=repr)
    assert got == brute(docs, 5, Fraction(4, 5)) != brute(docs)


def test_small_blocks_lose_no_link(spark, monkeypatch):
    monkeypatch.setattr(J, "BLOCK_ROWS", 5)
    docs = corpus(3, 80)
    assert rows(spark, docs) == brute(docs)


def test_empty(spark):
    assert rows(spark, []) == []


def test_components_of_a_long_chain(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 101), (7, 7), (None, 3)]
    got = dict(map(tuple, components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()))
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100}


def test_one_of_each_names_all_but_the_least(spark):
    docs = [(1, "a b c d"), (2, "a b c d"), (3, "x y z"), (4, None)]
    gone = J.one_of_each(J.jaccard_join(spark.createDataFrame(docs, "doc_id bigint, text string")))
    assert [r[0] for r in gone.collect()] == [2]


def test_dead_shuffles_are_dropped_before_the_sets_are_shuffled(spark, monkeypatch):
    asked = []
    monkeypatch.setattr(J, "tidy", lambda s: asked.append(s))
    df = spark.createDataFrame([(1, "a b c d e f"), (2, "a b c d e f"), (3, "x y z")], "doc_id bigint, text string")
    assert J.jaccard_join(df).count() == 3 and len(asked) == 2
