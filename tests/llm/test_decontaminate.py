import hashlib
import re

from rankscan.llm import decontaminate as D

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words(text):
    return WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))


def brute(docs, items):
    out = []
    wins = {(str(i) if i is not None else "null", tuple(w[s : s + 13])) for i, t in items if (w := words(t)) for s in range(max(1, len(w) - 12))}
    for i, t, *_ in docs:
        w = words(t)
        hit, names = set(), set()
        for name, win in wins:
            for s in range(len(w) - len(win) + 1):
                if tuple(w[s : s + len(win)]) == win:
                    hit.update(range(s, s + len(win)))
                    names.add(name)
        out.append((i, len(w), len(hit), len(names), hashlib.sha256(",".join(sorted(names)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    return sorted(out, key=repr)


def rows(spark, docs, items):
    d = spark.createDataFrame(docs, "doc_id bigint, text string, words string, pos int")
    b = spark.createDataFrame(items, "item_id bigint, text string")
    out = D.contamination(d, b).select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")
    return sorted(map(tuple, out.collect()), key=repr)


ITEM = "Alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi"
DOCS = [
    (1, f"some words before {ITEM.upper()} and after", "x", 0), (2, None, "x", 0), (3, "", None, None), (4, "...", "x", 1), (5, ITEM[6:], "x", 0),
    (6, "école Éole alpha beta", "x", 0), (6, "école Éole alpha beta", "x", 0), (7, "short item " * 400, "x", 0), (None, "a short, ITEM; here", "x", 0), (8, "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu", "x", 0),
    (9, " ".join(["filler"] * 600) + " " + ITEM, "x", 0),
]
ITEMS = [(1, ITEM), (2, "short item"), (3, None), (4, "!!"), (5, "Éole"), (5, "alpha beta"), (10, ITEM), (None, "filler filler")]


def test_matches_brute_force(spark):
    assert rows(spark, DOCS, ITEMS) == brute(DOCS, ITEMS)


def test_single_shingle_length_and_several_passes(spark, monkeypatch):
    monkeypatch.setattr(D, "PASS_ROWS", 2)
    assert rows(spark, DOCS, ITEMS) == brute(DOCS, ITEMS)
    assert rows(spark, DOCS, ITEMS[:1]) == brute(DOCS, ITEMS[:1])


def test_empty_tables(spark):
    assert rows(spark, [], ITEMS) == []
    assert rows(spark, DOCS, []) == brute(DOCS, [])


def test_native_plan(spark):
    d = spark.createDataFrame(DOCS, "doc_id bigint, text string, words string, pos int")
    plan = D.contamination(d, spark.createDataFrame(ITEMS, "item_id bigint, text string"))._jdf.queryExecution().toString()
    assert "BroadcastHashJoin" in plan and "Python" not in plan and "Cartesian" not in plan
