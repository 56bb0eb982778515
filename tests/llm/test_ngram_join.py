import random
import re

import numpy as np

from twoview.llm import ngram_join as J
from twoview.llm.graphs import components

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def shingles(text):
    low = re.sub("[A-Z]", lambda m: m[0].lower(), text or "")
    w = tuple(WORD.findall(low))
    return {w[i : i + 5] for i in range(len(w) - 4)} if len(w) >= 5 else {w} if w else set()


def brute(rows):
    sets = [(i, shingles(t)) for i, t in rows]
    comp = {i: i for i, _ in rows}

    def root(x):
        while comp[x] != x:
            x = comp[x]
        return x

    for k, (i, a) in enumerate(sets):
        for j, b in sets[:k]:
            both = len(a & b)
            if a and b and 100 * both >= 75 * (len(a) + len(b) - both):
                x, y = sorted((root(i), root(j)))
                comp[y] = x
    return sorted((i, len(s), root(i)) for i, s in sets)


def corpus(seed, n=260):
    rng = random.Random(seed)
    vocab = [f"w{k}" for k in range(400)]
    passage = [rng.choice(vocab) for _ in range(30)]
    made = []
    for i in range(n):
        kind = rng.random()
        if made and kind < 0.15:
            text = rng.choice(made)
        elif made and kind < 0.6:
            words = rng.choice(made).split()
            for _ in range(rng.randrange(1, 2 + len(words) // 20)):
                if words:
                    words[rng.randrange(len(words))] = rng.choice(vocab)
            text = " ".join(words)
        elif kind < 0.75:
            text = " ".join([rng.choice(vocab) for _ in range(rng.randrange(40))] + passage)
        else:
            text = " ".join(rng.choice(vocab) for _ in range(rng.randrange(80)))
        made.append(text)
    return list(enumerate(made))


def test_components_match_brute_force(spark):
    for seed in (1, 2):
        rows = corpus(seed)
        rows += [(1000, None), (1001, ""), (1002, "A b C"), (1003, "a B c"), (1004, "a b c d")]
        docs = spark.createDataFrame([(i, t, 0) for i, t in rows], "doc_id long, text string, cls int").repartition(5)
        got = sorted(map(tuple, J.ngram_components(docs, common=4).collect()))
        assert got == brute(rows)


def test_odd_tables(spark):
    docs = spark.createDataFrame([(None, "a b c d e f"), (1, "a b c d e f"), (1, "a b c d e f"), (2, None)], "doc_id long, text string")
    got = sorted(map(str, J.ngram_components(docs).collect()))
    assert len(got) == 4 and sum("component_id=1" in g for g in got) == 2 and sum("component_id=None" in g for g in got) == 1
    assert J.ngram_components(docs.limit(0)).count() == 0


def test_tree_matches_direct_overlap():
    rng = np.random.default_rng(0)
    for _ in range(40):
        base = np.sort(rng.choice(500, 60, replace=False)).astype(np.int64)
        sets = [np.unique(np.where(rng.random(60) < rng.random() * 0.4, rng.integers(0, 500, 60), base)) for _ in range(30)]
        link = lambda a, b: 7 * len(np.intersect1d(a, b)) >= 3 * (len(a) + len(b))
        want = {(i, j) for i, a in enumerate(sets) for j, b in enumerate(sets[:9]) if link(a, b)}
        got = {(t, int(j)) for t, who in J.PrefixTree(sets).linked(sets[:9], cells=rng.integers(1, 9999)) for j in who}
        assert got == want


def test_blocks_against_blocks(spark, monkeypatch):
    monkeypatch.setattr(J, "BLOCK", 150)
    rows = corpus(3)
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert sorted(map(tuple, J.ngram_components(docs, common=3).collect())) == brute(rows)


def test_long_chain_is_one_component(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(60)] + [(100, 101)], "a long, b long")
    spark.sparkContext.setCheckpointDir("/tmp/twoview-test")
    got = {r.node: r.comp for r in components(edges).collect()}
    assert set(got.values()) == {0, 100} and len(got) == 63


def test_a_document_links_by_any_of_its_texts(spark):
    x, y = " ".join(f"x{i}" for i in range(30)), " ".join(f"y{i}" for i in range(30))
    rows = [(5, x), (5, y), (7, x + " z"), (8, y + " z"), (9, "some other text that is alone here")]
    docs = spark.createDataFrame([(*r, 1, "s") for r in rows], "doc_id long, text string, n long, token string")
    assert {r.doc_id: r.component_id for r in J.ngram_components(docs).collect()} == {5: 5, 7: 5, 8: 5, 9: 9}


def test_very_long_texts(spark):
    long = " ".join(f"w{i % 7919}q{i}" for i in range(30_000))
    docs = spark.createDataFrame([(1, long), (2, long + " more"), (3, long[: len(long) // 2]), (4, "short text")], "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in J.ngram_components(docs).collect()}
    assert got[1] == (29_996, 1) and got[2] == (29_997, 1) and got[3][1] == 3 and got[4] == (1, 4)


def test_ids_that_go_by_either_way(spark):
    docs = spark.createDataFrame([(i, f"t{i}", i % 3) for i in range(500)], "doc_id long, text string, cls int").repartition(4)
    gone = docs.where("doc_id % 7 = 3").selectExpr("doc_id AS _gone")
    want = sorted(r.doc_id for r in docs.where("doc_id % 7 <> 3").collect())
    for most in (10**6, 0):
        out = J._without(docs, "doc_id", gone, most)
        assert out.columns == docs.columns and sorted(r.doc_id for r in out.collect()) == want
    assert J._without(docs, "doc_id", gone.limit(0), 0).count() == 500
