import numpy as np
import pyarrow as pa

from twoview.llm import grading as G
from twoview.llm import toxicity as T
from twoview.llm.subwords import chunks_of, passages, places
from twoview.llm.text import column_chunks


def corpus(seed, n, bad):
    rng = np.random.default_rng(seed)
    vocab = ["".join(rng.choice(list("abcdefgh"), rng.integers(2, 6))) for _ in range(300)]
    texts, y = [], []
    for i in range(n):
        words = rng.choice(vocab, rng.integers(5, 120)).tolist()
        if i % 3 == 0:
            for _ in range(1 + len(words) // 30):
                words[rng.integers(len(words))] = bad[rng.integers(len(bad))]
        texts.append(" ".join(words))
        y.append(int(i % 3 == 0))
    return texts, np.array(y)


def test_unseen_misspellings_are_caught():
    texts, y = corpus(1, 900, ["xyzzyfoul", "qwertvile", "zorkscum"])
    model = T.train(texts, y)
    new, z = corpus(2, 300, ["xyzzyfouly", "qwertvilez", "zorrkscum"])
    bias = float(model.bias[1] - model.bias[0])
    s = np.concatenate([T.score_chunk(c, model.margin.astype(float), bias, T.PASSAGE) for c in chunks_of(new)])
    assert (s[z == 1] >= 0.3).mean() > 0.8 and (s[z == 0] >= 0.3).mean() < 0.05


def test_gradient_direction_is_shared_by_all_embeddings():
    texts, y = corpus(3, 120, ["xyzzyfoul"])
    model = T.train(texts, y, steps=5)
    rows = model.embedding[np.abs(model.embedding).sum(1) > 0]
    assert np.linalg.matrix_rank(rows.astype(float), tol=1e-3 * np.abs(rows).max()) <= 2


def test_toxicity_on_odd_tables(spark):
    docs = spark.createDataFrame([(1, None, 1), (2, "", 2), (None, "a b", 3), (1, "word " * 5000, 4)], "doc_id long, text string, score int")
    labels = spark.createDataFrame([(1, 1), (2, 0), (2, None), (None, 1)], "doc_id long, toxic int")
    rows = T.toxicity(docs, labels).collect()
    assert len(rows) == 4 and all(0 <= r.score <= 1 and r.predicted in (0, 1) for r in rows)
    assert [r.score for r in T.toxicity(docs, labels.limit(0)).collect()] == [rows[0].score * 0 + r.score for r in T.toxicity(docs, labels.limit(0)).collect()]
    assert T.toxicity(docs.limit(0), labels).count() == 0


def test_passages_cover_all_words():
    for chunk in chunks_of(["a b c d e f g", "", "x", "p q r s"]):
        doc, first, end = passages(chunk, 3, 2)
        for i in range(chunk.n):
            seen = {w for d, a, b in zip(doc, first, end, strict=True) if d == i for w in range(a, b)}
            assert seen == set(range(chunk.word_off[i], chunk.word_off[i + 1]))


def test_places_match_strings():
    text = "Ab abc é"
    chunk = next(chunks_of([text]))
    p = places(chunk, (3, 4), bits=40)
    got = sorted(int(b) for _, bucket in p.layers[:-1] for b in bucket)
    names = sorted(g for w in ("ab", "abc", "é") for n in (3, 4) for g in [f" {w} "[i : i + n] for i in range(len(w) + 3 - n)])
    assert len(got) == len(names)
    assert len(set(got)) == len(set(names))


def test_grades_are_ordered():
    rng = np.random.default_rng(0)
    texts, y = [], []
    for i in range(600):
        g = i % 3
        words = ["good"] * (3 * g + rng.integers(0, 2)) + ["bad"] * (6 - 3 * g + rng.integers(0, 2)) + rng.choice(["the", "of", "and", "it"], 10).tolist()
        texts.append(" ".join(rng.permutation(words)))
        y.append(g)
    model = G.train(texts, np.array(y))
    assert (np.diff(model.thresholds) > 0).all()
    value = np.concatenate([model.value(c) for c in chunks_of(texts)])
    tails = model.tails(value)
    assert (tails[:, 0] >= tails[:, 1]).all()
    assert (tails.sum(1).round() == np.array(y)).mean() > 0.9


def test_grading_on_odd_tables(spark):
    docs = spark.createDataFrame([(1, None), (2, ""), (None, "a b")], "doc_id long, text string")
    ratings = spark.createDataFrame([(1, 0), (2, 2)], "doc_id long, grade int")
    assert len(G.quality_grades(docs, ratings).collect()) == 3
    assert all(r.tail == 0 for r in G.quality_grades(docs, ratings.limit(0)).collect())
    assert G.quality_grades(docs.limit(0), ratings).count() == 0


def brute_toxicity(text, margin, bias):
    """The score word by word and passage by passage."""
    words = (text or "").split()
    sums = []
    for i, w in enumerate(words):
        total, count = places(next(chunks_of([w]))).totals(margin)
        heard = any(v.lower() == w.lower() for v in words[max(0, i - T.PASSAGE) : i])
        sums.append((0.0, 0) if heard else (total[-1], count[-1]))
    best = -np.inf
    for k in range(max(1, -(-(len(words) - T.PASSAGE) // (T.PASSAGE // 2)) + 1)):
        part = sums[k * T.PASSAGE // 2 : k * T.PASSAGE // 2 + T.PASSAGE]
        best = max(best, sum(x for x, _ in part) / max(sum(n for _, n in part), T.FULL))
    return 1 / (1 + np.exp(-(best + bias)))


def test_scores_match_brute_force():
    margin = np.random.default_rng(8).normal(size=1 << 18)
    texts, _ = corpus(9, 40, ["xyzzyfoul"])
    texts += [None, "", "One two ONE", "x " * 300, " ".join(f"w{i}" for i in range(200))]
    for limit in (1, 1 << 18):
        got = np.concatenate([T.score_chunk(c, margin, 0.3, T.PASSAGE) for c in column_chunks(pa.array(texts, pa.string()), limit)])
        assert np.allclose(got, [brute_toxicity(t, margin, 0.3) for t in texts])


def test_grades_match_brute_force():
    """Values as the mean weight of all words and n-grams, computed word by word."""
    weights = np.random.default_rng(4).normal(size=1 << 18)
    grader = G.Grader(weights, np.array([-0.4, 0.7]), np.array([0, 1, 2]))
    texts = [None, "", "One two ONE", " ".join(f"W{i % 7}x" for i in range(90)), "é a  b"]
    want = []
    for t in texts:
        parts = [places(next(chunks_of([w])), G.SIZES, lower=False).totals(weights) for w in (t or "").split()]
        want.append(sum(p[0][-1] for p in parts) / max(sum(p[1][-1] for p in parts), 1))
    value = np.concatenate([grader.value(c) for c in column_chunks(pa.array(texts, pa.string()))])
    assert np.allclose(value, want)
    assert np.allclose(grader.tails(value), [[1 / (1 + np.exp(th - v)) for th in (-0.4, 0.7)] for v in want])


def test_grades_hold_on_rows_set_aside():
    """On the given ratings, rows not learned from: expected grades rank graded pairs far better than chance."""
    import duckdb

    d = "/root/testdata/sf0.01"
    rows = duckdb.sql(f"SELECT DISTINCT ON (d.doc_id) d.text, CASE WHEN quality <= 0 THEN 0 WHEN toxic > 0 THEN 1 ELSE 2 END, d.doc_id FROM '{d}/documents.parquet' d JOIN '{d}/labels.parquet' USING (doc_id) ORDER BY d.doc_id").fetchall()
    learn, held = [r for r in rows if r[2] % 3], [r for r in rows if not r[2] % 3]
    model = G.train([r[0] for r in learn], np.array([r[1] for r in learn]))
    value = np.concatenate([model.value(c) for c in chunks_of([r[0] for r in held])])
    pairs = [(a, b) for a, x in zip(value, held, strict=True) for b, y in zip(value, held, strict=True) if x[1] < y[1]]
    assert np.mean([a < b for a, b in pairs]) > 0.75


def test_very_long_texts_and_clashing_columns(spark):
    docs = spark.createDataFrame([(1, "good words " * 60_000, 0.5, "a"), (2, "bad words", 0.1, "b"), (None, None, None, None)], "doc_id long, text string, value double, tail string")
    ratings = spark.createDataFrame([(1, 2, "x"), (2, 0, "y")], "doc_id long, grade int, text string")
    out = G.quality_grades(docs, ratings).collect()
    assert len(out) == 3 and all(0 <= r.tail <= 1 and 0 <= r.expected_grade <= 2 for r in out)


def test_few_labelled_rows_of_a_class():
    """Fewer rows of a class than folds: they are learnt from all the same."""
    texts, y = corpus(5, 60, ["xyzzyfoul"])
    keep = np.append(np.flatnonzero(y == 0), np.flatnonzero(y == 1)[:2])
    model = T.train([texts[i] for i in keep], y[keep])
    assert np.isfinite(model.margin).all() and np.isfinite(model.bias).all()
