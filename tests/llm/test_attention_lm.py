import math
import re
from collections import Counter

import numpy as np
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from twoview.llm import attention_lm as L
from twoview.llm.token_store import default_path

PATH = default_path("word_bpe_49k.json")
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def test_gradient_matches_differences():
    rng = np.random.default_rng(0)
    w = L.Weights.fresh(rng)
    w.p = {k: v.astype(np.float64) for k, v in w.p.items()}
    now, last, target = (rng.integers(0, L.CLASSES, (3, L.WINDOW)) for _ in range(3))
    use = rng.random((3, L.WINDOW)) < 0.7
    _, g = L.gradient(w, now, last, target, use)
    for name in w.p:
        for _ in range(3):
            at = tuple(rng.integers(0, s) for s in w.p[name].shape)
            old, e = w.p[name][at], 1e-5
            w.p[name][at] = old + e
            up = L.gradient(w, now, last, target, use)[0]
            w.p[name][at] = old - e
            down = L.gradient(w, now, last, target, use)[0]
            w.p[name][at] = old
            assert abs((up - down) / (2 * e) - g[name][at]) < 1e-5, name


def test_each_token_is_scored_once_and_later_ones_are_unseen():
    rng = np.random.default_rng(1)
    w = L.Weights.fresh(rng)
    lens = [1, 2, 31, 32, 33, 60, 61, 100, 1]
    bounds = np.append(0, np.cumsum(lens))
    classes = rng.integers(0, L.CLASSES, bounds[-1])
    *_, use, index = L.windows_of(classes, bounds, 5)
    assert np.sort(index[use]).tolist() == list(range(bounds[-1]))
    a = L.log_chances(w, classes, bounds, 5)
    changed = classes.copy()
    changed[70] = (changed[70] + 1) % L.CLASSES  # within the text of 60
    b = L.log_chances(w, changed, bounds, 5)
    assert np.allclose(a[:70], b[:70]) and not np.allclose(a[70:73], b[70:73])
    before, earlier, *_ = L.windows_of(classes, bounds, 5)
    chance = np.exp(L.forward(w, before, earlier)["logits"].astype(float))
    full = chance / chance.sum(1, keepdims=True)
    target = classes[index].ravel()
    want = np.log(full[np.arange(len(target)), target])
    assert np.allclose(a[index.ravel()[use.ravel()]], want[use.ravel()], atol=1e-3)


def test_classes_hold_a_distribution():
    counts = np.random.default_rng(2).integers(0, 50, 1000)
    v = L.make_vocabulary(counts, np.random.default_rng(3).integers(0, 1000, 5000), np.random.default_rng(4))
    assert np.allclose(np.bincount(v.of, np.exp(v.share), L.CLASSES)[np.unique(v.of)], 1)
    assert v.of[-1] == L.OWN - 1 and (v.of == L.OWN - 1).sum() == 1


def test_base_matches_brute_force(spark):
    rng = np.random.default_rng(5)
    texts = [" ".join(rng.choice(["The", "the", "cat", "sat", "on", "a", "Mat,", "é", "dog"], rng.integers(0, 30))) for _ in range(60)] + [None, "", "unseen words only", "the " * 3000]
    docs = spark.createDataFrame([(i, t, 1) for i, t in enumerate(texts)] + [(None, "the cat", 2), (3, "the the", 3)], "doc_id long, text string, n int")
    for table in (500_000, 2):
        out = L.language_model_scores(docs, F.col("doc_id") % 4 != 1, PATH, steps=30, max_table=table, refine_every=2).collect()
        words = lambda t: WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        rows = [(i, t) for i, t in enumerate(texts)] + [(None, "the cat"), (3, "the the")]
        seen = Counter(x for i, t in rows if i is not None and i % 4 != 1 for x in [*words(t), "\n"])
        n, v = sum(seen.values()), len(seen)
        want = sorted((str(i), len(words(t)) + 1, sum(seen[x] > 0 for x in [*words(t), "\n"]), round(sum(math.log10((seen[x] + 1) / (n + v + 1)) for x in [*words(t), "\n"]), 6)) for i, t in rows)
        assert sorted((str(r.doc_id), r.n_tokens, r.n_known, round(r.base_score, 6)) for r in out) == want
        assert all(r.train_tokens == n and r.score < 0 for r in out)
    empty = L.language_model_scores(docs.limit(0), F.lit(True), PATH, steps=2)
    assert empty.count() == 0
    none = L.language_model_scores(docs, F.lit(False), PATH, steps=2).collect()
    assert all(r.train_tokens == 0 and r.n_known == 0 and r.base_score == 0 for r in none)


def _rows(spark, texts):
    return spark.createDataFrame([(bytearray(np.array([*t, 999], np.uint16).tobytes()),) for t in texts], "ids binary").coalesce(1)


def test_company_counts_all_texts(spark):
    rng = np.random.default_rng(6)
    texts = [(rng.integers(0, 30, n) ** 2).tolist() + rng.integers(0, 999, n // 3).tolist() for n in rng.integers(0, 40, 300)] + [[], [998, 998]]
    counts = np.bincount([i for t in texts for i in [*t, 999]], minlength=1000)
    own = L.own_classes(counts)
    want = np.zeros((1000, L.SIDES), np.int64)
    for t in texts:
        line = [999, *t, 999]
        for a, b, c in zip(line, line[1:], line[2:], strict=False):
            if own[b] < 0:
                want[b, own[a] if own[a] >= 0 else L.OWN] += 1
                want[b, L.OWN + 1 + (own[c] if own[c] >= 0 else L.OWN)] += 1
    for flush in (50, 2_000_000):
        assert (L._company(_rows(spark, texts).repartition(3), counts, flush) == want).all()


def test_classes_do_not_depend_on_the_sample(spark, monkeypatch):
    words = "river stone cloud ember grain".split()
    texts = [f"the {words[i % 5]} of a" + " the of a" * 5 for i in range(400)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    made, make = [], L.make_vocabulary
    monkeypatch.setattr(L, "make_vocabulary", lambda *a, **k: made.append(make(*a, **k)) or made[-1])
    for tokens in (20, 100_000):
        L.language_model_scores(docs, F.lit(True), PATH, fit_tokens=tokens, steps=1).count()
    assert (made[0].of == made[1].of).all()


def test_every_text_is_refined_on(spark):
    rng = np.random.default_rng(7)
    lens = rng.integers(1, 4000, 50)
    bounds = np.append(0, np.cumsum(lens))
    *_, index = L.windows_of(rng.integers(0, L.CLASSES, bounds[-1]), bounds, 5, 64, 3)
    text = np.searchsorted(bounds, index[:, 0], "right") - 1
    count = np.maximum(1, -(-(lens - L.CONTEXT) // (L.WINDOW - L.CONTEXT)))
    assert set(text) == set(range(50)) and (np.bincount(text) <= -(-count // 64)).all()

    v = L.make_vocabulary(rng.integers(0, 50, 1000), rng.integers(0, 999, 5000), rng)
    texts = [rng.integers(0, 999, 20).tolist() for _ in range(300)]
    w = L.Weights.fresh(rng)

    def refined(texts):
        return L._refined(L._followed(_keyed(spark, texts), v, 64).where("block is null"), len(texts), w).flat()

    before = refined(texts)
    for i in (0, 70, 150, 299):
        changed = texts[:i] + [[(x + 400) % 999 for x in texts[i]]] + texts[i + 1 :]
        assert not np.array_equal(refined(changed), before), i


def _keyed(spark, texts):
    return _rows(spark, texts).withColumn("key", F.xxhash64("ids"))


def test_refined_weights_do_not_depend_on_tasks(spark):
    rng = np.random.default_rng(8)
    v = L.make_vocabulary(rng.integers(0, 50, 1000), rng.integers(0, 999, 5000), rng)
    texts = [rng.integers(0, 999, n).tolist() for n in rng.integers(0, 4000, 60)] + [[5, 6, 7]] * 40
    w, out = L.Weights.fresh(rng), []
    for n in (1, 7):
        windows = L._followed(_keyed(spark, texts).repartition(n), v, 64).where("block is null")
        out.append(L._refined(windows, len(texts), w, group=10).flat())
    assert np.allclose(out[0], out[1], atol=1e-6) and not np.allclose(out[0], w.flat(), atol=1e-4)


def test_shares_after_classes(spark):
    rng = np.random.default_rng(9)
    texts = [(rng.integers(0, 31, n) ** 2).tolist() for n in rng.integers(0, 60, 200)] + [[], [998, 998]]
    counts = np.bincount([i for t in texts for i in [*t, 999]], minlength=1000)
    v = L.make_vocabulary(counts, np.array([i for t in texts for i in [*t, 999]]), rng)
    want = np.zeros((1000, L.CLASSES), np.int64)
    for t in texts:
        for a, b in zip([999, *t], [*t, 999], strict=True):
            want[b, v.of[a]] += v.of[b] >= L.OWN
    for flush in (50, 2_000_000):
        sent = L._followed(_keyed(spark, texts).repartition(3), v, 64, flush).where("block is not null")
        got = L._Blocks.summed(sent, 1000, L.CLASSES)
        assert (got == want).all()
    after = L.shares_after(v, got)
    for c in range(L.CLASSES):
        assert np.allclose(np.bincount(v.of, np.exp(after[c].astype(float)), L.CLASSES)[np.unique(v.of)], 1, atol=1e-4)


def test_scores_match_brute_force(spark, monkeypatch):
    rng = np.random.default_rng(10)
    words = "The river stone's cloud-ember grain of x9 Überfluss a to mill and".split()
    texts = [" ".join(rng.choice(words, n)) for n in rng.integers(0, 60, 120)] + [None, "", "zyxwv qqq", "river " * 90]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    made, fitted = [], []
    make, refine = L.make_vocabulary, L._refined
    monkeypatch.setattr(L, "make_vocabulary", lambda *a, **k: made.append(make(*a, **k)) or made[-1])
    monkeypatch.setattr(L, "_refined", lambda *a, **k: fitted.append(refine(*a, **k)) or fitted[-1])
    got = {r.doc_id: r.score for r in L.language_model_scores(docs, F.col("doc_id") % 5 != 0, PATH, steps=40).collect()}
    v, w = made[0], fitted[0]
    tokenizer = Tokenizer.from_file(PATH)
    end = len(v.of) - 1
    lines = [[*tokenizer.encode(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""), add_special_tokens=False).ids, end] for t in texts]
    after = Counter((v.of[a], b) for i, t in enumerate(lines) if i % 5 for a, b in zip([end, *t], t, strict=False))
    whole = Counter()
    for (c, b), n in after.items():
        whole[c, v.of[b]] += n
    for i, t in enumerate(lines):
        total = 0.0
        for at, x in enumerate(t):
            k = max(0, (at - L.CONTEXT) // (L.WINDOW - L.CONTEXT)) * (L.WINDOW - L.CONTEXT)
            line = [end, end, *t]
            seen = [line[k + j : k + j + 2] for j in range(at - k + 1)]
            seen += [[end, end]] * (L.WINDOW - len(seen))  # later places, which attention masks
            earlier, before = (v.of[np.array(z)][None] for z in zip(*seen, strict=True))
            logits = L.forward(w, before, earlier)["logits"][at - k].astype(float)
            total += logits[v.of[x]] - np.log(np.exp(logits).sum())
            c = v.of[line[at + 1]]
            total += np.log((after[c, x] * (v.of[x] >= L.OWN) + 10 * np.exp(v.share[x])) / (whole[c, v.of[x]] * (v.of[x] >= L.OWN) + 10))
        assert abs(got[i] - total / np.log(10)) < 1e-3 * max(1, len(t) / 20), (i, got[i], total / np.log(10))


def test_all_windows_of_all_texts_are_fitted_to(spark, monkeypatch):
    rng = np.random.default_rng(11)
    words = "river stone cloud ember grain mill and the of a".split()
    texts = [" ".join(rng.choice(words, n)) for n in rng.integers(0, 400, 40)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    seen, refine = [], L._refined

    def watched(lines, *a, **k):
        rows = lines.collect()
        seen.extend((r.key, r.classes, r.every) for r in rows)
        return refine(lines, *a, **k)

    monkeypatch.setattr(L, "_refined", watched)
    L.language_model_scores(docs, F.lit(True), PATH, steps=1).count()
    assert len(seen) == 40 and {every for *_, every in seen} == {1}

    v = L.make_vocabulary(rng.integers(0, 50, 1000), rng.integers(0, 999, 5000), rng)
    lines = [rng.integers(0, 999, 600).tolist() for _ in range(8)]
    w = L.Weights.fresh(rng)

    def refined(lines):
        return L._refined(L._followed(_keyed(spark, lines), v, 1).where("block is null"), len(lines), w).flat()

    monkeypatch.setitem(globals(), "_keyed", lambda spark, texts: _rows(spark, texts).withColumn("key", F.length("ids").cast("long")))
    lines = [line[: 600 - i] for i, line in enumerate(lines)]  # keys stay as they are when a token changes
    before = refined(lines)
    for at in range(14, 590, 28):  # a token of any window counts
        changed = [*lines[3][:at], next(x for x in range(999) if v.of[x] != v.of[lines[3][at]]), *lines[3][at + 1 :]]
        assert not np.array_equal(refined([*lines[:3], changed, *lines[4:]]), before), at


def test_keys_are_found():
    rng = np.random.default_rng(12)
    ends = np.iinfo(np.int64)
    for keys in ([], [5], [ends.min, -1, 0, ends.max], rng.integers(ends.min, ends.max, 5000), rng.integers(0, 900, 300)):
        keys = np.unique(np.array(keys, np.int64))
        h = np.concatenate([keys, keys[:-1] + 1, rng.integers(ends.min, ends.max, 500), [ends.min, ends.max, 0]])
        at, known = L.Keys(keys).find(h)
        assert known.tolist() == np.isin(h, keys).tolist() and (keys[at[known]] == h[known]).all()


def test_only_places_in_use_are_taken_to_logits():
    rng = np.random.default_rng(13)
    w = L.Weights.fresh(rng)
    w.p = {k: v.astype(np.float64) for k, v in w.p.items()}
    now, last, target = (rng.integers(0, L.CLASSES, (6, L.WINDOW)) for _ in range(3))
    use = rng.random((6, L.WINDOW)) < 0.5
    use[2] = False
    loss, g = L.gradient(w, now, last, target, use)
    logits = L.forward(w, now, last)["logits"]
    want = np.log(np.exp(logits).sum(1)) - logits[np.arange(len(logits)), target.ravel()]
    assert abs(loss - want[use.ravel()].mean()) < 1e-9
    chance = np.exp(logits) / np.exp(logits).sum(1, keepdims=True)
    chance[np.arange(len(logits)), target.ravel()] -= 1
    assert np.allclose(g["bias"], chance[use.ravel()].sum(0) / use.sum(), atol=1e-9)
    parts = [L.gradient(w, *(x[k : k + 1] for x in (now, last, target, use))) for k in range(6)]  # windows by themselves
    for name in g:
        whole = sum(part[name] * use[k].sum() for k, (_, part) in enumerate(parts)) / use.sum()
        assert np.allclose(g[name], whole, atol=1e-7), name
    loss, g = L.gradient(w, now, last, target, np.zeros_like(use))
    assert loss == 0 and all((x == 0).all() for x in g.values())
    w.p["bias"][3] = 2000.0  # beyond what exp takes
    with np.errstate(over="ignore"):
        loss, g = L.gradient(w, now, last, target, use)
    assert np.isfinite(loss) and all(np.isfinite(x).all() for x in g.values())


def test_logits_of_unused_places_are_not_computed(monkeypatch):
    rng = np.random.default_rng(14)
    w, bounds = L.Weights.fresh(rng), np.append(0, np.cumsum([100] * 40))
    classes, rows = rng.integers(0, L.CLASSES, bounds[-1]), []
    exp = np.exp
    monkeypatch.setattr(L.np, "exp", lambda x, **k: rows.append(len(x)) or exp(x, **k) if x.ndim == 2 and x.shape[1] == L.CLASSES else exp(x, **k))
    L.log_chances(w, classes, bounds, 5)
    before, earlier, target, use, _ = L.windows_of(classes, bounds, 5)
    assert sum(rows) == len(classes) < before.size
    rows.clear()
    L.gradient(w, before, earlier, target, use)
    assert sum(rows) == len(classes)
