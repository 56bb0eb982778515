import re
from collections import Counter

import numpy as np
import pyarrow as pa

from twoview.llm import quality_rules as Q
from twoview.llm.text import column_chunks

WORD = re.compile(r"[^\x20\x09-\x0D]+")
TEXTS = [
    "a b c d e f a b c d e f",
    None,
    "",
    "  \n\t ",
    "x\nx\n\n\nx \nx",
    "one\ntwo\none\ntwo\n",
    "\nlead\nlead\n\n",
    "é ü é ü é é ü é ü é #%$",
    "w " * 30,
    "long" * 3000,
    "q\r\nq\r\nq",
    "last line",
]


def brute(text):
    text = text or ""
    words = WORD.findall(text)
    wins = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
    often = Counter(wins)
    cover = {i + k for i, w in enumerate(wins) if often[w] > 1 for k in range(5)}
    seen, dup = set(), 0
    for line in text.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    return {
        "n_words": len(words),
        "word_chars": sum(map(len, words)),
        "n_symbols": sum(c in "#*$%&|<>" for c in text),
        "n_dup_lines": dup,
        "n_repeat_words": len(cover),
    }


def test_counts_match_brute_force():
    for limit in (1, 40, 1 << 18):
        got = []
        for chunk in column_chunks(pa.array(TEXTS), limit):
            c = Q.rule_counts(chunk)
            got += [{k: int(c[k][i]) for k in brute("")} for i in range(chunk.n)]
        assert got == [brute(t) for t in TEXTS]


def test_forest_sets_outliers_apart():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(2000, 3))
    x[:20] += 8
    s = Q.fit_forest(x).score(x)
    assert s[:20].min() > np.quantile(s[20:], 0.97)
    assert ((s > 0) & (s < 1)).all()


def test_threshold_spares_good_rows():
    assert Q.calibrate([(5, 100, 0), (9, 0, 7)], 10, 0.0) == 0.7
    assert Q.calibrate([(5, 100, 0)], 10, 0.0) == 2.0
    assert Q.calibrate([], 10, 0.0) == 2.0


def test_odd_tables(spark):
    docs = spark.createDataFrame([(i, t, "x") for i, t in enumerate(TEXTS)] + [(0, TEXTS[0], "y"), (None, None, None)], "doc_id long, text string, score string")
    labels = spark.createDataFrame([(0, 1), (0, 1), (None, 0), (4, None)], "doc_id long, quality int")
    out = Q.quality_rules(docs, labels, trees=5)
    rows = out.collect()
    assert len(rows) == len(TEXTS) + 2
    assert all(r.base_failed and not r.kept for r in rows if r.n_words == 0)
    assert Q.quality_rules(docs.limit(0), labels.limit(0), trees=5).count() == 0
