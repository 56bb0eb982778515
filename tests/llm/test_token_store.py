import zlib

import numpy as np
import pytest
from tokenizers import Tokenizer

from twoview.llm import token_store as S

PATH = S.default_path("word_bpe_49k.json")
TEXTS = ["Hello, WORLD's end", None, "", " \n", "naïve é a b  x", "don't 123 #$%% <|endoftext|> tail<|startoftext|>x", "áb ́c", "word " * 4000, "Ünïcode ß ﬁ \x1cz\x85q"]


def test_round_trip(spark):
    rows = [(10 * i, t) for i, t in enumerate(TEXTS)] + [(30, "again"), (None, "no id")]
    docs = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, part int").repartition(3)
    store = S.write_store(docs, PATH, end_id=2, parts=3)
    got = store.documents().collect()
    tok = Tokenizer.from_file(PATH)
    assert len(got) == len(rows)
    want = {}
    for i, t in rows:
        want.setdefault(i, []).append([*tok.encode(t or "", add_special_tokens=False).ids, 2])
    at = 0
    for r in sorted(got, key=lambda r: r.start):
        ids = np.frombuffer(r.ids, "<u4").tolist()
        assert ids in want[r.doc_id] and r.start == at and r.crc == zlib.crc32(np.array(ids, "<u4").tobytes())
        at += r.n_tokens
    order = [r.doc_id for r in sorted(got, key=lambda r: r.start)]
    assert order[0] is None and order[1:] == sorted(order[1:])
    assert [x.tolist() for x in store.get(0)] == want[0] and len(store.get(30)) == 2 and store.get(5) == []


def test_dictionary_is_used_and_checked(spark):
    docs = spark.createDataFrame([(i, f"the quick brown fox {i} jumps over lazy dogs " * 3) for i in range(600)], "doc_id long, text string")
    store = S.write_store(docs, PATH, end_id=2, parts=2)
    assert store.dictionary
    with pytest.raises(Exception, match="another dictionary"):
        S.TokenStore(store.blocks, b"").documents().collect()
    assert S.write_store(docs.limit(0), PATH, end_id=2).documents().count() == 0


def test_files_lie_in_order_and_reads_are_pruned(spark):
    docs = spark.createDataFrame([(i, f"document {i} " * 5, "x") for i in range(900)], "doc_id long, text string, lo string").repartition(5)
    store = S.write_store(docs, PATH, end_id=2, parts=6)
    spans = [tuple(r) for r in store.blocks.selectExpr("_metadata.file_name", "part", "lo", "hi").orderBy("file_name", "part").collect()]
    assert [s[2] for s in spans] == sorted(s[2] for s in spans) and all(a[3] < b[2] for a, b in zip(spans, spans[1:], strict=False))
    assert len({s[0] for s in spans}) == len({s[1] for s in spans})
    tok = Tokenizer.from_file(PATH)
    assert [x.tolist() for x in store.get(431)] == [[*tok.encode("document 431 " * 5, add_special_tokens=False).ids, 2]]
    plan = store.blocks.where("lo <= 431 AND hi >= 431").select("part")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(lo), IsNotNull(hi), LessThanOrEqual(lo,431)" in plan


def test_whole_query_against_brute_force(spark):
    """Every document of the given table: start, number of ids and their checksum."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    tok, at, want = Tokenizer.from_file(PATH), 0, {}
    for r in docs.orderBy("doc_id").collect():
        ids = np.array([*tok.encode(r.text or "", add_special_tokens=False).ids, 2], "<u4")
        want[r.doc_id] = (at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    assert {r.doc_id: tuple(r)[1:] for r in S.store_digest(spark, docs, PATH, 2).collect()} == want
