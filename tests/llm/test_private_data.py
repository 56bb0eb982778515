import hashlib
import random
import re

import pyarrow as pa

from twoview.llm import private_data as P
from twoview.llm.text import column_chunks

EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")


def brute(text):
    text = text or ""
    out = [(m.start(), 0, m.end()) for m in EMAIL.finditer(text)]
    out += [(m.start(), 1, m.end()) for m in IP.finditer(text) if all(int(x) <= 255 for x in m[0].split("."))]
    for m in CARD.finditer(text):
        d = re.sub("[^0-9]", "", m[0])
        if 14 <= len(d) <= 19 and P.luhn(d):
            out.append((m.start(), 2, m.end()))
    out += [(m.start(), 3, m.end()) for m in PHONE.finditer(text) if 10 <= len(re.sub("[^0-9]", "", m[0])) <= 15]
    return ",".join(f"{P.KINDS[k]}:{s}:{e}" for s, k, e in sorted(out))


FIXED = [
    None,
    "",
    "a@b.c",
    "é a.b+c@d-e.f.g, x@y@z.w a@b..c a@b.c@d.e",
    "1.2.3.4 256.1.1.1 1.2.3.4.5.6.7.8 1..2.3.4.5 0001.02.3.4 .1.2.3.4.",
    "4111 1111 1111 1111 and 4111-1111-1111-1112 4111  1111 1111 1111",
    "+1 (988) 555-2485 +1 +12 +123 +1-2345678901 +1 (2) 3. x +12345678901234567",
    "+4915112345678 ends",
    "12",
    "@",
    "5500005555555559 5500005555555559",
]


def rule_text(texts, limit=1 << 18):
    out = []
    for chunk in column_chunks(pa.array(texts, pa.string()), limit):
        out += [P.written_spans(x) for x in P.scan(chunk, [])[1]]
    return out


def test_rules_match_brute_force():
    rng = random.Random(1)
    pieces = ["1", "25", "255", "256", ".", ".", "@", "a", "Z-", " ", "-", "+", "(", ")", "é", "\n", "4111111111111111", "b.c", "+1 ", "0"]
    texts = FIXED + ["".join(rng.choice(pieces) for _ in range(rng.randrange(60))) for _ in range(6000)]
    assert rule_text(texts) == [brute(t) for t in texts]
    assert rule_text(texts, 1) == [brute(t) for t in texts]


def test_contexts_find_unseen_identifiers(spark):
    rows = [(i, f"please write to member no {1000 + i}@x{i}.org now") for i in range(12)]
    rows += [(100, "member no AB12-99871 now"), (101, "room 123456 is free"), (102, None), (103, "")]
    docs = spark.createDataFrame([(i, t, "n") for i, t in rows], "doc_id long, text string, row string")
    out = {r.doc_id: r for r in P.private_data(docs).collect()}
    assert out[100].spans == "id:10:20" and out[100].n_id == 1 and out[100].base == ""
    assert out[101].spans == "" and out[102].spans == "" and out[103].base_sha256 == hashlib.sha256(b"").hexdigest()
    assert out[3].spans == out[3].base and out[3].n_email == 1
    hidden = {r.doc_id: r.text for r in P.masked(docs).collect()}
    assert hidden[100] == "member no <id> now" and hidden[102] is None and hidden[103] == ""
    assert hidden[0] == "please write to member no <email> now"
    assert P.masked(docs).columns == docs.columns


def test_every_rule_span_is_a_seed(spark):
    """Seeds of several words or without digits teach patterns, which find identifiers of letters alone or with one digit."""
    names = ["ann", "bob", "cid", "dan", "eva", "fay", "gus", "hal", "ida", "jon", "kim", "lea"]
    rows = [(i, f"{'so ' * (i % 3)}mail to {n}.smith@example.org today") for i, n in enumerate(names)]
    rows += [(20 + i, f"ring desk +1 ({212 + i}) 555-26{10 + i} please") for i in range(12)]
    rows += [(50, "mail to jane_doe today"), (51, "ring desk x7abc please"), (52, "mail to nobody today"), (53, "we mail to the well-known shop")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    out = {r.doc_id: r for r in P.private_data(docs).collect()}
    assert out[50].spans == "id:8:16" and out[51].spans == "id:10:15"
    assert out[52].spans == "" and out[53].spans == ""
    assert all(out[i].n_email == 1 for i in range(12)) and all(out[20 + i].n_phone == 1 for i in range(12))


def test_rows_without_or_with_repeated_ids(spark):
    rows = [(None, "call +1 (988) 555-2485 or a@b.org"), (None, None), (7, "write x@y.org"), (7, "nothing here"), (7, "write x@y.org")]
    docs = spark.createDataFrame([(*r, "k", 1.5) for r in rows], "doc_id long, text string, spans string, base double")
    hidden = sorted(str(r.text) for r in P.masked(docs).collect())
    assert hidden == sorted(["call <phone> or <email>", "None", "write <email>", "nothing here", "write <email>"])
    found = sorted((str(r.doc_id), r.spans) for r in P.private_data(docs).collect())
    assert found == sorted([("None", "phone:5:22,email:26:33"), ("None", ""), ("7", "email:6:13"), ("7", ""), ("7", "email:6:13")])


def test_long_words_and_texts(spark):
    long = "k" * 300 + "9" * 300
    rows = [(i, "word " * (40_000 if i < 23 else 2) + f"serial {long}{i}@a.org end") for i in range(20, 45)] + [(9, f"serial {long}77 end"), (10, f"serial {long}78")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    out = {r.doc_id: r for r in P.private_data(docs).collect()}
    assert out[9].spans == f"id:7:{7 + 602}" and out[10].n_id == 1 and out[20].n_email == 1


def test_patterns_in_parts(spark):
    docs = spark.createDataFrame([(i, f"code {i}{i}a@x{i}.org is here") for i in range(12)] + [(50, "code q77-b is here")], "doc_id long, text string")
    whole, parts = P.learn_patterns(docs), P.learn_patterns(docs, part=2)
    assert len(whole) == 1 and len(parts) > 1 and sorted(whole[0].tolist()) == sorted(x for p in parts for x in p.tolist())
    chunk = next(column_chunks(pa.array(["code q77-b is here"])))
    assert P.scan(chunk, whole)[1] == P.scan(chunk, parts)[1] == [[(5, 4, 10)]]


def test_repeats_score_by_the_graph(spark):
    """Scores as the definition has them, computed by hand on a small graph."""
    graph = [(1, i, True) for i in range(9)] + [(1, 100, False)] + [(2, 100, False)] + [(2, i, True) for i in range(4)] + [(3, i, True) for i in range(5)] + [(3, 200 + i, False) for i in range(5)]
    df = spark.createDataFrame(graph, "pat long, inst long, seed boolean")
    for rounds in (1, 2, 3):
        score = {}
        for _, i, seed in graph:
            score[i] = max(score.get(i, 0.0), float(seed))
        for r in range(rounds):
            good = {}
            for p in (1, 2, 3):
                own = [score[i] for q, i, _ in graph if q == p]
                if sum(own) / len(own) >= 0.9 and sum(x >= 0.9 for x in own) >= 5:
                    good[p] = sum(own) / len(own)
            miss = {}
            for p, i, _ in graph:
                if p in good:
                    miss[i] = miss.get(i, 1.0) * max(1 - good[p], 1e-6)
            score = {i: max(v, 1 - miss.get(i, 1.0)) for i, v in score.items()}
        got = {r.pat: r.confidence for r in P.pattern_scores(df, rounds, 0.9, 5).collect()}
        assert got.keys() == good.keys() and all(abs(got[p] - good[p]) < 1e-9 for p in good)


def test_empty_table(spark):
    assert P.private_data(spark.createDataFrame([], "doc_id long, text string")).count() == 0
