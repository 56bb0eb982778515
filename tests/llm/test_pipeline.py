import corpus_pipeline as P
from twoview.llm.ngram_join import ngram_components


def test_stages_keep_what_they_should(spark):
    d = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    columns = docs.columns
    seen = {}
    for name, stage in P.STAGES:
        out = stage(spark, docs, d)
        if name != "packing":
            assert out.columns == columns
            out = P.written(out, name)
        seen[name] = (docs, out)
        docs = out
    before, after = seen["quality_rules"]
    assert 0.6 * before.count() < after.count() < before.count()
    before, after = seen["ngram_jaccard_join"]
    comps = {r.doc_id: r.component_id for r in ngram_components(before).collect()}
    assert sorted(r.doc_id for r in after.select("doc_id").collect()) == sorted({c for c in comps.values()})
    before, after = seen["private_data"]
    assert before.count() == after.count() and after.where("text rlike '[a-z]+@mail'").isEmpty() and after.where("n_chars <> length(text)").isEmpty()
    before, after = seen["mixing"]
    assert sorted(map(tuple, before.collect())) == sorted(map(tuple, after.collect()))
    assert sorted(r.doc_id for r in seen["packing"][1].collect()) == sorted(r.doc_id for r in after.collect())


def test_repeated_ids_and_nulls(spark):
    text = " ".join(f"word{i}" for i in range(40))
    rows = [(1, text, "en", "s", 1), (1, text, "en", "s", 1), (2, text, None, None, None), (None, text + " tail end", "en", "s", 1), (3, None, None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    d = "/root/testdata/sf0.001"
    kept = P.rules(spark, docs, d)
    assert sorted(map(str, (r.doc_id for r in kept.collect()))) == ["1", "1", "2", "None"]
    one = P.near_duplicates(spark, kept, d)
    assert one.count() == 1 and one.columns == docs.columns  # all of it is one group
    for _, stage in P.STAGES[2:]:
        one = stage(spark, one, d)
    assert one.count() == 1


def test_rows_without_ids_are_treated_by_their_texts(spark):
    """No stage lets a row through, or drops it, for another row's sake."""
    good = " ".join(f"word{i}" for i in range(40))
    other = " ".join(f"thing{i}" for i in range(40)) + " call +1 (988) 555-2485"
    rows = [(None, good), (None, "too short"), (None, other), (5, good + " x"), (5, "short"), (5, other), (None, None)]
    docs = spark.createDataFrame([(*r, "en", "s", 1) for r in rows], "doc_id long, text string, lang string, source string, n_chars long")
    d = "/root/testdata/sf0.001"
    kept = P.written(P.rules(spark, docs, d), "rules")
    assert sorted(r.text for r in kept.collect()) == sorted([good, other, good + " x", other])
    one = P.written(P.near_duplicates(spark, kept, d), "one")
    assert sorted(r.text.split()[0] for r in one.collect()) == ["thing0", "word0"]
    hidden = P.personal_data(spark, one, d).collect()
    assert all("555" not in r.text and r.n_chars == len(r.text) for r in hidden) and any("<phone>" in r.text for r in hidden)
