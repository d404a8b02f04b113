"""The corpus pipeline, stage by stage, on a table with planted cases."""

import random

import corpus_pipeline as P
from conftest import same_rows  # noqa: F401
from pyspark.sql import functions as F

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def planted(spark, small):
    """Real documents, and after them copies, shared passages, leaks and junk with known identifiers."""
    docs = spark.read.parquet(f"{small}/documents.parquet").where("length(text) > 400").dropDuplicates(["text"]).limit(120)
    rows = [(r.doc_id, r.text, r.lang, r.source, r.n_chars) for r in docs.collect()]
    rng = random.Random(4)
    item = max((r.text for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()), key=len)
    fresh = lambda n: " ".join("".join(rng.choice("aeioust") for _ in range(7)) for _ in range(n))
    passage = fresh(60)
    near = rows[0][1].split(" ")
    near[len(near) // 2] = "other"
    cases = {9001: rows[0][1], 9002: " ".join(near), 9003: fresh(100) + " " + item + " " + fresh(50), 9004: fresh(80) + " " + passage, 9005: passage + " " + fresh(90), 9006: "### 123 !!!", 9007: None, 9008: fresh(40)}
    rows += [(i, t, "en", "planted", len(t or "")) for i, t in cases.items()]
    return spark.createDataFrame(rows, SCHEMA), rows, passage


def test_stages_catch_planted_cases(spark, small):
    docs, rows, passage = planted(spark, small)
    stages = dict(P.STAGES)
    assert [n for n, _ in P.STAGES] == ["language_id", "near_duplicates", "substring_dedup", "decontamination", "packing"]

    kept = {r.doc_id for r in stages["language_id"](spark, docs, small).collect()}
    assert {9006, 9007}.isdisjoint(kept) and len(kept) >= len(rows) - 4

    some = docs.where("text is not null")
    out = stages["near_duplicates"](spark, some, small)
    kept = {r.doc_id for r in out.collect()}
    assert out.columns == docs.columns and rows[0][0] in kept and {9001, 9002}.isdisjoint(kept) and {9003, 9004, 9005, 9008} <= kept

    out = {r.doc_id: r.text for r in stages["substring_dedup"](spark, some, small).collect()}
    assert passage in out[9004] and passage not in out[9005] and out[9008] == next(r[1] for r in rows if r[0] == 9008) and 9001 not in out

    kept = {r.doc_id for r in stages["decontamination"](spark, some, small).collect()}
    assert 9003 not in kept and {9004, 9005, 9008} <= kept

    packed = stages["packing"](spark, some, small)
    assert packed.select("doc_id").distinct().count() == some.count()


def test_near_duplicates_keep_unrelated_texts_of_one_id(spark, small):
    rng = random.Random(8)
    fresh = lambda: [rng.choice("abcdefgh") + str(rng.randrange(10**6)) for _ in range(100)]
    edited = lambda ws: " ".join([*ws[:50], "other", *ws[51:]])
    a, b, c = fresh(), fresh(), fresh()
    cases = [(5, " ".join(a)), (5, " ".join(b)), (6, edited(a)), (7, edited(b)), (None, " ".join(c)), (None, edited(c))]
    docs = spark.createDataFrame([(i, t, "en", "planted", len(t)) for i, t in cases], SCHEMA)
    kept = [(r.doc_id, r.text) for r in dict(P.STAGES)["near_duplicates"](spark, docs, small).collect()]
    assert {k for k in kept if k[0] is not None} == {cases[0], cases[1]} and len(kept) == 3 and set(kept) & set(cases[4:])


def test_run_on_documents(spark, small):
    out = P.run(spark, small)
    assert out.groupBy("sequence_id").agg(F.sum("length").alias("n")).where("n > 2048").count() == 0
    assert 0.7 * 200 < out.select("doc_id").distinct().count() <= 200


def test_stages_on_an_empty_table(spark, small):
    empty = spark.createDataFrame([], SCHEMA)
    for _, stage in P.STAGES:
        assert stage(spark, empty, small).count() == 0


def test_entry_registers_everything():
    import __spark_entry__ as entry

    names = entry.queries()
    assert "pipeline" in names and all(any(n.startswith(f"op{k}_") for n in names) for k in range(1, 11))


CLASHES = ["score", "rejected", "lang_pred", "n_words", "n_removed", "kept_text", "kept_sha256", "spans", "contaminated", "n_hit", "own", "key", "words", "component", "node", "tallquant_row", "a.b"]


def test_stages_with_clashing_columns_repeated_rows_and_nulls(spark, small):
    """Columns of any name come through; repeated rows, null identifiers and null texts have a defined result in each stage."""
    docs, rows, _ = planted(spark, small)
    odd = [(None, rows[5][1], "en", "s", 1), (None, None, None, None, None), (7, "", "de", None, 0), rows[3], rows[3]]
    docs = docs.union(spark.createDataFrame(odd, SCHEMA))
    plain = docs
    for c in CLASHES:
        docs = docs.withColumn(c, F.concat(F.lit(f"{c}:"), F.coalesce(F.col("doc_id").cast("string"), F.lit("none"))))
    for name, stage in P.STAGES[:-1]:
        out = stage(spark, docs, small)
        assert out.columns == docs.columns, name
        got = out.collect()
        assert all(r[c] == f"{c}:{'none' if r.doc_id is None else r.doc_id}" for r in got for c in CLASHES), name
        want = stage(spark, plain, small).collect()
        assert sorted(((r.doc_id, r.text) for r in got), key=str) == sorted(((r.doc_id, r.text) for r in want), key=str), name
        if name in ("language_id", "decontamination"):
            assert sum((r.doc_id, r.text) == rows[3][:2] for r in got) == 3, name
        if name == "near_duplicates":
            assert sum(r.text == rows[3][1] for r in got) == 1 and sum(r.text == rows[5][1] for r in got) == 1 and any(r.text is None for r in got), name
    packed = P.STAGES[-1][1](spark, docs, small)
    assert packed.where("doc_id is null").select("doc_tokens").distinct().count() == 2
