"""Names and values that the operators use themselves."""


def test_redact_keeps_columns_of_its_own_names(spark):
    from locveil.llm.secrets import redact

    names = ["__found", "__base", "__id", "__assign", "row", "a.b"]
    df = spark.sql("SELECT 1L doc_id, 'token: abcdefgh12345678 x' text, 26 n_chars").selectExpr("*", *(f"'{n}' `{n}`" for n in names))
    got = redact(df)
    assert got.columns == df.columns
    row = got.first().asDict()
    assert row["text"] == "[SECRET] x" and row["n_chars"] == 10 and all(row[n] == n for n in names)


def test_spans_go_by_start_then_kind(spark):
    from pyspark.sql import functions as F

    from locveil.llm.secrets import scan

    text = "user=abcdef password=abcdefgh!! x"
    found = scan(spark.createDataFrame([(1, text)], "doc_id long, text string")).select(F.col("__found")).first()[0]
    assert [(s.start, s.kind, s.stop) for s in found] == [(0, "linked_id", 11), (12, "assign", 29), (12, "linked_secret", 31)]


def test_null_is_a_source_of_its_own(spark):
    from locveil.llm.mixing import mix_sources

    rows = [(i, "w " * 10, s) for i, s in enumerate(["\x00null", None, "", "null"] * 40)]
    got = mix_sources(spark.createDataFrame(rows, "doc_id long, text string, source string")).toPandas()
    assert len(got) == 160
    for name in ["\x00null", "", "null"]:
        own = got[got["source"] == name]
        assert len(own) == 40 and abs(own["taken"].sum() - own["target"].iloc[0]) <= 5
    own = got[got["source"].isna()]
    assert len(own) == 40 and abs(own["taken"].sum() - own["target"].iloc[0]) <= 5
