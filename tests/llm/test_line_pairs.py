"""Line dedup compares one pair of most similar lines, not all pairs of a group."""

from densesql.llm import op6_lines


def test_a_group_of_similar_lines_is_not_compared_in_all_pairs(spark, monkeypatch):
    common = " ".join(f"c{k}" for k in range(20))
    given = [(k, f"{common} own{k}") for k in range(30)]  # any two share 20 of 22 words
    written, table = {}, op6_lines.Staging.table

    def counted(self, df, name, row_id=None):
        out = table(self, df, name, row_id)
        written[name] = out.count()
        return out

    monkeypatch.setattr(op6_lines.Staging, "table", counted)
    df = spark.createDataFrame(given, "doc_id long, text string").repartition(3)
    found = {r["doc_id"]: r["n_kept"] for r in op6_lines.line_report(df).collect()}
    assert found == {k: int(k == 0) for k in range(30)}
    assert written["near"] + written["likeliest"] + written["left"] <= 30 < 30 * 29 // 2
