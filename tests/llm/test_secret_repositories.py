"""Ownership by owners and repositories; patterns run once."""

from kernmill.llm import secret_scan

KEY = "Ab3dEf6hIj9lMn2pQr5tUv8xYz1bCd4f"


def test_values_in_many_repositories_are_copied_examples(spark):
    rows = [(i, f"see {KEY} here", "one owner", f"repo{i}") for i in range(6)] + [(10, "and Zz9yXx8wVv7uTt6sRr5qPp4oNn3mMm2l too", "one owner", "repo1")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, repo string")
    live = {r.doc_id: r.spans for r in secret_scan.report(docs, repository="repo").collect()}
    assert all(live[i] == "" for i in range(6)) and live[10].startswith("opaque:4:36")
    assert all(r.spans for r in secret_scan.report(docs).collect())  # without repositories the owner alone counts


def test_repeated_rows_and_texts_without_candidates(spark):
    docs = spark.createDataFrame([(1, "password = hunter22", "a"), (1, "password = hunter22", "a"), (2, None, None), (3, "", "a")], "doc_id long, text string, source string")
    got = sorted((r.doc_id, r.n_assign, r.spans) for r in secret_scan.report(docs).collect())
    assert got == [(1, 1, "assign:0:19"), (1, 1, "assign:0:19"), (2, 0, ""), (3, 0, "")]
    assert sorted(str(r.text) for r in secret_scan.redact(docs).collect()) == ["", "None", "[SECRET]", "[SECRET]"]
