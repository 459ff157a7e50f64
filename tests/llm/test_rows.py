"""Rows are told apart by themselves, not by their keys: repeated and null keys lose no text, leak no secret, add no row."""

import collections

import pytest

from episodic.llm import embeddings, exact_dedup, near_dedup, secrets

A = "one two three four five six seven eight nine ten"
B = "alpha beta gamma delta epsilon zeta eta theta iota kappa"
C = "red green blue cyan magenta yellow black white grey brown"


def _docs(spark, rows):
    return spark.createDataFrame(rows, "doc_id bigint, text string, source string")


def _counted(df):
    return collections.Counter(map(tuple, df.collect()))


def test_near_groups_with_repeated_keys(spark):
    df = _docs(spark, [(1, A, "a"), (5, A, "a"), (5, B, "a"), (9, B, "a"), (9, B, "a"), (None, A, "a"), (None, C, "b"), (5, None, "a")])
    got = _counted(near_dedup.near_groups(df, 3, 85))
    assert got == collections.Counter(
        [(1, 8, 1, True), (5, 8, 1, False), (5, 8, 5, True), (9, 8, 5, False), (9, 8, 5, False), (None, 8, None, True), (None, 8, None, True), (5, 0, 5, True)]
    )


def test_near_copies_lose_no_text(spark):
    near = A.replace("ten", "eleven") + " and some more words"
    rows = [(1, A, "a"), (5, A, "a"), (5, B, "a"), (9, B, "a"), (9, B, "b"), (5, B, "c"), (None, A, "a"), (None, C, "b"), (5, None, "a"), (5, near, "a")]
    kept = near_dedup.drop_near_copies(_docs(spark, rows), 3, 85)
    texts = collections.Counter((r["doc_id"], r["text"]) for r in kept.collect())
    assert kept.columns == ["doc_id", "text", "source"]
    assert texts == collections.Counter([(1, A), (5, B), (None, A), (None, C), (5, None), (5, near)])
    assert near_dedup.drop_near_copies(_docs(spark, [(1, A, "a"), (5, A, "a"), (5, B, "a"), (9, B, "a")]), 3, 85).count() == 2


def test_exact_copies_lose_no_text(spark):
    rows = [(1, A, "a"), (5, A, "a"), (5, B, "a"), (9, B, "a"), (9, B, "b"), (None, A, "a"), (None, C, "b"), (None, C, "b"), (5, B, "c"), (7, "", "a"), (8, None, "a")]
    kept = exact_dedup.drop_exact_copies(_docs(spark, rows))
    assert collections.Counter((r["doc_id"], r["text"]) for r in kept.collect()) == collections.Counter([(1, A), (5, B), (None, C), (7, "")])
    groups = exact_dedup.exact_groups(_docs(spark, rows))
    assert groups.count() == len(rows)
    assert {(r["doc_id"], r["keep_id"], r["group_size"]) for r in groups.collect()} == {(1, 1, 3), (5, 1, 3), (None, 1, 3), (5, 5, 4), (9, 5, 4), (None, None, 2), (7, 7, 2), (8, 7, 2)}


SECRET = "password = hunter2hunter2xyz"


def _secret_rows():
    return [(None, f"first {SECRET} end", "a"), (None, "token=ab12cd34 x", "a"), (None, "nothing here at all", "a"), (7, f"{SECRET} second", "b"), (7, "an innocent row of the same key", "b"), (7, f"{SECRET} second", "b"), (8, None, None)]


def test_secret_spans_of_rows_with_null_and_repeated_keys(spark):
    df = _docs(spark, _secret_rows()).repartition(3)
    got = collections.Counter((r["doc_id"], r["n_assign"], r["spans"]) for r in secrets.digest_columns(secrets.scan_secrets(df)).collect())
    whole = "assign:0:28"
    assert got == collections.Counter([(None, 1, "assign:6:34"), (None, 0, "weak:0:14"), (None, 0, ""), (7, 1, whole), (7, 0, ""), (7, 1, whole), (8, 0, "")])


def test_each_row_loses_its_own_secrets_only(spark):
    df = _docs(spark, _secret_rows()).repartition(3)
    got = _counted(secrets.redact_live(df))
    m = "[REDACTED]"
    assert got == collections.Counter(
        [(None, f"first {m} end", "a"), (None, f"{m} x", "a"), (None, "nothing here at all", "a"), (7, f"{m} second", "b"), (7, "an innocent row of the same key", "b"), (7, f"{m} second", "b"), (8, None, None)]
    )


@pytest.mark.parametrize("kind", ["float", "double"])
def test_vectors_with_repeated_keys(spark, kind):
    near, far = [1.0, 0.05, 0.0], [0.0, 0.0, 1.0]
    rows = [(1, [1.0, 0.0, 0.0]), (1, near), (2, [1.0, 0.0, 0.05]), (2, [1.0, 0.0, 0.05]), (3, far), (1, far), (None, far), (4, None), (4, [1.0, 0.0, 0.0])]
    df = spark.createDataFrame(rows, f"vec_id bigint, embedding array<{kind}>").repartition(2)
    got = collections.Counter(map(tuple, embeddings.near_vectors(df).collect()))
    #                              key, links, component, kept
    assert got == collections.Counter(
        [(1, 2, 1, True), (1, 2, 1, True), (2, 2, 1, False), (2, 2, 1, False), (4, 2, 1, False), (3, 1, 1, False), (1, 1, 1, True), (None, 0, None, True), (4, 0, 4, True)]
    )
    kept = embeddings.drop_near_vectors(df)
    assert sorted((str(r["vec_id"]), r["embedding"] is None) for r in kept.collect()) == [("1", False), ("1", False), ("4", True), ("None", False)]


def test_vector_equal_to_many(spark):
    """A group of copies is one class: each counts all the others, and what lies near one lies near all."""
    rows = [(i, [3.0, 4.0]) for i in range(700)] + [(1000 + i, [3.0, 4.001]) for i in range(5)] + [(2000, [-1.0, 0.0])]
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in embeddings.near_vectors(spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")).collect()}
    assert got == {i: (704, 0) for i, _ in rows[:-1]} | {2000: (0, 2000)}
