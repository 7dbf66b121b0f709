"""A first star round without a pair must not end the search."""

import pytest

from pathload.llm import jaccard


@pytest.mark.parametrize("word", ["w", "x", "y", "z", "v"])
def test_pair_beside_failing_stars(spark, word):
    b = [f"{word}{i}" for i in range(9)]
    texts = [b, [*b, "more"], *(b[i : i + 4] for i in range(6))]
    docs = spark.createDataFrame([(i + 1, " ".join(t)) for i, t in enumerate(texts)], "doc_id bigint, text string")
    got = {r["doc_id"]: r["component_id"] for r in jaccard.jaccard_components(docs, 4, 85).collect()}
    assert got == {1: 1, 2: 1} | {i: i for i in range(3, 9)}
