"""Distinct pairs of members that share a key."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pytest

from sketchinit.functions.rng import key_id_py
from sketchinit.sources import graphs
from sketchinit.sources.pairs import block_pairs, pairs_within


@pytest.mark.parametrize("cells", [64, 1 << 23])
@pytest.mark.parametrize("same", [True, False])
@pytest.mark.parametrize("size", [3, 40])
def test_block_pairs_equal_brute_force(size, same, cells):
    rng = np.random.default_rng(size)
    sides = [[np.sort(rng.choice(6000, int(rng.integers(1, size)), replace=False)).astype(np.int64) * 2 + k for _ in range(300)] for k in (0, 1)]
    flat = [(np.concatenate(x), np.concatenate([[0], np.cumsum([len(y) for y in x])])) for x in sides]
    want = {p for x in sides[0] for p in combinations(x.tolist(), 2)} if same else {(a, b) for x, y in zip(*sides) for a in x.tolist() for b in y.tolist()}
    got = []
    for a, ptr, b in block_pairs(*flat[0], *(flat[1] if not same else (np.zeros(0, np.int64), np.zeros(301, np.int64))), same, cells):
        got += zip(np.repeat(a, np.diff(ptr)).tolist(), b.tolist())
    assert len(got) == len(set(got)) and set(got) == want


@pytest.mark.parametrize("blocks", [1, 3])
def test_pairs_within_blocks(spark, blocks):
    rng = np.random.default_rng(5)
    rows = [(int(k), int(m)) for k in range(60) for m in rng.integers(-50, 50, 1 + k % 9)] + [(99, m) for m in range(-30, 30)] + [(98, m) for m in range(-30, 30)] + [(None, 1), (1, None)]
    by: dict = {}
    for k, m in rows:
        if k is not None and m is not None:
            by.setdefault(k, set()).add(m)
    want = {p for s in by.values() for p in combinations(sorted(s), 2)}
    got = [tuple(r) for r in pairs_within(spark.createDataFrame(rows, "key long, member long"), len(rows), 100, blocks).collect()]
    assert len(got) == len(set(got)) and set(got) == want


def test_pairs_of_many_keys_are_not_sent(spark, tmp_path):
    """60 users who meet in 300 hours: the pairs that are found 300 times are never rows of an exchange."""
    spark.sql("SELECT explode(sequence(1, 60)) AS user_id").crossJoin(spark.range(300).selectExpr("timestamp_seconds(id * 3600) AS ts")).write.parquet(f"{tmp_path}/events.parquet")
    e = graphs.coactive(spark, str(tmp_path))
    assert e.count() == e.distinct().count() == 60 * 59 // 2
    plan = e._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan[: plan.index("MapInArrow")]


def test_documents_of_one_passage_are_not_sent_as_pairs(spark, tmp_path):
    """40 documents share 60 runs of five words: each pair is found 60 times and is in no exchange."""
    words = " ".join(f"w{i}" for i in range(64))
    spark.createDataFrame([(i, f"x{i} {words} y{i}") for i in range(40)] + [(40, "a b c d"), (41, None)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    e = graphs.docshare(spark, str(tmp_path))
    assert sorted(map(tuple, e.collect())) == list(combinations(range(40), 2))
    plan = e._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan[: plan.index("MapInArrow")]


def test_adjacent_words_are_counted_in_whole_texts(spark, tmp_path):
    """Repeats, one word beside itself, ends of texts, empty and null texts and languages, and words before a line's end, which are none."""
    rows = [("Élan vital élan  vital", "fr"), ("vital", "fr"), ("élan", None), ("vital Élan", None), ("x\n y", "en"), ("x y\n", "en"), ("a1 y ß y", "en"), ("", "en"), (None, "en"), ("z z y", "en")]
    spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    want = {("vital", "élan", "fr"): 2, ("vital", "élan", None): 1, ("y", "ß", "en"): 2, ("y", "z", "en"): 1}
    ids = lambda a, b: tuple(sorted((key_id_py(a), key_id_py(b))))
    assert {tuple(r)[:3]: r["n"] for r in graphs.word_pairs(spark, str(tmp_path), "lang").collect()} == {(*ids(a, b), c): n for (a, b, c), n in want.items()}
    assert {tuple(r) for r in graphs.word_pairs(spark, str(tmp_path)).collect()} == {(*ids(a, b), n) for a, b, n in (("vital", "élan", 3), ("y", "ß", 2), ("y", "z", 1))}
