"""The forest with its production parameters on few rows."""

import numpy as np
import pytest

from rpqframe.llm import ann_forest
from tests.llm.test_operators import nearest


@pytest.mark.parametrize("rows", [2, 24, 50, 100, 200])
def test_small_tables_are_searched_whole(spark, rows):
    v = np.random.default_rng(rows).standard_normal((rows, 64))
    data = [(i, x.tolist()) for i, x in enumerate(v)] + [(10_000 + i, [float(i), 1.0, -1.0]) for i in range(0, 100, 10)]
    df = spark.createDataFrame(data, "vec_id bigint, embedding array<double>").repartition(3)
    got = {}
    for r in ann_forest.search(df, lambda i: i % 50 == 0).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append(r.vec_id)
    assert got == nearest(data, 5)


@pytest.mark.parametrize("rows", [300, 600, 1500])
def test_recall_above_the_floor(rows):
    x = np.random.default_rng(7).standard_normal((rows, 64))
    unit = x / np.linalg.norm(x, axis=1)[:, None]
    asked = np.arange(0, rows, 10)
    hits = 0
    for q, c in zip(asked, ann_forest.Forest(x).candidates(x[asked], rows, ann_forest.FLOOR, asked)):
        s = unit @ unit[q]
        s[q] = -2
        assert len(set(c.tolist()) - {q}) >= ann_forest.FLOOR
        hits += len(set(np.argsort(-s)[:5].tolist()) & set(c.tolist()))
    assert hits >= 0.9 * 5 * len(asked)
