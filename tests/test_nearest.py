"""Nearest vectors in blocks against a plain search, with copies and more vectors than all pairs of a table could be scored in time."""

import numpy as np
from pyspark.sql import functions as F

from patternldp.sources import nearest


def test_blocks_equal_a_plain_search(spark, monkeypatch):
    monkeypatch.setattr(nearest, "BLOCK", 16)
    rng = np.random.default_rng(3)
    x = rng.standard_normal((60, 8))
    x[40:50] = x[3]  # ten copies: ties by id
    df = spark.createDataFrame([(i * 3, [float(v) for v in row]) for i, row in enumerate(x)], "vec_id long, embedding array<float>")
    x = x.astype(np.float32).astype(float)
    u = x / np.linalg.norm(x, axis=1)[:, None]
    sim = np.round(u @ u.T, 12)
    want = {(i * 3, j * 3) for i in range(60) for j in sorted((j for j in range(60) if j != i), key=lambda j: (-sim[i, j], j))[:3]}
    assert {tuple(r) for r in nearest.nearest_pairs(df, 3).collect()} == want


def test_many_vectors(spark):
    """4,500 vectors are 20 million pairs; one at a time they took minutes."""
    n = 4500
    df = spark.range(n).select(F.col("id").alias("vec_id"), F.array(*[F.sin(F.col("id") * (d + 1) * 0.37).cast("float") for d in range(16)]).alias("embedding"))
    got = nearest.nearest_pairs(df, 3)
    assert got.count() == 3 * n and got.where("a = b").count() == 0
