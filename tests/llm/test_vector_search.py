"""The sharded search on clustered vectors against brute force, and what the boxes spare."""

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from reclink.llm import kdtree


def test_clusters_against_brute_force(spark):
    rng = np.random.default_rng(6)
    centres = rng.normal(0, 3, (12, 6))
    points = np.concatenate([centres[rng.integers(0, 12, 1500)] + rng.normal(0, 0.1, (1500, 6)), np.tile(centres[0], (900, 1))])
    frame = spark.createDataFrame(pd.DataFrame({"vec_id": np.arange(len(points)), "embedding": points.tolist()}))
    got = kdtree.nearest(frame, F.col("vec_id") % 50 == 0, shard_rows=200, block_rows=8)
    whole = np.floor(256 * points).astype(np.int64)
    want = []
    for q in range(0, len(points), 50):
        scores = whole @ whole[q]
        best = [i for i in np.lexsort([np.arange(len(points)), -scores]).tolist() if i != q][:5]
        want += [(q, r, i, int(scores[i])) for r, i in enumerate(best, 1)]
    assert sorted(tuple(r) for r in got.select("query_id", "rank", "vec_id", "score").collect()) == want


def test_coarse_leaves_split_at_medians():
    points = np.random.default_rng(2).normal(0, 1, (1024, 5))
    coarse = kdtree.Coarse(points, 16)
    assert np.bincount(coarse.leaf(points), minlength=16).tolist() == [64] * 16
    assert kdtree.Coarse(np.zeros((0, 5)), 1).leaf(points).max() == 0


def test_boxes_spare_far_shards():
    query = np.array([[1.0, 0.0]])
    low, high = np.array([[9.0, 0.0], [1.0, 0.0], [5.0, 0.0]]), np.array([[10.0, 1.0], [2.0, 1.0], [6.0, 1.0]])
    row = {"dim": 2, "block": 0, "home": 0, "names": np.array([7]).tobytes(), "q": query.tobytes(), "kth": np.array([6.0]).tobytes(), "shards": np.array([0, 1, 2]).tobytes(), "lows": low.tobytes(), "highs": high.tobytes()}
    out = pd.concat(kdtree._reach([pd.DataFrame([row])]))
    assert out["shard"].tolist() == [2]  # a bound equal to the kth score is looked at, a lower one is not
