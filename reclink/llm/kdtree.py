"""Exact top-k search by inner product with a KD-tree per shard.

Vectors are dealt over shards of bounded size: a coarse tree of median splits, fitted to a
bounded sample, puts vectors that are close into one leaf, and a leaf that holds more than a
shard is dealt over several by a hash of vec_id (so equal vectors are no hot shard).  Each
shard is a KD-tree with median splits on the widest dimension (by position, so equal values
split too) and tight bounding boxes.
No point of a box scores more with a query than the sum over the dimensions of the larger
of q*low and q*high, so a best-first traversal opens nodes by falling bound and stops when
the bound is under the query's kth score; equal bounds are opened, for ties.

Queries go in blocks of one leaf.  In a first round each block searches a shard of its leaf;
the kth scores it finds are handed on.  Then the queries are held against the root boxes of
all other shards, and only those whose bound reaches their kth score go to a shard in the
second round.  A tree is sent to as many tasks as the blocks that reach it need.

Components are floor(256 * x).  Scores are whole numbers: 64-bit floats are exact while
they stay under 2**53, Python integers are used beyond (and cut to the range of a long).
Vectors that are null, empty or hold null or non-finite components, and rows without
vec_id, take no part.  A query is compared with vectors of its own length only; rows with
its own vec_id are its own.  Repeated rows are candidates each for itself.  Empty tables
give no rows; further columns are ignored.
"""

from __future__ import annotations

import heapq
import pickle

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reclink.llm._common import bounded, materialise, tidy

SHARD, BLOCK, CHUNK, LEAF = 8192, 512, 8, 64
#: Bytes of the sample that the coarse tree is fitted to; its leaves have this many of the
#: sample's vectors at least, so it has a bounded number of leaves.
SAMPLE_BYTES, LEAF_SAMPLE = 16 << 20, 16
#: Boxes of shards that queries are held against at once; groups of them that are broadcast.
BOXES, BROADCAST_GROUPS = 1024, 16
_LONG = np.iinfo(np.int64)


class KdTree:
    def __init__(self, ids: np.ndarray, points: np.ndarray, leaf: int = LEAF):
        order = np.arange(len(ids))
        low, high, child, span = [], [], [], []
        todo = [(0, len(ids), -1, 0)]
        while todo:
            a, b, parent, side = todo.pop()
            me = len(low)
            if parent >= 0:
                child[parent][side] = me
            own = points[order[a:b]]
            low.append(own.min(axis=0))
            high.append(own.max(axis=0))
            child.append([-1, -1])
            span.append((a, b))
            if b - a > leaf:
                wide = int((high[me] - low[me]).argmax())
                half = (b - a) // 2
                order[a:b] = order[a:b][np.argpartition(own[:, wide], half)]
                todo += [(a, a + half, me, 0), (a + half, b, me, 1)]
        self.ids, self.points = ids[order], points[order]
        self.low, self.high, self.child, self.span = np.array(low), np.array(high), child, span

    def exact(self, queries: np.ndarray) -> bool:
        """Whether all scores are exact in 64-bit floats."""
        return float(np.abs(queries).max(initial=0)) * float(np.abs(self.points).max(initial=0)) * self.points.shape[1] < 2.0**53

    def search(self, names: np.ndarray, queries: np.ndarray, k: int, kth: np.ndarray) -> list[tuple[int, int, int]]:
        """(query, vector, score) of each query's k best; kth: the least score of use."""
        if not self.exact(queries):
            return self._search_all(names, queries, k)
        up, down = np.maximum(queries, 0), np.maximum(-queries, 0)
        bounds = up @ self.high.T - down @ self.low.T
        out = []
        for i, q in enumerate(queries):
            bound, best, least = bounds[i], [], kth[i]
            front = [(-bound[0], 0)]
            while front:
                most, node = heapq.heappop(front)
                if -most < least:
                    break
                left, right = self.child[node]
                if left >= 0:
                    for x in (left, right):
                        if bound[x] >= least:
                            heapq.heappush(front, (-bound[x], x))
                    continue
                a, b = self.span[node]
                scores = self.points[a:b] @ q
                for j in np.flatnonzero((scores >= least) & (self.ids[a:b] != names[i])).tolist():
                    one = (scores[j], -int(self.ids[a + j]))
                    if len(best) < k:
                        heapq.heappush(best, one)
                    elif one > best[0]:
                        heapq.heapreplace(best, one)
                if len(best) == k:
                    least = max(least, best[0][0])
            out += [(int(names[i]), -v, int(s)) for s, v in best]
        return out

    def _search_all(self, names: np.ndarray, queries: np.ndarray, k: int) -> list[tuple[int, int, int]]:
        """For components beyond exact floats: whole numbers, every point."""
        whole = [[int(x) for x in row] for row in self.points]
        out = []
        for name, q in zip(names.tolist(), queries):
            q = [int(x) for x in q]
            found = ((sum(a * b for a, b in zip(q, p)), -int(v)) for p, v in zip(whole, self.ids) if v != name)
            out += [(name, -v, min(max(s, _LONG.min), _LONG.max)) for s, v in heapq.nlargest(k, found)]
        return out


# ---------------------------------------------------------------- Spark
def whole_vectors(rows: DataFrame) -> DataFrame:
    """vec_id, dim and the components floor(256 * x) as packed 64-bit floats."""

    def clean(batches):
        for batch in batches:
            ids, vectors = batch.column(0), batch.column(1)
            flat = vectors.flatten()
            bad = ~np.isfinite(flat.fill_null(float("nan")).to_numpy(zero_copy_only=False))
            sizes = np.where(vectors.is_null().to_numpy(zero_copy_only=False), 0, np.array(vectors.value_lengths().fill_null(0)))
            stops = np.cumsum(sizes)
            seen = np.concatenate([[0], np.cumsum(bad)])
            good = (sizes > 0) & (seen[stops] == seen[stops - sizes]) & ids.is_valid().to_numpy(zero_copy_only=False)
            values = np.floor(256.0 * flat.fill_null(0).to_numpy(zero_copy_only=False)).astype("<f8")
            take = np.flatnonzero(good)
            packed = [values[stops[i] - sizes[i] : stops[i]].tobytes() for i in take.tolist()]
            yield pa.RecordBatch.from_arrays([ids.take(pa.array(take)), pa.array(sizes[take].astype(np.int32)), pa.array(packed, pa.binary())], names=["vec_id", "dim", "v"])

    rows = rows.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"))
    return rows.mapInArrow(tidy(clean), "vec_id long, dim int, v binary")


def _matrix(packed: pd.Series) -> np.ndarray:
    return np.frombuffer(b"".join(packed), "<f8").reshape(len(packed), -1)


class Coarse:
    """Median splits of a sample: the leaf of a vector names its part of the space."""

    def __init__(self, points: np.ndarray, leaves: int):
        self.depth = max(0, min(int(np.ceil(np.log2(max(leaves, 1)))), int(np.log2(max(len(points) // LEAF_SAMPLE, 1)))))
        self.wide, self.cut = np.zeros(1 << self.depth, np.int64), np.full(1 << self.depth, np.inf)
        parts = {1: points}
        for node in range(1, 1 << self.depth):
            own = parts.pop(node)
            if len(own):
                self.wide[node] = w = int((own.max(axis=0) - own.min(axis=0)).argmax())
                self.cut[node] = np.median(own[:, w])
            right = own[:, self.wide[node]] > self.cut[node]
            parts[2 * node], parts[2 * node + 1] = own[~right], own[right]

    def leaf(self, points: np.ndarray) -> np.ndarray:
        node = np.ones(len(points), np.int64)
        for _ in range(self.depth):
            node = 2 * node + (points[np.arange(len(points)), self.wide[node]] > self.cut[node])
        return node - (1 << self.depth)


def fit_coarse(vectors: DataFrame, sizes: dict[int, int], shard_rows: int) -> dict[int, Coarse]:
    """A coarse tree for each length of vectors (given with their counts) from a sample by the
    hash of vec_id."""
    out = {}
    for dim, n in sizes.items():
        share = min(1.0, SAMPLE_BYTES / (8 * dim * n))
        drawn = vectors.where((F.col("dim") == dim) & (F.pmod(F.xxhash64("vec_id", F.lit(9)), F.lit(1 << 30)) < int(share * (1 << 30)) + 1))
        sample = drawn.select("vec_id", "v").toArrow() if n > shard_rows else None
        packed = sorted(sample["v"].to_pylist()) if sample is not None else []
        points = np.frombuffer(b"".join(packed), "<f8").reshape(-1, dim)
        out[dim] = Coarse(points, -(-n // shard_rows))
    return out


def with_leaf(vectors: DataFrame, coarse: dict[int, Coarse]) -> DataFrame:
    def assign(batches):
        for batch in batches:
            dims, leaf = batch.column(1).to_numpy(), np.zeros(batch.num_rows, np.int64)
            for dim in np.unique(dims).tolist():
                at = np.flatnonzero(dims == dim)
                points = np.frombuffer(b"".join(batch.column(2).take(pa.array(at)).to_pylist()), "<f8").reshape(len(at), -1)
                leaf[at] = coarse[dim].leaf(points)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(leaf)], names=["vec_id", "dim", "v", "leaf"])

    return vectors.mapInArrow(tidy(assign), "vec_id long, dim int, v binary, leaf long")


def _plant(rows: pd.DataFrame) -> pd.DataFrame:
    tree = KdTree(rows["vec_id"].to_numpy(), _matrix(rows["v"]))
    return pd.DataFrame({"dim": rows["dim"][:1], "shard": rows["shard"][:1], "tree": [pickle.dumps(tree.__dict__)], "low": [tree.low[0].tobytes()], "high": [tree.high[0].tobytes()]})


def _gather(rows: pd.DataFrame) -> pd.DataFrame:
    rows = rows.sort_values("vec_id", kind="stable")
    return pd.DataFrame({"dim": rows["dim"][:1], "block": rows["block"][:1], "home": rows["home"][:1], "names": [rows["vec_id"].to_numpy().tobytes()], "q": [b"".join(rows["v"])], "kth": [np.full(len(rows), -np.inf).tobytes()]})


def _box(rows: pd.DataFrame) -> pd.DataFrame:
    rows = rows.sort_values("shard", kind="stable")
    return pd.DataFrame({"dim": rows["dim"][:1], "shards": [rows["shard"].to_numpy().tobytes()], "lows": [b"".join(rows["low"])], "highs": [b"".join(rows["high"])]})


def _reach(frames):
    """Of each block, per shard that is not its home, the queries whose bound with the shard's
    box reaches their kth score."""
    for frame in frames:
        for row in frame.itertuples(index=False):
            names, kth = np.frombuffer(row.names, "<i8"), np.frombuffer(row.kth, "<f8")
            queries = np.frombuffer(row.q, "<f8").reshape(len(names), -1)
            shards = np.frombuffer(row.shards, "<i8")
            low, high = (np.frombuffer(x, "<f8").reshape(len(shards), -1) for x in (row.lows, row.highs))
            most = max(np.abs(low).max(initial=0), np.abs(high).max(initial=0)) * np.abs(queries).max(initial=0) * queries.shape[1]
            bound = np.maximum(queries, 0) @ high.T - np.maximum(-queries, 0) @ low.T
            need = (bound >= kth[:, None]) | (most >= 2.0**53)
            out = []
            for j in np.flatnonzero(need.any(axis=0) & (shards != row.home)).tolist():
                at = np.flatnonzero(need[:, j])
                out.append((row.dim, row.block, int(shards[j]), names[at].tobytes(), queries[at].tobytes(), kth[at].tobytes()))
            if out:
                yield pd.DataFrame(out, columns=["dim", "block", "shard", "names", "q", "kth"])


def _meet(k: int):
    def meet(trees: pd.DataFrame, blocks: pd.DataFrame) -> pd.DataFrame:
        out = []
        for raw in trees["tree"] if len(blocks) else []:
            tree = KdTree.__new__(KdTree)
            tree.__dict__.update(pickle.loads(raw))
            for dim, block, names, q, kth in zip(*(blocks[c] for c in ("dim", "block", "names", "q", "kth"))):
                names = np.frombuffer(names, "<i8")
                queries = np.frombuffer(q, "<f8").reshape(len(names), -1)
                out += [(dim, block, *x) for x in tree.search(names, queries, k, np.frombuffer(kth, "<f8"))]
        return pd.DataFrame(out, columns=["dim", "block", "query_id", "vec_id", "score"]).astype({"dim": "int32", "block": "int64", "query_id": "int64", "vec_id": "int64", "score": "int64"})

    return meet


def _raise_kth(k: int):
    """Put the kth score that a block's first shard gave into the block."""

    def put(blocks: pd.DataFrame, found: pd.DataFrame) -> pd.DataFrame:
        if not len(blocks):
            return blocks
        names = np.frombuffer(blocks["names"].iloc[0], "<i8")
        full = found.groupby("query_id")["score"].agg(["size", "min"])
        least = full["min"][full["size"] >= k].reindex(names).to_numpy(float, na_value=-np.inf)
        return blocks.assign(kth=[least.tobytes()])

    return put


def nearest(rows: DataFrame, is_query: Column, k: int = 5, shard_rows: int = SHARD, block_rows: int = BLOCK) -> DataFrame:
    """query_id, rank, vec_id, score of the k best vectors of every query, for rows of
    (vec_id, embedding); equal scores go to the smaller vec_id."""
    vectors = materialise(whole_vectors(rows), "vectors")
    sizes = {r["dim"]: r["count"] for r in vectors.groupBy("dim").count().collect()}
    placed = materialise(with_leaf(vectors, fit_coarse(vectors, sizes, shard_rows)), "placed")
    # shards of a leaf: as many as its rows need; likewise blocks of a leaf's queries
    marked = placed.withColumn("asked", F.coalesce(is_query, F.lit(False)))
    leaves = marked.groupBy("dim", "leaf").agg(F.ceil(F.count(F.lit(1)) / shard_rows).alias("shards"), F.ceil(F.count_if("asked") / block_rows).alias("blocks"))
    known = F.broadcast(leaves)  # at most SAMPLE_BYTES / (8 * dim * LEAF_SAMPLE) leaves a length
    deal = lambda n, seed: F.col("leaf") * F.lit(1 << 32) + F.pmod(F.xxhash64("vec_id", F.lit(seed)), F.col(n))
    marked = marked.join(known, ["dim", "leaf"])
    sharded = marked.withColumn("shard", deal("shards", 1))
    trees = materialise(sharded.groupBy("dim", "shard").applyInPandas(_plant, "dim int, shard long, tree binary, low binary, high binary"), "trees")
    block = "dim int, block long, home long, names binary, q binary, kth binary"
    # a shard that got no row of its leaf is no home
    homes = trees.groupBy("dim", F.floor(F.col("shard") / F.lit(1 << 32)).alias("leaf")).agg(F.min("shard").alias("home"))
    asked = marked.where("asked").join(F.broadcast(homes), ["dim", "leaf"]).withColumn("block", deal("blocks", 2))
    first = materialise(asked.groupBy("dim", "block").applyInPandas(_gather, block), "blocks")
    answer = "dim int, block long, query_id long, vec_id long, score long"
    keys = ["dim", "shard", "chunk"]
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")

    def round_(sent: DataFrame, name: str) -> DataFrame:
        """Answers of the blocks (sent: dim, block, shard, names, q, kth) from their shards."""
        sizes = sent.groupBy("dim", "shard").agg(F.ceil(F.count(F.lit(1)) / CHUNK).alias("chunks"))
        spread = trees.join(sizes, ["dim", "shard"]).withColumn("chunk", F.explode(F.sequence(F.lit(0).cast("long"), F.col("chunks") - 1))).select(*keys, "tree")
        dealt = sent.join(sizes, ["dim", "shard"]).withColumn("chunk", F.pmod(F.xxhash64("block"), F.col("chunks"))).drop("chunks")
        return materialise(spread.groupBy(*keys).cogroup(dealt.groupBy(*keys)).applyInPandas(_meet(k), answer), name)

    one = round_(first.withColumnRenamed("home", "shard"), "answers")
    second = first.groupBy("dim", "block").cogroup(one.groupBy("dim", "block")).applyInPandas(_raise_kth(k), block)
    count = trees.count()
    group = F.pmod(F.xxhash64("shard"), F.lit(-(-count // BOXES) or 1))
    boxes = materialise(trees.withColumn("g", group).groupBy("dim", "g").applyInPandas(_box, "dim int, shards binary, lows binary, highs binary"), "boxes")
    near = materialise(second, "blocks").join(bounded(boxes, BROADCAST_GROUPS), "dim")
    reached = near.mapInPandas(_reach, "dim int, block long, shard long, names binary, q binary, kth binary")
    both = one.unionByName(round_(materialise(reached, "reached"), "answers"))
    return both.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
