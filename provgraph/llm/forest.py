"""Approximate nearest neighbours by a forest of random-projection trees.

The trees' planes come from a bounded sample; every row is filed under its leaf in each tree.  A
query walks all trees through one priority queue, always opening the branch whose planes it is
nearest to, until the leaves opened hold the asked share of rows; rows that stand in enough of the
opened leaves are scored exactly.  Vectors get one more component so that the largest inner product
is the nearest vector.
"""
from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provgraph.functions.ranking import hash_sample

TREES = 64
SAMPLE = 8192
LEAF_SAMPLE = 32
#: Share of the rows whose leaves a query opens, counted in all trees together, and how many of these leaves a row must stand in.
SHARE, VOTES = 10.0, 11
#: Rows, and queries, that meet in one task.
ROW_BLOCK, QUERY_BLOCK = 8192, 2048
#: Queries that walk the trees in one task.
WALKS = 256


class Forest:
    """Planes of complete binary trees: node k of a level splits at the sample's median along a random direction."""

    def __init__(self, sample: np.ndarray, trees: int, leaf: int, seed: int = 7):
        rng = np.random.default_rng(seed)
        self.depth = max(0, int(np.ceil(np.log2(max(1, len(sample)) / leaf))))
        self.trees = []
        for _ in range(trees):
            normals, cuts, parts = [], [], [np.arange(len(sample))]
            for _ in range(self.depth):
                below = []
                for p in parts:
                    a = rng.standard_normal(sample.shape[1])
                    a /= np.linalg.norm(a) or 1
                    x = sample[p] @ a
                    m = float(np.median(x)) if len(x) else 0.0
                    normals.append(a)
                    cuts.append(m)
                    below += [p[x < m], p[x >= m]]
                parts = below
            share = np.array([len(p) for p in parts]) / max(1, len(sample))
            self.trees.append((np.array(normals).reshape(-1, sample.shape[1]), np.array(cuts), share))

    def leaves(self, x: np.ndarray) -> np.ndarray:
        """(rows, trees): the leaf of each row in each tree."""
        out = np.zeros((len(x), len(self.trees)), np.int32)
        for t, (a, c, _) in enumerate(self.trees):
            node = np.zeros(len(x), np.int64)
            for level in range(self.depth):
                at = (1 << level) - 1 + node
                node = node * 2 + (np.einsum("ij,ij->i", x, a[at]) >= c[at])
            out[:, t] = node
        return out

    def open_leaves(self, q: np.ndarray, share: float) -> list[tuple[int, int]]:
        """The (tree, leaf) pairs that one query opens, nearest first, through the queue shared by all trees."""
        side = [a @ q - c for a, c, _ in self.trees]
        queue = [(0.0, t, 0, 0) for t in range(len(self.trees))]
        out, got = [], 0.0
        while queue and got < share:
            far, t, level, node = heapq.heappop(queue)
            while level < self.depth:
                d = side[t][(1 << level) - 1 + node]
                heapq.heappush(queue, (far + d * d, t, level + 1, node * 2 + (d < 0)))
                level, node = level + 1, node * 2 + int(d >= 0)
            out.append((t, node))
            got += self.trees[t][2][node]
        return out


def usable(vectors: DataFrame, id_col: str, vector: str) -> DataFrame:
    """(vec_id, v): rows with an id and a non-zero vector of finite components; doubles."""
    v = F.transform(F.col(vector), lambda x: x.cast("double"))
    fine = F.col(id_col).isNotNull() & F.col(vector).isNotNull() & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0)
    return vectors.where(fine).select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v"))


def _norm2():
    return F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)


def neighbours(vectors: DataFrame, k: int = 20, every: int = 20, *, id_col: str = "vec_id", vector: str = "embedding", trees: int = TREES, share: float = SHARE, votes: int = VOTES, sample: int = SAMPLE, leaf: int = LEAF_SAMPLE) -> DataFrame:
    """(query_id, rank, vec_id, score): each query's ``k`` nearest rows found, ties to the smaller id.

    Queries are the ids divisible by ``every``.  A row counts as found if it is in at least ``votes`` of the
    leaves opened; in a block of rows where fewer than k are, those with most votes stand in.  Rows that are null, zero or not finite take no part;
    vectors of the most common length only can be compared, so others take none either.  Repeated
    rows of one id and vector count once.  Fewer rows than k: all of them.
    """
    rows = usable(vectors, id_col, vector).dropDuplicates(["vec_id", "v"])
    shape = rows.groupBy(F.size("v").alias("d")).agg(F.count(F.lit(1)).alias("n"), F.max(_norm2()).alias("m")).orderBy(F.desc("n"), "d").limit(1).collect()
    if not shape:
        return rows.select(F.col("vec_id").alias("query_id"), F.lit(1).alias("rank"), "vec_id", F.lit(0.0).alias("score"))
    dim, total, most = shape[0]["d"], shape[0]["n"], shape[0]["m"]
    rows = rows.where(F.size("v") == dim)
    drawn = np.array([r["v"] for r in hash_sample(rows, [F.col("vec_id")], sample, total).collect()])
    lifted = lambda x: np.hstack([x, np.sqrt(np.maximum(0, most - (x * x).sum(axis=1)))[:, None]])
    forest = Forest(lifted(drawn), trees, leaf)
    sent = rows.sparkSession.sparkContext.broadcast(forest)  # planes: trees * 2**depth vectors, bounded by the sample
    depth = forest.depth

    def file_rows(batches):
        for pdf in batches:
            x = np.array(pdf["v"].tolist()).reshape(-1, dim)
            yield pd.DataFrame({"vec_id": pdf["vec_id"], "v": pdf["v"], "leaf": list(sent.value.leaves(lifted(x)))})

    def walk(batches):
        for pdf in batches:
            opened = [sent.value.open_leaves(np.append(np.asarray(v), 0.0), share) for v in pdf["v"]]
            yield pd.DataFrame({"query_id": pdf["vec_id"], "v": pdf["v"], "opened": [[(t << depth) + n for t, n in o] for o in opened]})

    row_blocks, query_blocks = -(-total // ROW_BLOCK), -(-total // every // QUERY_BLOCK) + 1
    filed = rows.mapInPandas(file_rows, "vec_id long, v array<double>, leaf array<int>")
    filed = filed.withColumn("rb", F.pmod(F.xxhash64("vec_id"), F.lit(row_blocks)).cast("int")).withColumn("qb", F.explode(F.sequence(F.lit(0), F.lit(query_blocks - 1))))
    walks = -(-total // every // WALKS) + 1
    asked = rows.where(F.col("vec_id") % every == 0).repartition(walks, "vec_id").mapInPandas(walk, "query_id long, v array<double>, opened array<int>")
    asked = asked.withColumn("qb", F.pmod(F.xxhash64("query_id", F.lit(1)), F.lit(query_blocks)).cast("int")).withColumn("rb", F.explode(F.sequence(F.lit(0), F.lit(row_blocks - 1))))

    def search(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(a) and len(b):
            a = a.sort_values("vec_id")
            ids, x, leaf = a["vec_id"].to_numpy(), np.array(a["v"].tolist()), np.array(a["leaf"].tolist())
            # The rows of every (tree, leaf), one after another.
            code = (np.arange(leaf.shape[1]) * (1 << depth) + leaf).ravel()
            row = np.argsort(code, kind="stable")
            start = np.searchsorted(code[row], np.arange(leaf.shape[1] * (1 << depth) + 1))
            row //= leaf.shape[1]
            for qid, v, opened in zip(b["query_id"], b["v"], b["opened"]):
                o = np.asarray(opened, np.int64)
                first, n = start[o], start[o + 1] - start[o]
                at = np.repeat(first - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(int(n.sum()))
                got = np.bincount(row[at], minlength=len(ids))
                got[ids == qid] = 0
                at = np.flatnonzero(got >= votes)
                if len(at) < k:
                    at = np.sort(np.argsort(-got, kind="stable")[:k])
                    at = at[ids[at] != qid]
                s = x[at] @ np.asarray(v)
                if len(at) > k:
                    least = np.partition(s, len(s) - k)[len(s) - k]
                    at, s = at[s >= least], s[s >= least]
                o = np.lexsort((ids[at], -s))[:k]
                out += [(qid, int(i), float(y)) for i, y in zip(ids[at[o]], s[o])]
        return pd.DataFrame(out, columns=["query_id", "vec_id", "score"])

    part = filed.groupBy("rb", "qb").cogroup(asked.groupBy("rb", "qb")).applyInPandas(search, "query_id long, vec_id long, score double")
    ranked = part.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")))
    return ranked.where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def exact(vectors: DataFrame, k: int = 20, every: int = 20) -> DataFrame:
    """The same by brute force, to measure recall with: one leaf, searched whole."""
    return neighbours(vectors, k, every, trees=1, share=2.0, votes=1, leaf=1 << 30)
