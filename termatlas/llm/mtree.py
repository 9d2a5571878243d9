"""Exact top-k inner products by M-tree best-first search (operator 7).

Vectors become integers, floor(64 x). With M at least every vector's norm, x gets one more
coordinate, the root of M**2 - |x|**2, and a query gets 0: then the squared distance is
|q|**2 + M**2 - 2 q.x, a metric whose nearest rows are those of the largest inner product.

Rows are dealt by their nearest of a bounded sample of PIVOTS rows, and by number within a
pivot with many rows (whatever their ids and values), into shards of about SHARD rows. A shard is a tree of pages of at most
PAGE entries: leaves keep rows with their distance to the page's routing object, inner
pages keep routing objects with covering radii and the distance to their parent. It is
packed as one binary value. Queries travel in blocks of BLOCK; each block meets each
shard once, block by block. A search goes down the pages in order of their least possible
distance and stops at the first page beyond the k-th best; stored parent distances
exclude entries by the triangle inequality before their distance is computed. A sample's
exact scores give each query a first bound for its k-th best. Scores that decide are integers.

Vectors that are null or have null or non-finite components, or another length than the
most common one, take no part, as query or candidate. Equal scores go to the smaller
vec_id. Rows that share a vec_id are candidates of their own, but none for their own id.
"""

from __future__ import annotations

import heapq
import io
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from termatlas.functions.scratch import materialize

SCALE, PIVOTS, SHARD, PAGE, BLOCK = 64, 256, 2048, 256, 1024


def integers(vector: Column) -> Column:
    return F.transform(vector, lambda x: F.floor(x.cast("double") * SCALE))


def usable(vector: Column) -> Column:
    finite = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x.cast("double")) < float("inf")))
    return vector.isNotNull() & (F.size(vector) > 0) & F.coalesce(finite, F.lit(False))


def lifted(x: np.ndarray, most: float) -> np.ndarray:
    x = x.astype(float)
    return np.hstack([x, np.sqrt(np.maximum(most**2 - (x**2).sum(axis=1, keepdims=True), 0))])


def scores(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Exact integer inner products of rows x with q."""
    if x.shape[1] * float(np.abs(x).max(initial=0)) * float(np.abs(q).max(initial=0)) < 2**52:
        return (x.astype(float) @ q.astype(float)).astype(np.int64)
    return x @ q


class Tree:
    """Pages of a shard. Level 0 are the leaves; pages of level n hold routing objects of pages of level n - 1."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray, most: float):
        self.most = most
        leaves = self._groups(lifted(rows, most))
        order = np.concatenate(leaves)  # the rows of a leaf lie together
        self.ids, self.rows, ends = ids[order], rows[order], np.cumsum([len(g) for g in leaves])
        self._lift()
        entries, self.levels = self.points, []
        reach = np.zeros(len(entries))
        while True:
            groups = np.split(np.arange(len(rows)), ends[:-1]) if entries is self.points else self._groups(entries)
            routes = np.array([self._middle(entries[g]) for g in groups])
            to_parent = [np.sqrt(((entries[g] - r) ** 2).sum(axis=1)) for g, r in zip(groups, routes, strict=True)]
            radii = np.array([float((d + reach[g]).max()) for d, g in zip(to_parent, groups, strict=True)])
            self.levels.append({"pages": groups, "to_parent": to_parent, "entries": entries, "reach": reach, "routes": routes, "radii": radii})
            if len(groups) == 1:
                return
            entries, reach = routes, radii

    def _lift(self) -> None:
        self.points, self.exact = lifted(self.rows, self.most), self.rows.shape[1] * float(np.abs(self.rows).max(initial=0))

    @staticmethod
    def _middle(x: np.ndarray) -> np.ndarray:
        return x[np.argmin(((x - x.mean(axis=0)) ** 2).sum(axis=1))]

    @staticmethod
    def _groups(x: np.ndarray) -> list[np.ndarray]:
        """Pages of at most PAGE entries, by halving along the line of two far entries."""
        todo, out = [np.arange(len(x))], []
        while todo:
            g = todo.pop()
            if len(g) <= PAGE:
                out.append(g)
                continue
            y = x[g]
            a = y[np.argmax(((y - y[0]) ** 2).sum(axis=1))]
            b = y[np.argmax(((y - a) ** 2).sum(axis=1))]
            order = np.argsort(y @ (b - a), kind="stable")
            todo += [g[order[: len(g) // 2]], g[order[len(g) // 2 :]]]
        return out

    def search(self, query_id: int, q: np.ndarray, k: int, floor_score: float) -> tuple[list[tuple[int, int]], int]:
        """The k best (score, id) of at least floor_score, best first, and the number of distances computed."""
        own, point = float((q.astype(float) ** 2).sum()), np.append(q.astype(float), 0.0)
        far = lambda score: np.sqrt(max(own + self.most**2 - 2 * score, 0.0)) * (1 + 1e-9) + 1e-6
        limit = far(floor_score) if floor_score > -np.inf else np.inf
        bar = floor_score
        score, ids = np.empty(0, np.int64), np.empty(0, np.int64)
        top = len(self.levels) - 1
        first = float(np.sqrt(((self.levels[top]["routes"][0] - point) ** 2).sum()))
        queue, computed, tie = [(max(first - self.levels[top]["radii"][0], 0.0), 0, top, 0, first)], 1, 1
        while queue:
            least, _, level, page, d_parent = heapq.heappop(queue)
            if least > limit:
                break
            at = self.levels[level]
            members = at["pages"][page]
            # |d(q, parent) - d(x, parent)| bounds d(q, x) from below without computing it
            near = np.abs(d_parent - at["to_parent"][page]) - at["reach"][members] <= limit
            if not near.all():
                members = members[near]
                if not len(members):
                    continue
            computed += len(members)
            if level:
                d = np.sqrt(((at["entries"][members] - point) ** 2).sum(axis=1))
                bound = np.maximum(d - at["reach"][members], 0.0)
                for m, dist, low in zip(members.tolist(), d.tolist(), bound.tolist(), strict=True):
                    if low <= limit:
                        heapq.heappush(queue, (low, tie, level - 1, m, dist))
                        tie += 1
                continue
            got = self.scores(members, q)
            fits = (got >= bar) & (self.ids[members] != query_id)
            score, ids = np.append(score, got[fits]), np.append(ids, self.ids[members][fits])
            if len(score) > k:
                best = np.lexsort((ids, -score))[:k]
                score, ids = score[best], ids[best]
            if len(score) == k and score.min() > bar:
                bar = int(score.min())
                limit = min(limit, far(bar))
        best = np.lexsort((ids, -score))
        return list(zip(score[best].tolist(), ids[best].tolist(), strict=True)), computed

    def scores(self, members: np.ndarray, q: np.ndarray) -> np.ndarray:
        if len(members) == members[-1] - members[0] + 1:  # ascending, so a whole page
            members = slice(members[0], members[-1] + 1)
        if self.exact * float(np.abs(q).max(initial=0)) < 2**52:
            return (self.points[members, :-1] @ q.astype(float)).astype(np.int64)
        return self.rows[members] @ q

    def pack(self) -> bytes:
        out = io.BytesIO()
        parts = {"ids": self.ids, "rows": self.rows.astype(np.int64), "most": np.array(self.most), "levels": np.array(len(self.levels))}
        for n, x in enumerate(self.levels):
            sizes = np.array([len(g) for g in x["pages"]])
            parts |= {f"s{n}": sizes, f"g{n}": np.concatenate(x["pages"]).astype(np.int32), f"t{n}": np.concatenate(x["to_parent"]), f"o{n}": x["routes"], f"r{n}": x["radii"]}
        np.savez(out, **parts)
        return out.getvalue()

    @classmethod
    def unpack(cls, packed: bytes) -> Tree:
        with np.load(io.BytesIO(packed)) as z:
            tree = cls.__new__(cls)
            tree.ids, tree.rows, tree.most = z["ids"], z["rows"], float(z["most"])
            tree._lift()
            tree.levels, entries, reach = [], tree.points, np.zeros(len(tree.ids))
            for n in range(int(z["levels"])):
                cuts = np.cumsum(z[f"s{n}"])[:-1]
                level = {"pages": np.split(z[f"g{n}"], cuts), "to_parent": np.split(z[f"t{n}"], cuts), "entries": entries, "reach": reach, "routes": z[f"o{n}"], "radii": z[f"r{n}"]}
                tree.levels.append(level)
                entries, reach = level["routes"], level["radii"]
        return tree


def build(rows: DataFrame, most: float) -> DataFrame:
    """shard, tree (binary) of rows (id, x)."""
    pick = rows.orderBy(F.xxhash64("id"), "id").limit(PIVOTS).select("x").collect()
    pivots = lifted(np.array([r.x for r in pick], np.int64), most)

    @F.pandas_udf("int")
    def nearest(x: pd.Series) -> pd.Series:
        y = lifted(np.stack(x.to_numpy()), most) if len(x) else np.empty((0, pivots.shape[1]))
        return pd.Series(((pivots**2).sum(axis=1) - 2 * y @ pivots.T).argmin(axis=1).astype(np.int32))

    near = materialize(rows.withColumn("pivot", nearest("x")).withColumn("number", F.monotonically_increasing_id()), "routed")
    # neighbouring pivots are gathered up to SHARD rows, a pivot with more is split by a hash
    size = near.groupBy("pivot").agg(F.count("*").alias("n"))
    before = F.sum("n").over(Window.orderBy("pivot").rowsBetween(Window.unboundedPreceding, -1))
    plan = size.select("pivot", F.ceil(F.col("n") / SHARD).alias("parts"), F.floor(F.coalesce(before, F.lit(0)) / SHARD).alias("base"), (F.col("n") > SHARD).alias("split"))
    placed = near.join(F.broadcast(plan), "pivot").withColumn("shard", F.when(F.col("split"), F.concat_ws("-", F.lit("p"), "pivot", F.pmod(F.xxhash64("number", F.lit(1)), F.col("parts")))).otherwise(F.concat_ws("-", F.lit("b"), "base")))

    def tree(shard: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(shard.x.to_numpy()).astype(np.int64)
        return pd.DataFrame({"shard": [shard["shard"].iloc[0]], "tree": [Tree(shard.id.to_numpy(), x, most).pack()]})

    return placed.select("shard", "id", "x").groupBy("shard").applyInPandas(tree, "shard string, tree binary")


def top_inner_products(vectors: DataFrame, k: int = 20, every: int = 20, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the k best other rows of each row whose key is divisible by `every`."""
    schema = "query_id long, rank int, vec_id long, score long"
    rows = vectors.where(F.col(key).isNotNull() & usable(F.col(vector))).select(F.col(key).cast("long").alias("id"), integers(F.col(vector)).alias("x"))
    sizes = rows.groupBy(F.size("x").alias("size")).agg(F.count("*").alias("n"), F.max(F.aggregate("x", F.lit(0.0), lambda s, v: s + v.cast("double") * v)).alias("most"))
    common = sizes.orderBy(F.desc("n"), "size").first()
    if common is None:
        return vectors.sparkSession.createDataFrame([], schema)
    rows, most = rows.where(F.size("x") == common["size"]), float(np.sqrt(common["most"])) * (1 + 1e-12) + 1e-9
    trees = materialize(build(rows, most), "trees")
    known = rows.orderBy(F.xxhash64("id"), "id").limit(4 * PIVOTS).collect()
    sample_ids, sample = np.array([r.id for r in known]), np.array([r.x for r in known], np.int64)
    queries = rows.where(F.pmod("id", F.lit(every)) == 0)
    blocks = F.greatest(F.lit(1), F.ceil(F.count("*") / BLOCK)).cast("long")
    n_blocks = queries.agg(blocks).first()[0]

    def pack(block: pd.DataFrame) -> pd.DataFrame:
        ids, x = block.id.to_numpy(), np.stack(block.x.to_numpy()).astype(np.int64)
        floors = []
        for i, q in zip(ids, x, strict=True):
            got = scores(sample, q)[sample_ids != i]
            floors.append(float(np.partition(got, -k)[-k]) if len(got) >= k else -np.inf)
        out = io.BytesIO()
        np.savez(out, ids=ids, x=x, floors=np.array(floors))
        return pd.DataFrame({"block": [int(block.block.iloc[0])], "queries": [out.getvalue()]})

    asked = queries.withColumn("block", F.pmod(F.xxhash64("id", F.lit(2)), F.lit(n_blocks))).groupBy("block").applyInPandas(pack, "block long, queries binary")
    shards = trees.select("shard")
    n = shards.count()
    # every block visits every shard: the shards' numbers are dealt to the blocks and joined by number
    numbered = _numbered(trees)
    visits = asked.withColumn("number", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).join(numbered, "number").select("number", "queries", "tree")

    def search(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        number = tree = None
        for frame in frames:
            for row in frame.itertuples(index=False):
                if row.number != number:
                    number, tree = row.number, Tree.unpack(row.tree)
                with np.load(io.BytesIO(row.queries)) as z:
                    ids, x, floors = z["ids"], z["x"], z["floors"]
                found = [(i, v, s) for i, q, f in zip(ids.tolist(), x, floors, strict=True) for s, v in tree.search(i, q, k, f)[0]]
                yield pd.DataFrame(found, columns=["query_id", "vec_id", "score"]).astype("int64")

    found = visits.mapInPandas(search, "query_id long, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _numbered(trees: DataFrame) -> DataFrame:
    """trees with number 0, 1, ... in the order of shards; only names are sorted."""
    names = trees.select("shard").withColumn("number", F.row_number().over(Window.orderBy("shard")) - 1)
    return trees.join(names, "shard").select("number", "tree")
