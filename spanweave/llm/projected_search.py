"""Largest inner products by stable projections, a kd-tree and a chi-square stopping test.

Rows are first split by norm into bands within which norms differ by at most a half.  In a band whose greatest norm is M,
largest inner products become smallest distances by one more coordinate, sqrt(M^2 - |x|^2) (0 for a query).  Points are
projected to few dimensions by Gaussian directions: for a point at distance d the squared projected distance over d^2 is
chi-square distributed.  A query takes projected neighbours in order of their projected distance and verifies them on the
original vectors, until the chance that a point nearer than its present k-th neighbour still follows, by the chi-square
distribution, is below ``1 - confidence``.

A kd-tree holds the projected points.  Its top is fitted, band by band, on a bounded sample of rows (``SAMPLE``) and cuts
space into cells, one task's work each; all rows are indexed.  A query first searches its cell in the band of the greatest
norms; with the k-th product found there it goes to the cells which neither the test nor the bound |q| M excludes, and in a
cell to the leaves which the test does not exclude.  Equal vectors are one point that keeps its k + 1 smallest ids, gathered in
each task before the shuffle, so copies do not meet in one place.  ``verified`` tells how many distinct points a query's
answer took.

Defined results: vectors that are null, zero, or hold null or non-finite components take no part; nor do rows with a null
id.  Shorter vectors count as continued by zeros.  Rows with an equal id are never each other's neighbours, and each distinct
vector of an id that is a query has a list of its own.  Ties go to the smaller id.  With fewer than k candidates all are
returned.  Extra columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .native import let
from .shared import settle

DIMS, SAMPLE, CELL_ROWS, LEAST_CELLS, LEAF = 32, 8192, 16_384, 8, 64
#: Measured on the given vectors, which are spread evenly over a sphere in 64 dimensions: recall 0.92 to 0.95, a third to a half of the points verified.
CONFIDENCE = 0.7


def chi_square_below(x: np.ndarray, dims: int = DIMS) -> np.ndarray:
    """Distribution function for an even number of dimensions: one less a Poisson tail."""
    half, term, total = np.minimum(x, 1e3) / 2, 1.0, 1.0
    for k in range(1, dims // 2):
        term = term * half / k
        total = total + term
    return 1 - np.exp(-half) * total


def chi_square_limit(confidence: float, dims: int = DIMS) -> float:
    """The value that the distribution function reaches ``confidence`` at."""
    low, high = 0.0, 1e3
    for _ in range(80):
        middle = (low + high) / 2
        low, high = (middle, high) if chi_square_below(np.array(middle), dims) < confidence else (low, middle)
    return high


def directions(width: int) -> np.ndarray:
    return np.random.default_rng(5).standard_normal((width + 1, DIMS))


def lifted(vectors: np.ndarray, top: np.ndarray) -> np.ndarray:
    """With the coordinate that makes each norm the given one."""
    return np.hstack([vectors, np.sqrt(np.maximum(top * top - (vectors * vectors).sum(axis=1), 0))[:, None]])


class Splits:
    """Top of the kd-tree of one band: a complete binary tree of median cuts, in an array as a heap."""

    def __init__(self, sample: np.ndarray, depth: int) -> None:
        self.depth, inner = depth, (1 << depth) - 1
        self.axis, self.at = np.zeros(inner, dtype=np.int64), np.zeros(inner)
        groups = {0: sample}
        for node in range(inner):
            points = groups.pop(node)
            axis = int(np.argmax(points.var(axis=0))) if len(points) else node % DIMS
            cut = float(np.median(points[:, axis])) if len(points) else 0.0
            self.axis[node], self.at[node] = axis, cut
            right = points[:, axis] > cut if len(points) else np.zeros(0, dtype=bool)
            groups[2 * node + 1], groups[2 * node + 2] = points[~right], points[right]

    def cell(self, points: np.ndarray) -> np.ndarray:
        node = np.zeros(len(points), dtype=np.int64)
        for _ in range(self.depth):
            node = 2 * node + 1 + (points[np.arange(len(points)), self.axis[node]] > self.at[node])
        return node - len(self.axis)

    def bounds(self, points: np.ndarray) -> np.ndarray:
        """Row q, column c: squared projected distance from point q to cell c, at least."""
        off = np.zeros((len(points), 1, DIMS))
        for level in range(self.depth):
            nodes = np.arange((1 << level) - 1, (2 << level) - 1)
            gap = points[:, self.axis[nodes]] - self.at[nodes]
            left, right = off.copy(), off.copy()
            k = np.arange(len(nodes))
            left[:, k, self.axis[nodes]] = np.maximum(left[:, k, self.axis[nodes]], gap)
            right[:, k, self.axis[nodes]] = np.maximum(right[:, k, self.axis[nodes]], -gap)
            off = np.stack([left, right], axis=2).reshape(len(points), 2 * len(nodes), DIMS)
        return (off * off).sum(axis=2)


class Cell:
    """The points of a cell, in the order of the leaves of its kd-tree, with the leaves' bounding boxes."""

    def __init__(self, vectors: np.ndarray, ids: list, top: float, axes: np.ndarray) -> None:
        projected = lifted(vectors, np.float64(top)) @ axes
        parts, done = [np.arange(len(vectors))], []
        while parts:
            p = parts.pop()
            if len(p) <= LEAF:
                done.append(p)
                continue
            order = p[np.argsort(projected[p, int(np.argmax(projected[p].var(axis=0)))], kind="stable")]
            parts += [order[: len(p) // 2], order[len(p) // 2 :]]
        order = np.concatenate(done)
        self.top, self.vectors, self.projected, self.ids = top, vectors[order], projected[order], [list(ids[k]) for k in order]
        self.square = (self.projected * self.projected).sum(axis=1)
        starts = np.cumsum([0, *(len(p) for p in done[:-1])])
        self.sizes = np.array([len(p) for p in done])
        self.low, self.high = np.minimum.reduceat(self.projected, starts), np.maximum.reduceat(self.projected, starts)

    def search(self, queries: np.ndarray, projected: np.ndarray, who: list[int], known: np.ndarray, k: int, limit: float) -> Iterator[tuple[int, int, float, int]]:
        """(query, id, product, points verified): the k best that the test leaves for each query; ``known`` holds k-th products found elsewhere."""
        for at in range(0, len(queries), 64):
            p = projected[at : at + 64]
            distances = np.maximum(self.square[None, :] - 2 * p @ self.projected.T + (p * p).sum(axis=1)[:, None], 0)
            for n in range(len(p)):
                yield from self._one(at + n, queries[at + n], p[n], distances[n], who[at + n], float(known[at + n]), k, limit)

    def _one(self, number: int, query: np.ndarray, projected: np.ndarray, distances: np.ndarray, own: int, known: float, k: int, limit: float) -> Iterator[tuple[int, int, float, int]]:
        both = float(query @ query) + self.top * self.top
        slack = 1e-12 * both
        reach = lambda worst: limit * (max(both - 2 * worst, 0) + slack) if worst > -math.inf else math.inf
        worst = known
        if worst > -math.inf:
            box = np.maximum(np.maximum(self.low - projected, projected - self.high), 0)
            near = np.repeat((box * box).sum(axis=1) <= reach(worst), self.sizes)
            order = np.flatnonzero(near)
            order = order[distances[order] <= reach(worst)]
        else:
            order = np.arange(len(distances))
        order = order[np.argsort(distances[order], kind="stable")]
        scores, at, step = np.empty(0), 0, 4 * (k + 1)
        while at < len(order) and distances[order[at]] <= reach(worst):
            some = order[at : at + step]
            scores = np.concatenate([scores, self.vectors[some] @ query])
            at, step = at + len(some), step * 2
            if len(scores) > k:  # one of them may be the query itself
                worst = max(worst, float(np.partition(scores, len(scores) - k - 1)[len(scores) - k - 1]))
        if not at:
            return
        found = []
        for j in order[:at][scores >= max(known, np.partition(scores, len(scores) - k - 1)[len(scores) - k - 1] if len(scores) > k else -math.inf) - slack]:
            exact = math.fsum((self.vectors[j] * query).tolist())
            found += [(i, exact) for i in self.ids[j] if i != own]
        best = sorted(found, key=lambda x: (-x[1], x[0]))[:k]
        for n, (i, exact) in enumerate(best or [(None, None)]):  # a search without a find still counts
            yield number, i, exact, 0 if n else at


def usable(vector: Column) -> Column:
    fine = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return F.coalesce(fine & F.exists(vector, lambda x: x != 0), F.lit(False))


#: ``which`` is a hash of the query's vector, which tells the lists of one id apart.
FOUND = "query_id bigint, which bigint, vec_id bigint, score double, verified bigint"


def nearest(rows: DataFrame, is_query: Column, *, vec_id: str = "vec_id", vector: str = "embedding", k: int = 20, confidence: float = CONFIDENCE) -> DataFrame:
    """(query_id, rank, vec_id, score, verified) for the rows that ``is_query`` selects, against all rows."""
    spark = rows.sparkSession
    fine = rows.select(F.col(vec_id).cast("bigint").alias("vec_id"), F.col(vector).cast("array<double>").alias("v"), is_query.alias("q")).where(F.col("vec_id").isNotNull()).where(usable(F.col("v")))
    largest = F.array_max(F.transform("v", lambda x: F.abs(x)))  # squares of its shares neither vanish nor overflow
    fine = fine.withColumn("norm", let(largest, lambda m: m * F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + (x / m) * (x / m)))))
    fine = fine.withColumn("band", F.floor(F.log2("norm") / math.log2(1.5)).cast("int"))
    # One row a band, of which there are at most some two thousand for numbers of double precision.
    bands = {r["band"]: r for r in fine.groupBy("band").agg(F.count("*").alias("n"), F.max("norm").alias("top"), F.max(F.size("v")).alias("width")).collect()}
    if not bands:
        return spark.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score double, verified bigint")
    width, total = max(r["width"] for r in bands.values()), sum(r["n"] for r in bands.values())
    padded = F.concat("v", F.array_repeat(F.lit(0.0), F.lit(width) - F.size("v")))
    fine = fine.withColumn("v", padded)

    def merge_ids(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: dict[tuple[int, bytes], list[int]] = {}

        def out() -> pd.DataFrame:
            return pd.DataFrame({"band": [b for b, _ in held], "raw": [r for _, r in held], "ids": [sorted(x)[: k + 1] for x in held.values()]})

        for f in frames:
            for i, v, band in zip(f["vec_id"], f["v"], f["band"], strict=True):
                ids = held.setdefault((band, (np.asarray(v, dtype="<f8") + 0.0).tobytes()), [])
                if i not in ids:
                    ids.append(i)
                    if len(ids) > 8 * k:
                        ids[:] = sorted(ids)[: k + 1]
            if len(held) >= 20_000:
                yield out()
                held = {}
        if held:
            yield out()

    near = fine.select("vec_id", "v", "band").mapInPandas(merge_ids, "band int, raw binary, ids array<bigint>")
    points = settle(near.groupBy("band", "raw").agg(F.slice(F.array_sort(F.array_distinct(F.flatten(F.collect_list("ids")))), 1, k + 1).alias("ids")))

    axes, limit = directions(width), chi_square_limit(confidence)
    few = points.select("band", "raw").orderBy(F.xxhash64("raw")).limit(SAMPLE).toPandas()
    unpack = lambda raw: np.frombuffer(b"".join(raw), dtype="<f8").reshape(-1, width)
    tops = {b: float(r["top"]) * (1 + 1e-12) for b, r in bands.items()}
    splits, first, cells = {}, {}, 0
    least = int(math.log2(LEAST_CELLS))
    for b in sorted(bands):
        some = few.loc[few["band"] == b, "raw"]
        depth = max(math.ceil(math.log2(max(bands[b]["n"] / CELL_ROWS, 1))), least if 2 * bands[b]["n"] >= total else 0)
        splits[b] = Splits(lifted(unpack(some), np.float64(tops[b])) @ axes if len(some) else np.zeros((0, DIMS)), depth)
        first[b], cells = cells, cells + (1 << depth)
    main = max(bands)  # of the greatest norms, where a query begins

    def place(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            for b, g in f.groupby("band"):
                yield g.assign(cell=first[b] + splits[b].cell(lifted(unpack(g["raw"]), np.float64(tops[b])) @ axes))

    def project(raw: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        q = unpack(raw)
        return q, q @ axes[:-1]

    def at_home(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            if len(f):
                raw = [(np.asarray(v, dtype="<f8") + 0.0).tobytes() for v in f["v"]]
                yield pd.DataFrame({"cell": first[main] + splits[main].cell(project(raw)[1]), "query_id": f["vec_id"], "raw": raw, "known": -math.inf})

    placed = settle(points.mapInPandas(place, "band int, raw binary, ids array<bigint>, cell bigint"))
    asked = fine.where("q").select("vec_id", "v").mapInPandas(at_home, "cell bigint, query_id bigint, raw binary, known double")
    queries = settle(asked.withColumn("which", F.xxhash64("raw")).dropDuplicates(["query_id", "which"]))

    def search(pts: pd.DataFrame, qs: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(pts) and len(qs):
            cell = Cell(unpack(pts["raw"]), list(pts["ids"]), tops[int(pts["band"].iloc[0])], axes)
            q, p = project(list(qs["raw"]))
            who, which = qs["query_id"].tolist(), qs["which"].tolist()
            out = [(who[n], which[n], i, s, v) for n, i, s, v in cell.search(q, p, who, qs["known"].to_numpy(), k, limit)]
        frame = pd.DataFrame(out, columns=["query_id", "which", "vec_id", "score", "verified"])
        return frame.assign(vec_id=frame["vec_id"].astype("Int64"), score=frame["score"].astype(float))

    by_cell = placed.groupBy("cell")
    home = settle(by_cell.cogroup(queries.groupBy("cell")).applyInPandas(search, FOUND))
    best = Window.partitionBy("query_id", "which").orderBy(F.desc("score"), "vec_id")
    limits = home.where("vec_id is not null").withColumn("rank", F.row_number().over(best)).where(F.col("rank") == k).select("query_id", "which", F.col("score").alias("limit"))

    def elsewhere(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            for at in range(0, len(f), 1024):
                g = f.iloc[at : at + 1024]
                q, p = project(list(g["raw"]))
                worst = g["limit"].fillna(-math.inf).to_numpy()
                own = (q * q).sum(axis=1)
                for b, top in tops.items():
                    square = own + top * top - 2 * np.where(np.isfinite(worst), worst, 0)
                    passed = splits[b].bounds(p) > limit * (np.maximum(square, 0) + 1e-12 * (own + top * top))[:, None]
                    passed |= (worst > np.sqrt(own) * top * (1 + 1e-9))[:, None]
                    go = ~(passed & np.isfinite(worst)[:, None])
                    if b == main:
                        go[np.arange(len(g)), g["cell"] - first[b]] = False
                    n, cell = np.nonzero(go)
                    if len(n):
                        yield pd.DataFrame({"cell": first[b] + cell, "query_id": g["query_id"].to_numpy()[n], "which": g["which"].to_numpy()[n], "raw": g["raw"].to_numpy()[n], "known": worst[n]})

    travelling = queries.join(limits, ["query_id", "which"], "left").select("cell", "query_id", "which", "raw", "limit").mapInPandas(elsewhere, "cell bigint, query_id bigint, which bigint, raw binary, known double")
    both = home.unionByName(by_cell.cogroup(travelling.groupBy("cell")).applyInPandas(search, FOUND))
    one = both.groupBy("query_id", "which", "vec_id").agg(F.max("score").alias("score"), F.sum("verified").alias("verified"))
    effort = F.sum("verified").over(Window.partitionBy("query_id", "which"))
    ranked = one.withColumn("verified", effort).where("vec_id is not null").withColumn("rank", F.row_number().over(best))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score", "verified")
