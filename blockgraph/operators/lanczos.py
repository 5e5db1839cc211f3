"""Eigensolver on the two-mode engine: Lanczos with selective, full or no re-orthogonalisation; vectors are tables, the tridiagonal
matrix is small.

A step takes one vector, or a block of several side by side, which needs fewer steps over the edges. It is two jobs: one multiplies by the matrix
(a vertex program over the layout) and, while writing, sums up the products with the basis; one subtracts the two last blocks of the basis and
the converged Ritz vectors and sums up what makes the rest orthonormal. Every block is written once; products are taken away
when the step is done. Converged Ritz vectors lie side by side in one table, so a step meets them in one join.
"""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from blockgraph.operators import vectorops as vo
from blockgraph.plans import engine, layout as lay, schemes
from blockgraph.plans.program import VertexProgram
from blockgraph.sources.graphs import Graph
from blockgraph.storage import cut, drop_path, own_path, settings

Kept = tuple[DataFrame, Callable[[], None]]


def keep(df: DataFrame, name: str) -> Kept:
    """df written and read back, and how to take it away."""
    spark, path = df.sparkSession, own_path(df.sparkSession, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), lambda: drop_path(spark, path)


def reverse(g: Graph) -> Graph:
    return Graph(g.name, g.n, g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *(["w"] if g.weighted else [])), g.weighted)


class Matrix:
    """The transposed adjacency matrix of a graph, laid out once: x (id, x) to the product by one iteration of the engine."""

    def __init__(self, g: Graph, beta: int = 8, scheme: str = "two_mode", bucketed: bool | None = None):
        self.n, self.weighted, self.spark = g.n, g.weighted, g.edges.sparkSession
        self.layout = lay.build(g, beta, scheme, bucketed=bucketed)

    def __call__(self, x: DataFrame) -> DataFrame:
        """Every id of x is kept, with zero where nothing comes. To be run under engine.PLAN."""
        return self.several(x, ["x"])

    def several(self, x: DataFrame, names: list[str]) -> DataFrame:
        """The products of several vectors, columns of one table, in one iteration."""
        carried = [F.col("w") * F.col(c) if self.weighted else F.col(c) for c in names]
        prog = VertexProgram({c: F.col(c) for c in names}, carried, ["sum"] * len(names), {c: F.coalesce(f"acc{i}", F.lit(0.0)) for i, c in enumerate(names)})
        values = self.layout.intervals.place(x, "id", "p").select("id", "p", F.lit(0).cast("long").alias("outdeg"), *names)
        return schemes.two_mode(self.layout, values, prog).select("id", *names)

    def drop(self) -> None:
        self.layout.drop()


def product(edges: DataFrame, weighted: bool, n: int | None = None) -> Matrix:
    """The product with the matrix of a symmetric edge table, in one interval."""
    n = n if n is not None else (edges.agg(F.max(F.greatest("src", "dst"))).first()[0] or 0) + 1
    return Matrix(Graph("matrix", n, edges, weighted), 1)


class Result:
    def __init__(self, values: np.ndarray, residuals: np.ndarray, blocks: list[DataFrame], weights: np.ndarray, seconds: list[float]):
        """residuals: bounds. blocks: of the basis (id, x0, x1 ...). weights: of the basis vectors, one column for each value. seconds: of
        each step."""
        self.values, self.residuals, self.blocks, self.weights, self.seconds = values, residuals, blocks, weights, seconds

    @property
    def basis(self) -> list[DataFrame]:
        return [b.select("id", F.col(c).alias("x")) for b in self.blocks for c in b.columns[1:]]

    def vectors(self) -> list[DataFrame]:
        table = self.table()
        return [table.select("id", F.col(f"x{i}").alias("x")) for i in range(len(self.values))]

    def table(self) -> DataFrame:
        """id, x0, x1 ...: all Ritz vectors side by side."""
        return mixture(self.blocks, self.weights)


def _mixed(names: list[str], weights: np.ndarray) -> list:
    """Columns: for each column of weights, the sum of the named ones so weighted."""
    return [sum((float(w) * F.col(c) for c, w in zip(names, column, strict=True)), F.lit(0.0)) for column in weights.T]


def mixture(blocks: list[DataFrame], weights: np.ndarray) -> DataFrame:
    """id, x0, x1 ...: weighted sums of all vectors of the blocks (one row of weights for each), by one union and one grouped sum."""
    out, at, many = None, 0, weights.shape[1]
    for b in blocks:
        names = b.columns[1:]
        part = b.select("id", *(c.alias(f"x{i}") for i, c in enumerate(_mixed(names, weights[at : at + len(names)]))))
        out, at = part if out is None else out.union(part), at + len(names)
    return out.groupBy("id").agg(*(F.sum(f"x{i}").alias(f"x{i}") for i in range(many)))


def _products(left: list[str], right: list[str], tag: str) -> list:
    return [F.sum(F.col(a) * F.col(b)).alias(f"{tag}{i}_{j}") for i, a in enumerate(left) for j, b in enumerate(right)]


def _read(said: dict, size: int, tag: str) -> np.ndarray:
    return np.array([[said[f"{tag}{i}_{j}"] or 0.0 for j in range(size)] for i in range(size)])


def lanczos(apply: Callable[[DataFrame, list[str]], DataFrame], spark, n: int, k: int, steps: int | None = None, reorth: str = "selective", seed: int = 1, largest: str = "magnitude", tol: float | None = None, block: int = 1) -> Result:
    """The k eigenvalues of largest magnitude (or value) of a symmetric matrix, given by its products with named columns of a table.

    tol: go on (to ``steps``, by default n) until the residual bounds of all k are at most tol times their values. block: vectors of a step."""
    size = min(block, n)
    steps = min(n // size, steps or (n if tol else max(2 * k, k + 20)))
    names, old, prior = ([f"{c}{i}" for i in range(size)] for c in ("x", "v", "before"))
    first = vo.random_unit(spark, n, seed).withColumnRenamed("x", "x0")
    for i in range(1, size):
        first = first.join(vo.random_unit(spark, n, seed + 7919 * i).withColumnRenamed("x", f"x{i}"), "id")
    first = cut(first, "basis")
    start = np.linalg.cholesky(_read(first.agg(*_products(names, names, "g")).first().asDict(), size, "g"))
    blocks = [first.select("id", *(c.alias(x) for x, c in zip(names, _mixed(names, np.linalg.inv(start).T), strict=True)))]
    renamed = lambda b, to: b.select("id", *(F.col(x).alias(v) for x, v in zip(names, to, strict=True)))
    t, step_back = np.zeros((0, 0)), np.zeros((size, size))
    seconds: list[float] = []
    good: list[float] = []
    ritz: Kept | None = None  # id, g: the converged vectors as one array
    with settings(spark, **engine.PLAN):
        for j in range(steps):
            began = time.perf_counter()
            watch = Observation()
            pair = apply(blocks[j], names).join(renamed(blocks[j], old), "id").observe(watch, *_products(old, names, "a"))
            rows, drop = keep(pair, "product")
            drops = [drop]
            alpha = _read(watch.get, size, "a")
            alpha = (alpha + alpha.T) / 2
            minus = _mixed(old, alpha)
            if j:
                rows = rows.join(renamed(blocks[j - 1], prior), "id")
                minus = [a + b for a, b in zip(minus, _mixed(prior, step_back.T), strict=True)]
            rows = rows.select("id", *((F.col(x) - m).alias(x) for x, m in zip(names, minus, strict=True)))
            for _ in range(2 if reorth == "full" else 1):
                if reorth == "full":
                    rows, drop = keep(rows, "before-reorth")
                    drops.append(drop)
                    long = None
                    for i, b in enumerate(blocks):
                        one = renamed(b, old).withColumn("i", F.lit(i))
                        long = one if long is None else long.union(one)
                    met = long.join(rows, "id").groupBy("i").agg(*_products(old, names, "d"))
                    dots = {r["i"]: _read(r.asDict(), size, "d") for r in met.collect()}  # a few numbers for each block
                    along = renamed(mixture(blocks, np.vstack([dots[i] for i in range(len(blocks))])), old)
                    rows = rows.join(along, "id").select("id", *((F.col(x) - F.col(v)).alias(x) for x, v in zip(names, old, strict=True)))
                elif reorth == "selective" and ritz is not None:
                    rows, drop = keep(rows.join(ritz[0], "id"), "before-reorth")
                    drops.append(drop)
                    many = len(good)
                    dots = rows.agg(*(F.sum(F.col(x) * F.col("g")[i]) for x in names for i in range(many))).first()
                    rows = rows.select("id", *((F.col(x) - sum((float(dots[c * many + i]) * F.col("g")[i] for i in range(many)), F.lit(0.0))).alias(x) for c, x in enumerate(names)))
            watch = Observation()
            rest, drop_rest = keep(rows.observe(watch, *_products(names, names, "g")), "residual")
            square = _read(watch.get, size, "g")
            for drop in drops:
                drop()
            seconds.append(time.perf_counter() - began)
            t = np.pad(t, (0, size))
            t[-size:, -size:] = alpha
            if j:
                t[-size:, -2 * size : -size], t[-2 * size : -size, -size:] = step_back, step_back.T
            values, s = np.linalg.eigh(t)
            order = np.argsort(-np.abs(values) if largest == "magnitude" else -values)[:k]
            bounds = np.sqrt(np.maximum(np.einsum("ij,ik,kj->j", s[-size:], square, s[-size:]), 0))
            through = np.linalg.eigvalsh(square)[0] <= (1e-10 * max(1.0, np.abs(t).max())) ** 2
            done = tol is not None and len(order) == min(k, n) and (bounds[order] <= tol * np.abs(values[order])).all()
            if through or done or j == steps - 1:
                drop_rest()
                break
            if reorth == "selective":
                limit = np.sqrt(np.finfo(float).eps) * np.abs(values).max()
                new = [i for i in np.flatnonzero(bounds <= limit) if not any(abs(values[i] - v) <= limit for v in good)]
                if new:
                    more = mixture(blocks, s[:, new])
                    ends = [f"x{i}" for i in range(len(new))]
                    length = more.agg(*(F.sqrt(F.sum(F.col(c) * F.col(c))) for c in ends)).first()
                    more = more.select("id", F.array(*(F.col(c) / float(z) for c, z in zip(ends, length, strict=True))).alias("more"))
                    both = more.withColumnRenamed("more", "g") if ritz is None else ritz[0].join(more, "id").select("id", F.concat("g", "more").alias("g"))
                    before, ritz = ritz, keep(both, "ritz")
                    if before is not None:
                        before[1]()
                    good += [float(values[i]) for i in new]
            lower = np.linalg.cholesky(square)
            step_back = lower.T
            blocks.append(rest.select("id", *(c.alias(x) for x, c in zip(names, _mixed(names, np.linalg.inv(lower).T), strict=True))))
    if ritz is not None:
        ritz[1]()
    return Result(values[order], bounds[order], blocks, s[:, order], seconds)


def eigenpairs(g: Graph, k: int, steps: int | None = None, reorth: str = "selective", seed: int = 1, tol: float | None = None, matrix: Matrix | None = None, block: int = 1) -> Result:
    """Eigenpairs of a symmetric graph's adjacency matrix."""
    matrix = matrix or Matrix(g)
    return lanczos(matrix.several, matrix.spark, g.n, k, steps, reorth, seed, tol=tol, block=block)


def residuals(matrix: Matrix, found: Result) -> list[float]:
    """Length of A x - value x over that of value x for every pair found, by one iteration over all vectors."""
    names = [f"x{i}" for i in range(len(found.values))]
    with settings(matrix.spark, **engine.PLAN):
        x, drop = keep(found.table(), "ritz-vectors")
        y = matrix.several(x, names).select("id", *(F.col(c).alias(f"y{c}") for c in names))
        sums = x.join(y, "id").agg(*(F.sqrt(F.sum((F.col(f"y{c}") - float(v) * F.col(c)) ** 2) / F.sum(F.col(c) ** 2)) / abs(float(v)) for c, v in zip(names, found.values, strict=True))).first()
        drop()
    return [float(v) for v in sums]


def svd(g: Graph, k: int, steps: int | None = None, seed: int = 1) -> np.ndarray:
    """The k largest singular values: eigenvalues of A transpose(A), which is never formed."""
    back, forward = Matrix(g), Matrix(reverse(g))

    def apply(x: DataFrame, names: list[str]) -> DataFrame:
        return forward.several(cut(back.several(x, names), "half"), names)

    found = lanczos(apply, back.spark, g.n, k, steps, "full", seed, "value")
    back.drop()
    forward.drop()
    return np.sqrt(np.maximum(found.values, 0))


def power_iteration(g: Graph, iters: int = 20) -> float:
    """The largest eigenvalue of a symmetric matrix by repeated multiplication from equal entries."""
    apply, value = Matrix(g), 0.0
    x, drop = vo.fill(apply.spark, g.n, g.n**-0.5), lambda: None
    with settings(apply.spark, **engine.PLAN):
        for _ in range(iters):
            watch = Observation()
            y = apply(x).join(x.withColumnRenamed("x", "v"), "id").observe(watch, F.sum(F.col("x") * F.col("v")).alias("rq"), F.sum(F.col("x") * F.col("x")).alias("s"))
            y, drop_y = keep(y.select("id", "x"), "power")
            value = watch.get["rq"]
            drop()
            x, drop = vo.scale(1 / np.sqrt(watch.get["s"]), y), drop_y
    drop()
    apply.drop()
    return value


def triangles_spectral(g: Graph, k: int = 10) -> float:
    """A sixth of the sum of the largest eigenvalues' cubes."""
    plain = Graph(g.name, g.n, g.symmetric().edges.where("src <> dst").select("src", "dst"))
    return float((eigenpairs(plain, k).values ** 3).sum() / 6)


def spectral_clusters(g: Graph, k: int, seed: int = 1) -> DataFrame:
    """id, cluster: k-means over the rows of the k top eigenvectors of the symmetric, degree-normalised graph."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    both = g.symmetric()
    d = both.edges.groupBy("src").agg(F.sum("w" if g.weighted else F.lit(1.0)).alias("d"))
    e = both.edges.join(d, "src").join(d.select(F.col("src").alias("dst"), F.col("d").alias("e")), "dst")
    e = e.select("src", "dst", ((F.col("w") if g.weighted else F.lit(1.0)) / F.sqrt(F.col("d") * F.col("e"))).alias("w"))
    wide = None
    for i, v in enumerate(eigenpairs(Graph(g.name, g.n, e, True), k, 3 * k, "full", seed).vectors()):
        v = v.withColumnRenamed("x", f"x{i}")
        wide = v if wide is None else wide.join(v, "id")
    rows = VectorAssembler(inputCols=[f"x{i}" for i in range(k)], outputCol="features").transform(cut(wide, "spectral"))
    return KMeans(k=k, seed=seed).fit(rows).transform(rows).select("id", F.col("prediction").alias("cluster"))
