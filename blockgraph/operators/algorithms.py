"""Algorithms on the programming model: each is a VertexProgram and a call of the engine, unless it says otherwise."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blockgraph.operators.components import components, forest
from blockgraph.operators.triangles import triangles  # noqa: F401  (one of the algorithms)
from blockgraph.plans import engine
from blockgraph.plans.program import VertexProgram
from blockgraph.sources.graphs import Graph
from blockgraph.storage import cut

FOLD_ROWS = 500_000

_or = lambda a, b: F.coalesce(F.col(a), F.lit(b))


def pagerank_program(n: int, damping: float = 0.85, start: float | None = None, normalized: bool = False, extra: float = 0.0, tol: float = 0.0) -> VertexProgram:
    base = (1 - damping) / (n if normalized else 1)
    first = start if start is not None else (1 / n if normalized else 1.0)
    return VertexProgram(
        {"rank": F.lit(float(first))}, [F.col("rank") / F.col("outdeg")], ["sum"], {"rank": F.lit(base + extra) + damping * _or("acc0", 0.0)}, F.abs(F.col("rank") - F.col("old_rank")) > tol, needs_degree=True
    )


def pagerank(g: Graph, iters: int = 10, damping: float = 0.85, start: float | None = None, normalized: bool = False, dangling: bool = False, tol: float | None = None, **options) -> engine.Run:
    """Un-normalised by default (teleport 1 - damping, dangling mass lost). dangling: that mass is spread over all vertices."""

    def after(values: DataFrame, _prog: VertexProgram) -> VertexProgram:
        lost = values.where("outdeg = 0").agg(F.coalesce(F.sum("rank"), F.lit(0.0))).first()[0]
        return pagerank_program(g.n, damping, start, normalized, damping * lost / g.n, tol or 0.0)

    prog = pagerank_program(g.n, damping, start, normalized, tol=tol or 0.0)
    return engine.run(g, prog, iters, stop_when_stable=tol is not None, after=after if dangling else None, **options)


def rwr(g: Graph, seeds: Column, restart: float = 0.15, iters: int = 10, **options) -> engine.Run:
    """Random walk with restart: as PageRank, but only the seeds (a predicate over id) are jumped to."""
    flag = F.when(seeds, 1.0).otherwise(0.0)
    prog = VertexProgram({"score": flag, "seed": flag}, [F.col("score") / F.col("outdeg")], ["sum"], {"score": restart * F.col("seed") + (1 - restart) * _or("acc0", 0.0), "seed": F.col("seed")}, needs_degree=True)
    return engine.run(g, prog, iters, **options)


def spmv_program(weighted: bool, x: Column) -> VertexProgram:
    return VertexProgram({"x": x}, [F.col("w") * F.col("x") if weighted else F.col("x")], ["sum"], {"x": _or("acc0", 0.0)})


def spmv(g: Graph, x: Column, transpose: bool = True, **options) -> DataFrame:
    """id, y: y = transpose(A) x, or A x; x is a Column over id."""
    if not transpose:
        g = Graph(g.name, g.n, g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *(["w"] if g.weighted else [])), g.weighted)
    return engine.run(g, spmv_program(g.weighted, x), 1, **options).values.withColumnRenamed("x", "y")


def wcc_program() -> VertexProgram:
    return VertexProgram({"label": F.col("id")}, [F.col("label")], ["min"], {"label": F.least("label", "acc0")}, F.col("label") != F.col("old_label"))


def fits(n: int, phi: int, memory: float) -> bool:
    return phi * n <= memory


def wcc(g: Graph, method: str = "auto", max_iter: int = 10_000, memory: float = 2**30, **options) -> DataFrame:
    """id, label (the component's smallest id). auto: union-find where all vertices fit the memory, else iterative."""
    if method == "auto":
        method = "unionfind" if fits(g.n, 16, memory) else "iterative"
    if method == "iterative":
        return engine.run(g.symmetric(), wcc_program(), max_iter, stop_when_stable=True, **options).values
    if method == "unionfind":
        return _unionfind(g)
    if method == "contract":
        found = components(g.edges, "src", "dst", small=0)
        return g.vertices.join(found.withColumnRenamed("node", "id"), "id", "left").select("id", F.coalesce("component", "id").alias("label"))
    raise ValueError(method)


def _forests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A task's edges to one edge from each vertex to its root, if that is another. What has come is folded in once it is as much as the
    forest itself, so at most a few edges per vertex are held and the work stays in proportion to the edges."""
    src = dst = np.zeros(0, np.int64)
    held, rows = [], 0

    def folded() -> tuple[np.ndarray, np.ndarray]:
        ids, roots = forest(*(np.concatenate([x, *(h[i] for h in held)]) for i, x in enumerate((src, dst))))
        held.clear()
        away = ids != roots
        return ids[away], roots[away]

    for b in batches:
        held.append(tuple(b.column(c).to_numpy() for c in ("src", "dst")))
        rows += b.num_rows
        if rows >= max(len(src), FOLD_ROWS):
            (src, dst), rows = folded(), 0
    if held:
        src, dst = folded()
    for at in range(0, len(src), 65_536):
        yield pa.RecordBatch.from_arrays([pa.array(src[at : at + 65_536]), pa.array(dst[at : at + 65_536])], ["src", "dst"])


def _unionfind(g: Graph, fan: int = 8) -> DataFrame:
    """One pass over the edges: every task keeps a forest of at most n edges; forests meet in a tree of ``fan`` at a time.

    For graphs whose vertices fit one task (``fits``); larger ones take the iterative or the contracting way."""
    spark = g.edges.sparkSession
    parts = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    now = g.edges.select("src", "dst").repartition(parts, "src", "dst").mapInArrow(_forests, "src long, dst long")
    while parts > 1:  # an exchange at every level, so that its forests are made by as many tasks
        parts = -(-parts // fan)
        now = now.repartition(parts, "src", "dst").mapInArrow(_forests, "src long, dst long")
    return g.vertices.join(now.withColumnRenamed("src", "id"), "id", "left").select("id", F.coalesce("dst", "id").alias("label"))


def bfs(g: Graph, sources: Column, max_iter: int = 10_000, **options) -> DataFrame:
    """id, dist (null where not reached) over directed edges."""
    prog = VertexProgram({"dist": F.when(sources, F.lit(0)).cast("long")}, [F.col("dist") + 1], ["min"], {"dist": F.least("dist", "acc0")}, ~F.col("dist").eqNullSafe(F.col("old_dist")))
    return engine.run(g, prog, max_iter, stop_when_stable=True, **options).values


def sssp(g: Graph, sources: Column, max_iter: int = 10_000, **options) -> DataFrame:
    """id, dist by the sum of weights (none negative)."""
    prog = VertexProgram({"dist": F.when(sources, F.lit(0.0))}, [F.col("dist") + F.col("w")], ["min"], {"dist": F.least("dist", "acc0")}, ~F.col("dist").eqNullSafe(F.col("old_dist")))
    return engine.run(g, prog, max_iter, stop_when_stable=True, **options).values


def degrees(g: Graph) -> DataFrame:
    """id, in_degree, out_degree of every vertex."""
    ends = g.edges.select(F.col("src").alias("id"), F.lit(1).alias("o"), F.lit(0).alias("i")).union(g.edges.select("dst", F.lit(0), F.lit(1)))
    d = ends.groupBy("id").agg(F.sum("i").alias("i"), F.sum("o").alias("o"))
    return g.vertices.join(d, "id", "left").select("id", _or("i", 0).alias("in_degree"), _or("o", 0).alias("out_degree"))


def neighbourhood_exact(g: Graph, max_hops: int = 10_000) -> DataFrame:
    """hops, pairs: pairs (u, v) with v at most so many steps from u, u itself counted; for graphs of small closure.

    Until no pair is new; an error if that takes over ``max_hops`` hops."""
    seen = cut(g.vertices.select("id", F.col("id").alias("to"), F.lit(0).alias("hops")), "closure")
    for hop in range(1, max_hops + 1):
        reached = seen.where(F.col("hops") == hop - 1).join(g.edges.select(F.col("src").alias("to"), F.col("dst").alias("next")), "to")
        new = cut(reached.select("id", F.col("next").alias("to"), F.lit(hop).alias("hops")).distinct().join(seen.select("id", "to"), ["id", "to"], "left_anti"), "closure")
        if not new.limit(1).count():
            break
        seen = seen.unionByName(new)
    else:
        raise RuntimeError(f"pairs are still new after {max_hops} hops")
    per = seen.groupBy("hops").agg(F.count(F.lit(1)).alias("new"))
    levels = per.alias("a").join(per.alias("b"), F.col("b.hops") <= F.col("a.hops"))  # hops rows
    return levels.groupBy(F.col("a.hops").alias("hops")).agg(F.sum("b.new").alias("pairs"))


def sketch_program(registers: int, seed: int = 1) -> VertexProgram:
    """Bit sketches: each register starts with one bit, bit i with probability 2 ** -(i + 1), and takes in its neighbours' bits."""
    names = [f"s{i}" for i in range(registers)]
    first = {}
    for i, name in enumerate(names):
        h = F.xxhash64("id", F.lit(seed * 1000 + i))
        low = F.bit_count(h.bitwiseXOR(h - 1).bitwiseAND(F.lit(2**62 - 1))) - 1
        first[name] = F.call_function("shiftleft", F.lit(1).cast("long"), low.cast("int"))
    return VertexProgram(first, [F.col(n) for n in names], ["bit_or"] * registers, {n: F.col(n).bitwiseOR(F.coalesce(F.col(f"acc{i}"), F.lit(0).cast("long"))) for i, n in enumerate(names)}, changed=F.expr(" or ".join(f"{n} <> old_{n}" for n in names)))


def _expected_zeros(most: int = 64) -> list[float]:
    """The expected lowest zero of a register over 0 .. most ids: those that miss its first bit fill the next ones in the same way."""
    e = [0.0]
    for n in range(1, most + 1):
        e.append(sum(math.comb(n, m) / 2**n * (1 + e[m]) for m in range(n)))
    return e


def estimated_ids(zero: float) -> float:
    """The number of ids whose expected lowest zero is ``zero``: exact for few ids, where 2 ** zero / 0.77351 is up to 1.8 times too high."""
    if zero < _ZEROS[-1]:
        return float(np.interp(zero, _ZEROS, range(len(_ZEROS))))
    return 2**zero / 0.77351


_ZEROS = _expected_zeros()


def neighbourhood_sketch(g: Graph, registers: int = 16, max_hops: int = 10_000, **options) -> list[tuple[int, float]]:
    """(hops, estimated pairs): a vertex's set grows along edges towards it; see ``estimated_ids`` of its mean lowest zero.

    Until no bit is new; an error if that takes over ``max_hops`` hops."""
    from blockgraph.plans import layout as lay

    prog = sketch_program(registers)
    backward = Graph(g.name, g.n, g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    layout = lay.build(backward, options.pop("beta", 4), **options)
    names = list(prog.init)
    zeros = sum((F.bit_count(F.col(n).bitwiseXOR(F.col(n) + 1)) - 1 for n in names), F.lit(0))
    out: list[tuple[int, float]] = []

    def measure(values: DataFrame, _prog: VertexProgram) -> None:
        sums = values.groupBy(zeros.alias("z")).count().collect()  # at most 64 * registers rows
        out.append((len(out), math.fsum(r["count"] * estimated_ids(r.z / registers) for r in sums)))

    run = engine.iterate(layout, prog, max_hops, stop_when_stable=True, after=measure)
    if not run.changed or run.changed[-1]:
        raise RuntimeError(f"bits are still new after {max_hops} hops")
    measure(run.values, prog)
    return out


def diameter(g: Graph, quantile: float = 0.9, exact: bool = False, max_hops: int = 10_000, **options) -> tuple[float, int]:
    """Effective diameter (hops within which ``quantile`` of all reachable pairs lie, interpolated) and the largest hop count."""
    grown = [(r.hops, float(r.pairs)) for r in neighbourhood_exact(g, max_hops).orderBy("hops").collect()] if exact else neighbourhood_sketch(g, max_hops=max_hops, **options)
    return effective_diameter(grown, quantile)


def effective_diameter(grown: list[tuple[int, float]], quantile: float = 0.9) -> tuple[float, int]:
    """The same from a neighbourhood function."""
    goal = quantile * grown[-1][1]
    last = next(h for h, m in grown if m >= grown[-1][1])
    h, m = next((h, m) for h, m in grown if m >= goal)
    before = grown[h - 1][1] if h else 0.0
    return (h - 1 + (goal - before) / (m - before) if h else 0.0), last


def cp_als(counts: DataFrame, rank: int = 2, iters: int = 5, seed: int = 1) -> tuple[dict[str, DataFrame], float]:
    """Rank-``rank`` canonical decomposition of counts(i, j, k, x) over ids of any size by alternating least squares: factor tables
    (id, f0, f1 ...) by mode, and the share of the norm that is explained.

    Each half-step is one join with the two other factors and a grouped sum; rows times the inverse of a rank x rank matrix are the new
    factor, so only rank * rank numbers are ever on the driver. Ids without an entry have factors of zero and no row."""
    modes, names = ["i", "j", "k"], [f"f{c}" for c in range(rank)]
    total = counts.agg(F.sum(F.col("x") * F.col("x"))).first()[0]
    if not total:
        return {m: counts.select(F.col(m).alias("id"), *(F.lit(0.0).alias(f) for f in names)) for m in modes}, 0.0

    def gram(table: DataFrame) -> np.ndarray:
        return np.array(table.agg(*(F.sum(F.col(a) * F.col(b)) for a in names for b in names)).first(), float).reshape(rank, rank)

    unit = lambda m, c: F.pmod(F.xxhash64("id", F.lit(f"{seed}:{m}:{c}")), F.lit(2**30)) / 2.0**30
    factors = {m: cut(counts.select(F.col(m).alias("id")).distinct().select("id", *(unit(m, c).alias(f) for c, f in enumerate(names))), f"factor-{m}") for m in modes}
    grams, told = {m: gram(factors[m]) for m in modes}, 0.0
    for _ in range(iters):
        for m in modes:
            a, b = (o for o in modes if o != m)
            met = counts
            for o in (a, b):
                met = met.join(factors[o].select(F.col("id").alias(o), *(F.col(f).alias(f"{o}{f}") for f in names)), o)
            sums = met.groupBy(F.col(m).alias("id")).agg(*(F.sum(F.col("x") * F.col(f"{a}{f}") * F.col(f"{b}{f}")).alias(f"s{c}") for c, f in enumerate(names)))
            left = grams[a] * grams[b]
            inverse = np.linalg.pinv(left)
            new = sums.select("id", *(sum((float(inverse[r, c]) * F.col(f"s{r}") for r in range(rank)), F.lit(0.0)).alias(f) for c, f in enumerate(names)), *(f"s{c}" for c in range(rank)))
            new = cut(new, f"factor-{m}")
            both = new.agg(F.sum(sum((F.col(f"s{c}") * F.col(f) for c, f in enumerate(names)), F.lit(0.0)))).first()[0]
            factors[m] = new.select("id", *names)
            grams[m] = gram(factors[m])
            told = (2 * both - float((left * grams[m]).sum())) / total
    return factors, float(told)
