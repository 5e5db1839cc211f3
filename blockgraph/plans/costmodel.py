"""Input/output cost of the two paths, for numbers and for Columns alike (plain arithmetic).

phi and psi: bytes of a vertex value and of an edge. theta: vertices of an interval. xi: edges of a block. beta: intervals.
b: transfer size, 1 to count bytes.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PHI, PSI = 4, 8


@dataclass(frozen=True)
class IoCount:
    """Blocks transferred and jumps to another place."""

    transfers: float
    seeks: float

    @property
    def total(self) -> float:
        return self.transfers + self.seeks


def dense_graph(v, e, beta, b=1, seeks=True, count_dst_read=False, zigzag=False):
    """One iteration of the dense path: source intervals once for each destination interval, edges and results once."""
    loads = (beta * beta - beta + 1) * v / beta if zigzag else beta * v
    moved = (loads + (2 * v if count_dst_read else v) + e) / b
    return moved + beta * beta if seeks else moved


def stream_graph(v, e, ehat, beta, b=1, seeks=True):
    """One iteration of the streamed path: values read and written, edges read, valued edges written and read."""
    moved = (2 * v + e + 2 * ehat) / b
    return moved + beta if seeks else moved


def graph_io(scheme: str, v: float, e: float, beta: int, b: float = 1, ehat: float | None = None) -> IoCount:
    if scheme == "dense":
        return IoCount(dense_graph(v, e, beta, b, seeks=False), beta * beta)
    return IoCount(stream_graph(v, e, e if ehat is None else ehat, beta, b, seeks=False), beta)


def dense_block(xi, theta, beta, phi=PHI, psi=PSI, b=1):
    return (theta * phi * (1 + 1 / beta if not isinstance(beta, Column) else F.lit(1.0) + F.lit(1.0) / beta) + xi * psi) / b


def stream_block(xi, theta, beta, phi=PHI, psi=PSI, b=1):
    return (2 * theta * phi / beta + 2 * xi * (phi + psi) + xi * psi) / b


def criterion(xi, theta, beta, phi=PHI, psi=PSI):
    """Below 1 exactly where the streamed path costs less."""
    return (F.lit(1.0) / beta if isinstance(beta, Column) else 1 / beta) + (2 * xi / theta) * (1 + psi / phi)


def preprocess_cost(e, b=1):
    return 4 * e / b


def tcost_unit(v, e):
    return 2 * v + e


def crossover(k, phi=PHI, psi=PSI):
    """The number of intervals from which on blocks of uniform density k = E / V are sparse."""
    return 1 + 2 * k * (1 + psi / phi)


def crossover_elements(k):
    """The same where every element counts one."""
    return 1 + 2 * k


def num_intervals(n: int, phi: int, threads: int, memory: float) -> int:
    """So many intervals that one interval's values for each thread and one result interval fit the memory."""
    return max(1, -(-phi * (threads + 1) * n // int(memory)))


def num_intervals_cluster(n: int, phi: int, cores: int, executor_memory: float, share: float = 0.5) -> int:
    """The same for executors: each core holds one interval's slice and one accumulator, of ``share`` of the memory."""
    return num_intervals(n, phi, cores, executor_memory * share)


def zigzag_loads(beta):
    """Interval loads when each column of blocks is walked in the other direction than the one before."""
    return beta * beta - beta + 1


def classify(blocks: DataFrame, beta: int, width: int | Column, phi: int = PHI, psi: int = PSI, rule: str = "printed") -> DataFrame:
    """blocks(p, q, xi[, s, d]) with ``crit`` and ``mode``.

    printed: the paper's test. argmin: the cheaper of the two block costs (the same decision). network: the fewer bytes to
    exchange, from the distinct sources s and destinations d of a block."""
    theta = width if isinstance(width, Column) else F.lit(float(width))
    crit = criterion(F.col("xi"), theta, F.lit(float(beta)), phi, psi)
    if rule == "printed":
        sparse = crit < 1
    elif rule == "argmin":
        sparse = stream_block(F.col("xi"), theta, float(beta), phi, psi) < dense_block(F.col("xi"), theta, float(beta), phi, psi)
    elif rule == "network":
        sparse = F.col("d") <= F.col("s")
    else:
        raise ValueError(rule)
    return blocks.withColumn("crit", crit).withColumn("mode", F.when(sparse, "sparse").otherwise("dense"))


def two_mode_cost(blocks: DataFrame, beta: int, width: int, phi: int = PHI, psi: int = PSI) -> DataFrame:
    """One row: modelled bytes of all non-empty blocks under the dense, the streamed and the cheaper path."""
    d, s = dense_block(F.col("xi"), float(width), float(beta), phi, psi), stream_block(F.col("xi"), float(width), float(beta), phi, psi)
    return blocks.agg(F.sum(d).alias("dense"), F.sum(s).alias("stream"), F.sum(F.least(d, s)).alias("two_mode"))
