"""Cost against memory and density, and arithmetic on the published figures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blockgraph.plans import costmodel as cm
from blockgraph.plans.schemes import zigzag

PAPER_GRAPHS = [("G-S", 4_847_571, 68_993_773), ("G-M", 41_652_230, 1_468_365_182), ("G-L", 1_413_511_391, 6_636_600_779), ("G-X", 4_000_000_000, 12_000_000_000)]
_TABLE = {
    "pagerank G-S": {"B1": 33.1, "B2": 10.5, "B3": 7.9, "B4": 18.2, "B5": 6.4, "engine": 5.3},
    "pagerank G-M": {"B1": 1199, "B2": 962, "B3": 241, "B4": 186, "B5": 269, "engine": 173},
    "pagerank G-L": {"B1": 642, "B2": 668, "B3": 628, "B4": 1245, "B5": 235.95, "engine": 195},
    "pagerank G-X": {"B1": 2145, "B2": 1360, "engine": 745},
    "components G-S": {"B1": 3.2, "B2": 5.7, "B3": 4.4, "B4": 10.7, "B5": 4.4, "engine": 1.3},
    "components G-M": {"B1": 70, "B2": 1038, "B3": 128, "B4": 45, "B5": 287, "engine": 25},
    "components G-L": {"B1": 668, "B2": 889, "engine": 125},
    "components G-X": {"B1": 3334, "B2": 2167.63, "engine": 663.17},
}
GL_PREPARE_AND_RUN = [("B1", 2781, 642), ("B2", 865, 668), ("B3", 4694, 628), ("B4", 636, 1245), ("engine", 1265, 195)]
RUNTIMES = [(w, s, t) for w, row in _TABLE.items() for s, t in row.items()]


def grid(spark: SparkSession, **values: list) -> DataFrame:
    """All combinations of a few parameter values; lists of fixed length, so the cross join is small."""
    out = None
    for name, items in values.items():
        one = spark.createDataFrame([(v,) for v in items], f"{name} {'double' if any(isinstance(v, float) for v in items) else 'long'}")
        out = one if out is None else out.crossJoin(F.broadcast(one))
    return out


def paper_graphs(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(g, float(v), float(e)) for g, v, e in PAPER_GRAPHS], "graph string, v double, e double")


def beta_column(v: Column, memory: Column, phi: int = 4, threads: int = 4) -> Column:
    return F.greatest(F.lit(1), F.ceil(phi * (threads + 1) * v / memory)).cast("long")


def _schemes(df: DataFrame, d: Column, s: Column) -> DataFrame:
    kinds = F.explode(F.array(*(F.struct(F.lit(n).alias("scheme"), c.alias("tcost")) for n, c in (("dense", d), ("stream", s), ("two_mode", F.least(d, s)))))).alias("x")
    return df.select("*", kinds).select(*df.columns, "x.scheme", "x.tcost")


def memory_curve(graphs: DataFrame, gibs: list[float], unit: str = "elements") -> DataFrame:
    """graph, gib, scheme, tcost: one iteration's modelled cost in units of 2 V + E, the intervals following from the memory."""
    spark = graphs.sparkSession
    g = graphs.crossJoin(F.broadcast(spark.createDataFrame([(float(m),) for m in gibs], "gib double"))).withColumn("beta", beta_column(F.col("v"), F.col("gib") * 2**30))
    v, e, beta = F.col("v"), F.col("e"), F.col("beta")
    if unit == "bytes":
        d, s = (beta + 1) * v * cm.PHI + e * cm.PSI, 2 * v * cm.PHI + e * cm.PSI + 2 * e * (cm.PHI + cm.PSI)
        return _schemes(g, d / (2 * v * cm.PHI + e * cm.PSI), s / (2 * v * cm.PHI + e * cm.PSI))
    return _schemes(g, cm.dense_graph(v, e, beta, seeks=False) / cm.tcost_unit(v, e), cm.stream_graph(v, e, e, beta, seeks=False) / cm.tcost_unit(v, e))


def density_curve(spark: SparkSession, ks: list[int], betas: list[int]) -> DataFrame:
    """k, beta, scheme, tcost, chosen for uniform graphs with E = k V."""
    g = grid(spark, k=[float(k) for k in ks], beta=[float(b) for b in betas])
    k, beta = F.col("k"), F.col("beta")
    d, s = (beta + 1 + k) / (2 + k), (2 + 3 * k) / (2 + k)
    return _schemes(g.withColumn("chosen", F.when(s < d, "stream").otherwise("dense")), d, s)


def zigzag_measured(spark: SparkSession, betas: list[int]) -> DataFrame:
    """beta, loads, saved: counted from the order of blocks itself."""
    out = None
    for b in betas:
        one = zigzag(spark, b).agg(F.sum(F.when(F.col("reused"), 0).otherwise(1)).alias("loads"), F.sum(F.when(F.col("reused"), 1).otherwise(0)).alias("saved")).select(F.lit(b).cast("long").alias("beta"), "loads", "saved")
        out = one if out is None else out.union(one)
    return out


def speedups(spark: SparkSession) -> DataFrame:
    rows = spark.createDataFrame([(w, s, float(t)) for w, s, t in RUNTIMES], "workload string, system string, seconds double")
    own = F.max(F.when(F.col("system") == "engine", F.col("seconds"))).over(Window.partitionBy("workload"))
    return rows.withColumn("speedup", F.col("seconds") / own).where("system <> 'engine'")


def totals(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(s, float(p), float(r)) for s, p, r in GL_PREPARE_AND_RUN], "system string, p double, r double").select("system", (F.col("p") + F.col("r")).alias("total"))
