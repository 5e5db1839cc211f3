"""The loop of iterations: every generation of values is written before the one before it goes, so a run survives lost executors."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockgraph.plans import costmodel, layout as lay, schemes
from blockgraph.plans.layout import Layout
from blockgraph.plans.program import VertexProgram
from blockgraph.sources.graphs import Graph
from blockgraph.storage import cut, drop_path, own_path, settings

#: Edges and slices of one interval share their partitioning by q or p alone; nothing of the size of the graph is broadcast by guess.
#: Dense buckets are written sorted, and read as such.
PLAN = {"spark__sql__requireAllClusterKeysForCoPartition": "false", "spark__sql__autoBroadcastJoinThreshold": "-1", "spark__sql__legacy__bucketedTableScan__outputOrdering": "true"}


class Run:
    """Result of a run: ``values`` (id, value columns), ``iterations`` done, and the number of vertices changed in each."""

    def __init__(self, values: DataFrame, iterations: int, changed: list[int]):
        self.values, self.iterations, self.changed = values, iterations, changed


def start(layout: Layout, prog: VertexProgram) -> DataFrame:
    """Initial values: id, p, outdeg and the program's columns."""
    here = layout.vertices("p")
    if prog.needs_degree:
        here = here.join(layout.degrees.withColumnRenamed("src", "id"), "id", "left").withColumn("outdeg", F.coalesce("outdeg", F.lit(0)).cast("long"))
    else:
        here = here.withColumn("outdeg", F.lit(0).cast("long"))
    return here.select("id", "p", "outdeg", *(c.alias(n) for n, c in prog.init.items()))


def generation(layout: Layout, values: DataFrame) -> tuple[DataFrame, Callable[[], None]]:
    """values written (for bucketed layouts by p, as they lie already), and how to take them away again."""
    spark = values.sparkSession
    if layout.bucketed:
        mine: list[str] = []
        kept = lay.save(values, "generation", "p", layout.buckets, True, mine)
        return kept, lambda: lay.drop_tables(spark, mine)
    path = own_path(spark, "generation")
    values.write.parquet(path)
    return spark.read.schema(values.schema).parquet(path), lambda: drop_path(spark, path)


def iterate(layout: Layout, prog: VertexProgram, iters: int, stop_when_stable: bool = False, pre_combine: bool = True, after=None) -> Run:
    """iters iterations, fewer if nothing changes and stop_when_stable. after: a function of the new values for algorithms that
    need a whole-graph quantity (it may return a new program).

    Two generations exist at a time: the one before goes when the next one is written."""
    spark = layout.blocks.sparkSession
    changed: list[int] = []
    done = 0
    with settings(spark, **PLAN):
        values, drop = generation(layout, start(layout, prog))
        for done in range(1, iters + 1):
            if after is not None:
                prog = after(values, prog) or prog
            new, drop_new = generation(layout, schemes.two_mode(layout, values, prog, pre_combine))
            drop()
            values, drop = new.drop(*(f"old_{c}" for c in prog.init)), drop_new
            if stop_when_stable:
                moved = new.where(prog.changed).count()
                changed.append(moved)
                if not moved:
                    break
        if layout.bucketed:  # the result outlives the layout's tables
            kept = cut(values.select("id", *prog.init), "result")
            drop()
            return Run(kept, done, changed)
    return Run(values.select("id", *prog.init), done, changed)


def intervals_for(graph: Graph, memory: float, threads: int) -> int:
    """The number of intervals: by the executors' memory and cores where Spark names them, else by memory and threads."""
    conf = graph.edges.sparkSession.sparkContext.getConf()
    said = conf.get("spark.executor.memory", None)
    if not said or conf.get("spark.master", "").startswith("local["):
        return costmodel.num_intervals(graph.n, costmodel.PHI, threads, memory)
    number, unit = said.rstrip("bB"), 2**20
    if number[-1].lower() in "kmgt":
        number, unit = number[:-1], 1024 ** ("kmgt".index(number[-1].lower()) + 1)
    return costmodel.num_intervals_cluster(graph.n, costmodel.PHI, int(conf.get("spark.executor.cores", "1")), int(number) * unit)


def run(graph: Graph, prog: VertexProgram, iters: int, beta: int | None = None, scheme: str = "two_mode", memory: float = 2**30, threads: int = 4, rule: str = "printed", how: str = "width", **options) -> Run:
    """Lays the graph out in beta intervals and iterates. Without beta: as many as a machine of ``memory`` bytes and ``threads`` needs,
    on a cluster (spark.executor.memory is set) as many as its executors need."""
    beta = beta or intervals_for(graph, memory, threads)
    layout = lay.build(graph, beta, scheme, rule, how=how)
    done = iterate(layout, prog, iters, **options)
    layout.drop()
    return done
