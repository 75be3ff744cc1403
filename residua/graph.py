"""Flow problems and their residual state as tables.

``slots`` holds one row for each ordered neighbour pair, in both orientations: ``cap_out`` and ``cap_in`` are the
capacities along and against the row, ``net`` the net flow along it. The residual room of an arc and of its reverse are
columns of one row: ``cap_out - net`` and ``cap_in + net``.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .lineage import cut

LONG = T.LongType()
ARCS = T.StructType([T.StructField(n, LONG, False) for n in ("src", "dst", "cap")])
SOURCE, SINK = -1, -2


@dataclass(frozen=True)
class FlowProblem:
    """Arcs ``(src, dst, cap)`` with capacities of 0 or more, a source and a sink."""

    arcs: DataFrame
    s: int
    t: int
    name: str = "flow"


@dataclass(frozen=True)
class FlowState:
    """Residual state handed from run to run. ``counters`` are sums over the run, ``trace`` a row for each superstep."""

    slots: DataFrame
    verts: DataFrame
    s: int
    t: int
    n: int
    n_arcs: int
    cut: DataFrame | None = None
    counters: dict = field(default_factory=dict)
    trace: list = field(default_factory=list)

    def mirror(self) -> FlowState:
        """The transposed network with reversed signs: pushing there is pulling here."""
        slots = self.slots.select("src", "dst", F.col("cap_in").alias("cap_out"), F.col("cap_out").alias("cap_in"), (-F.col("net")).alias("net"))
        return replace(self, slots=slots, verts=self.verts.withColumn("excess", -F.col("excess")), s=self.t, t=self.s)

    def save(self, path: str) -> None:
        """Slots lie clustered by source, so that a later run reads only the files its batch touches."""
        self.slots.repartition("src").sortWithinPartitions("src").write.mode("overwrite").parquet(f"{path}/slots")
        self.verts.write.mode("overwrite").parquet(f"{path}/verts")
        spark = self.slots.sparkSession
        (self.cut if self.cut is not None else spark.createDataFrame([], "id long, side string")).write.mode("overwrite").parquet(f"{path}/cut")
        spark.createDataFrame([(self.s, self.t, self.n, self.n_arcs)], "s long, t long, n long, n_arcs long").write.mode("overwrite").parquet(f"{path}/facts")

    def register_views(self, prefix: str = "flow") -> None:
        """Temporary views ``<prefix>_slots``, ``<prefix>_verts`` and, where a cut is known, ``<prefix>_cut`` for SQL."""
        self.slots.createOrReplaceTempView(f"{prefix}_slots")
        self.verts.createOrReplaceTempView(f"{prefix}_verts")
        if self.cut is not None:
            self.cut.createOrReplaceTempView(f"{prefix}_cut")

    def size(self) -> DataFrame:
        """One row: slots, vertices and the bytes that their long columns take, five for a slot and three for a vertex."""
        one = F.count(F.lit(1))
        both = self.slots.agg(one.alias("slots")).crossJoin(self.verts.agg(one.alias("vertices")))
        return both.select("slots", "vertices", (F.col("slots") * 5 * 8 + F.col("vertices") * 3 * 8).alias("bytes"))

    @staticmethod
    def load(spark, path: str) -> FlowState:
        s, t, n, m = spark.read.parquet(f"{path}/facts").first()
        sides = spark.read.parquet(f"{path}/cut")
        return FlowState(spark.read.parquet(f"{path}/slots"), spark.read.parquet(f"{path}/verts"), s, t, n, m, None if sides.isEmpty() else sides)


def room_out():
    return F.col("cap_out") - F.col("net")


def room_in():
    return F.col("cap_in") + F.col("net")


def validate_arcs(arcs: DataFrame) -> DataFrame:
    """Rejects null ends, null and negative capacities."""
    bad = arcs.where("src is null or dst is null or cap is null or cap < 0").limit(1).count()
    if bad:
        raise ValueError("arcs need both ends and a capacity of 0 or more")
    return arcs


def rejected_arcs(arcs: DataFrame) -> DataFrame:
    return arcs.where("src is null or dst is null or cap is null or cap < 0")


def simple_arcs(arcs: DataFrame) -> DataFrame:
    """Parallel arcs summed, self-loops dropped."""
    return arcs.where("src <> dst").groupBy("src", "dst").agg(F.sum("cap").cast("long").alias("cap"))


def build_slots(arcs: DataFrame) -> DataFrame:
    """Slots with zero flow; a missing reverse arc has capacity 0."""
    one = arcs.where("src <> dst")
    both = one.select("src", "dst", F.col("cap").alias("cap_out"), F.lit(0).cast("long").alias("cap_in")).unionByName(one.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(0).cast("long").alias("cap_out"), F.col("cap").alias("cap_in")))
    return both.groupBy("src", "dst").agg(F.sum("cap_out").cast("long").alias("cap_out"), F.sum("cap_in").cast("long").alias("cap_in")).withColumn("net", F.lit(0).cast("long"))


def excess_of(slots: DataFrame) -> DataFrame:
    """Inflow less outflow of every vertex."""
    return slots.groupBy(F.col("src").alias("id")).agg((-F.sum("net")).cast("long").alias("excess"))


def with_super_terminals(arcs: DataFrame, sources: DataFrame, sinks: DataFrame, s: int = SOURCE, t: int = SINK) -> DataFrame:
    """Adds arcs from ``s`` to every source and from every sink to ``t``; sources and sinks are ``(id, cap)``."""
    return arcs.select("src", "dst", "cap").unionByName(sources.select(F.lit(s).cast("long").alias("src"), F.col("id").alias("dst"), "cap")).unionByName(sinks.select(F.col("id").alias("src"), F.lit(t).cast("long").alias("dst"), "cap"))


def saturate(slots: DataFrame, s: int | None = None, t: int | None = None) -> DataFrame:
    """Fills the remaining room of all arcs out of ``s`` and into ``t``, in both orientations of the rows."""
    net = F.col("net")
    out = F.col("src") == s if s is not None else F.lit(False)
    back = F.col("dst") == s if s is not None else F.lit(False)
    if t is not None:
        out, back = out | (F.col("dst") == t), back | (F.col("src") == t)
    return slots.withColumn("net", F.when(out, F.col("cap_out")).when(back, -F.col("cap_in")).otherwise(net))


def init_state(problem: FlowProblem, into_sink: bool = False) -> FlowState:
    """Zero flow with every source arc (on demand every sink arc too) saturated, and the excess that follows."""
    if problem.s == problem.t:
        raise ValueError("source and sink must differ")
    slots = cut(saturate(build_slots(validate_arcs(problem.arcs)), problem.s, problem.t if into_sink else None))
    return fresh(FlowState(slots, None, problem.s, problem.t, 0, 0))


def fresh(state: FlowState) -> FlowState:
    """Vertices with excess from net flow and height 0, and the sizes of the graph."""
    ends = state.slots.sparkSession.createDataFrame([(state.s,), (state.t,)], "id long")
    verts = excess_of(state.slots).join(ends, "id", "full").select("id", F.lit(0).cast("long").alias("height"), F.coalesce("excess", F.lit(0)).cast("long").alias("excess"))
    verts = cut(verts)
    arcs = state.slots.where("cap_out > 0").count()
    return replace(state, verts=verts, n=verts.count(), n_arcs=arcs)


def default_cycles(n_arcs: int, n_vertices: int, most: int | None = 4) -> int:
    """Steps between two global relabels: the average degree, at most ``most`` (a Spark step costs far more than a thread's)."""
    k = max(1, round(n_arcs / max(1, n_vertices)))
    return min(k, most) if most else k
