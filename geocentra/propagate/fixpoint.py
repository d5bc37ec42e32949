"""A semi-naive fixpoint over a lattice: what rose in a round is all that travels in the next.

State is rows (node, run, item, value). A round sends the rows that changed along the
arcs, joins them per (node, run, item) with the lattice's operation, and keeps those
that change the receiver's value. Both sides of the state join are dealt by the same
keys once, so that the state itself is not shuffled again.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geocentra.errors import ParameterError
from geocentra.graph.model import Graph
from geocentra.plans.checkpoint import cut, cut_by, own_folder
from geocentra.propagate import local as L

KEYS = ["node", "run", "item"]
#: Changed rows gathered since the base table was made, as a share of it, at which a new base is made.
COMPACT_AT = 0.5
#: Arcs, and rows of state, that a partition is made for.
PART_ROWS = 4 << 20
#: A sender of more arcs is spread: its rows go to several places, each with some of its arcs.
HUB_ARCS = 1 << 20


@dataclass(frozen=True)
class Lattice:
    """How values meet (an aggregate), what the merged value is, and whether it is news."""

    aggregate: Callable[[str], Column]
    merge: Callable[[Column, Column], Column]
    news: Callable[[Column, Column], Column]


MAXIMUM = Lattice(F.max, F.greatest, lambda new, old: new > old)
BITS = Lattice(F.bit_or, lambda new, old: new.bitwiseOR(old), lambda new, old: new.bitwiseOR(old) != old)
#: A row is news once: the values are of no account.
PRESENCE = Lattice(F.min, lambda new, old: old, lambda new, old: F.lit(False))


class LocalRounds:
    """The same of a graph whose arcs fit in a task, for values above 0; there are no seconds of rounds, as no round is a job."""

    truncated = False

    def __init__(self, seeds: DataFrame, blob: DataFrame, bits: bool, full: bool):
        self.seeds, self.blob, self.bits, self.full = seeds, blob, bits, full
        self.seconds: list[float] = []

    def _run(self, last: bool) -> DataFrame:
        return L.dealt(self.seeds, self.blob, L.n_tasks(self.seeds.sparkSession), L.value_rounds(self.bits, self.full, last), L.CHANGES)

    @cached_property
    def changes(self) -> DataFrame:
        return cut(self._run(False))

    @property
    def last(self) -> int:
        return self.changes.agg(F.max("t").alias("t")).first()["t"]

    def final(self) -> DataFrame:
        return self._run(True).select(*KEYS, "value")

    def stats(self) -> DataFrame:
        return self.changes.groupBy("t").agg(F.countDistinct("node").alias("changed_nodes"), F.count(F.lit(1)).alias("changed_rows"), F.lit(None).cast("double").alias("seconds"))


def rounds_of(seeds: DataFrame, graph: Graph, lattice: Lattice, direction: str = "in", propagation: str = "delta", max_iter: int | None = None) -> Rounds | LocalRounds:
    """The rounds of maxima or patterns: of a graph whose arcs fit in a task in memory, of others, and of runs that may be cut short, by `fixpoint`."""
    if propagation not in ("delta", "full"):
        raise ParameterError(f"propagation must be 'delta' or 'full', not {propagation!r}")
    arcs = cut(oriented(graph, direction))
    if max_iter is not None or arcs.count() > L.LOCAL_ARCS:
        ends = ("tx", "rx") if direction == "in" else ("rx", "tx")
        kept = Graph(graph.vertices, arcs.select(F.col(ends[0]).alias("src"), F.col(ends[1]).alias("dst")))
        return fixpoint(seeds, kept, lattice, direction, propagation, max_iter)
    typed = seeds.select(F.col("node").cast("long"), F.col("run").cast("int"), F.col("item").cast("long"), F.col("value").cast("long"))
    return LocalRounds(cut(typed), cut(L.packed_graph(arcs)), lattice is BITS, propagation == "full")


@dataclass
class Rounds:
    """All changes of a run: rows (node, run, item, value, old, t); t = 0 are the seeds."""

    changes: DataFrame
    seconds: list[float] = field(default_factory=list)
    truncated: bool = False

    @property
    def last(self) -> int:
        return len(self.seconds) - 1

    def final(self) -> DataFrame:
        """The state after the last round."""
        return self.changes.groupBy(*KEYS).agg(F.max_by("value", "t").alias("value"))

    def stats(self) -> DataFrame:
        """t, changed_nodes, changed_rows, seconds of every round that changed something."""
        spark = self.changes.sparkSession
        times = spark.createDataFrame(list(enumerate(self.seconds)), "t int, seconds double")
        return self.changes.groupBy("t").agg(F.countDistinct("node").alias("changed_nodes"), F.count(F.lit(1)).alias("changed_rows")).join(times, "t", "left")


def oriented(graph: Graph, direction: str) -> DataFrame:
    """Arcs as (tx, rx), sender and receiver: balls of incoming distances send along the arcs, of outgoing ones against them."""
    if direction not in ("in", "out"):
        raise ParameterError(f"direction must be 'in' or 'out', not {direction!r}")
    tx, rx = ("src", "dst") if direction == "in" else ("dst", "src")
    return graph.arcs.select(F.col(tx).alias("tx"), F.col(rx).alias("rx"))


def fixpoint(seeds: DataFrame, graph: Graph, lattice: Lattice, direction: str = "in", propagation: str = "delta", max_iter: int | None = None, prune: Callable[[DataFrame, DataFrame, int], DataFrame] | None = None) -> Rounds:
    """Grow `seeds` (node, run, item, value) along the arcs until a round changes nothing.

    propagation="full" sends the whole state in every round, as systems without change
    flags do; the result is the same. With `max_iter` the result may be truncated,
    and says so. `prune`(candidates, state, t) may drop candidates of a round.
    """
    if propagation not in ("delta", "full"):
        raise ParameterError(f"propagation must be 'delta' or 'full', not {propagation!r}")
    spark = seeds.sparkSession
    folder = f"{own_folder(spark)}/rounds-{uuid.uuid4().hex}"
    schema = "node long, run int, item long, value long, old long"
    arcs = cut(oriented(graph, direction))
    m = arcs.count()  # from the files' footers
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-m // PART_ROWS))
    hubs = arcs.groupBy("tx").agg(F.count(F.lit(1)).alias("k")).where(F.col("k") > HUB_ARCS) if m > HUB_ARCS else None
    if hubs is not None:
        # At most one sender in HUB_ARCS arcs.
        hubs = cut(hubs.select(F.col("tx").alias("hub"), F.ceil(F.col("k") / HUB_ARCS).cast("int").alias("places")))
        hubs = None if hubs.isEmpty() else hubs
    place = F.lit(0)
    if hubs is not None:
        arcs, place = arcs.join(hubs, F.col("tx") == F.col("hub"), "left"), F.coalesce(F.pmod(F.xxhash64("rx"), F.col("places")).cast("int"), F.lit(0))
    arcs = cut_by(arcs.select("tx", place.alias("place"), "rx"), parts, "tx", "place")

    def written(df: DataFrame, t: int) -> DataFrame:
        df.write.parquet(f"{folder}/t={t}")
        return spark.read.schema(schema).parquet(f"{folder}/t={t}")

    began = time.time()
    typed = seeds.select(F.col("node").cast("long"), F.col("run").cast("int"), F.col("item").cast("long"), F.col("value").cast("long"))
    delta = written(typed.groupBy(*KEYS).agg(lattice.aggregate("value").alias("value")).withColumn("old", F.lit(None).cast("long")), 0)
    base_rows = delta.count()
    base = cut_by(delta.select(*KEYS, "value"), parts, *KEYS) if base_rows else delta.select(*KEYS, "value")
    recent: list[DataFrame] = []
    recent_rows, t, seconds, truncated = 0, 0, [time.time() - began], False
    while base_rows:
        if max_iter is not None and t >= max_iter:
            truncated = True
            break
        began = time.time()
        t += 1
        sending = delta.select(*KEYS, "value") if propagation == "delta" else _state(base, recent, lattice)
        places = F.array(F.lit(0))
        if hubs is not None:
            sending, places = sending.join(hubs, F.col("node") == F.col("hub"), "left"), F.sequence(F.lit(0), F.coalesce(F.col("places"), F.lit(1)) - 1)
        sending = sending.select(*KEYS, "value", F.explode(places).alias("at"))
        met = sending.join(arcs, (F.col("node") == F.col("tx")) & (F.col("at") == F.col("place"))).select(F.col("rx").alias("node"), "run", "item", "value")
        candidates = met.groupBy(*KEYS).agg(lattice.aggregate("value").alias("new"))
        known = candidates.join(base.withColumnRenamed("value", "kept"), KEYS, "left")
        if recent:
            late = _merged(recent, lattice).withColumnRenamed("value", "late")
            known = known.join(late, KEYS, "left").withColumn("old", F.when(F.col("late").isNull(), F.col("kept")).otherwise(F.col("late")))
        else:
            known = known.withColumnRenamed("kept", "old")
        changed = known.where(F.col("old").isNull() | lattice.news(F.col("new"), F.col("old")))
        if prune is not None:
            changed = prune(changed, _state(base, recent, lattice), t)
        value = F.when(F.col("old").isNull(), F.col("new")).otherwise(lattice.merge(F.col("new"), F.col("old")))
        delta = written(changed.select(*KEYS, value.alias("value"), "old"), t)
        rows = delta.count()  # from the files' footers
        if not rows:
            break
        seconds.append(time.time() - began)
        recent.append(delta.select(*KEYS, "value"))
        recent_rows += rows
        if recent_rows > COMPACT_AT * base_rows or len(recent) >= 8:
            base = cut_by(_state(base, recent, lattice), parts, *KEYS)
            base_rows, recent, recent_rows = base_rows + recent_rows, [], 0
    return Rounds(spark.read.schema(schema + ", t int").parquet(folder), seconds, truncated)


def _merged(tables: list[DataFrame], lattice: Lattice) -> DataFrame:
    out = tables[0]
    for df in tables[1:]:
        out = out.unionByName(df)
    return out.groupBy(*KEYS).agg(lattice.aggregate("value").alias("value"))


def _state(base: DataFrame, recent: list[DataFrame], lattice: Lattice) -> DataFrame:
    return _merged([base.select(*KEYS, "value"), *recent], lattice) if recent else base.select(*KEYS, "value")
