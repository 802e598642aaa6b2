"""The experiments as timed runs: every function gives rows of one runs table, which the measures then read.

``python -m halograph.workloads strong weak --sf /root/testdata/sf0.1`` prints the rows of each workload and its measure.
A part is a lane, so p parts keep p cores busy; times are of this machine and of surrogate models on stand-in systems.
"""

from __future__ import annotations

import argparse
import json
import time
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from halograph import measures
from halograph.baselines.spatial import run_spatial
from halograph.dynamics import md_run
from halograph.graph import partition
from halograph.graph.runtime import backward, build_partitioned_graph, forward
from halograph.graph.scratch import Scratch
from halograph.potentials import PotentialSpec
from halograph.sources import systems

RUNS = "workload string, system_id string, family string, method string, parts int, layers int, width int, reach long, rep int, wall_us long, atoms long, steps int, most_bytes long, failed boolean"
PARTS = (1, 2, 4, 8)
MODEL = PotentialSpec("many_body", layers=2, cutoff=3500)
FAMILIES = {
    "many_body": MODEL, "light": replace(MODEL, family="light"), "invariant_bond": replace(MODEL, family="invariant_bond", bond_cutoff=2000), "smooth": replace(MODEL, family="smooth"),
}
#: Modelled bytes that a part may hold.
BUDGET = 256 << 20


class Bench:
    """Collects rows; ``reps`` runs of each, of which the first ``warm`` are left out of the means."""

    def __init__(self, spark: SparkSession, sf_dir: str, reps: int = 2, warm: int = 1, budget: int = BUDGET):
        self.spark, self.sf_dir, self.reps, self.warm, self.budget = spark, sf_dir, reps, warm, budget
        self.rows: list[tuple] = []

    def note(self, workload, system, spec, method, parts, rep, wall, atoms, steps=1, most=0, failed=False) -> None:
        self.rows.append((workload, system, spec.family, method, parts, spec.layers, spec.width, spec.interaction_range, rep, wall, atoms, steps, most, failed))

    def table(self) -> DataFrame:
        return self.spark.createDataFrame(self.rows, RUNS)

    def inference(self, workload: str, name: str, system, spec: PotentialSpec, p: int, method: str = "wall", forces: bool = True, setup: str = "distributed", reps: int | None = None) -> None:
        """Times forward and backward over a graph that is built before; a part over the budget is a failed run."""
        scratch = Scratch(self.spark)
        try:
            graph = build_partitioned_graph(system, spec, p, method=method, scratch=scratch)
            atoms = graph.nodes.count()
            most = measures.memory_model(graph, spec).agg(F.max("bytes")).first()[0] or 0
            if most > self.budget:
                self.note(workload, name, spec, method, p, 0, 0, atoms, 1, most, True)
                return
            for rep in range(reps or self.reps):
                began = time.time()
                state = forward(graph, spec, setup=setup)
                (backward(graph, spec) if forces else state).write.format("noop").mode("overwrite").save()
                self.note(workload, name, spec, method, p, rep, int((time.time() - began) * 1e6), atoms, 1, most)
        finally:
            scratch.drop()

    def padded(self, workload: str, name: str, system, spec: PotentialSpec, p: int, how: str = "slab") -> None:
        """The spatial baseline: each run pads, builds and computes, as nothing outlives it but the copies."""
        atoms = system.atoms.count()
        for rep in range(self.reps):
            scratch = Scratch(self.spark)
            began = time.time()
            run_spatial(system, spec, p, decomposition=how, scratch=scratch).write.format("noop").mode("overwrite").save()
            self.note(workload, name, spec, how, p, rep, int((time.time() - began) * 1e6), atoms)
            scratch.drop()


def capacity(b: Bench) -> DataFrame:
    """Most atoms for parts, by family, under the budget of modelled bytes."""
    from halograph.queries.models import capacity_points

    rows = [r for f in FAMILIES for r in capacity_points(b.spark, f, PARTS, b.budget // 32)]
    return b.spark.createDataFrame(rows, "family string, parts int, atoms long, relative double").withColumn("ideal", F.col("parts").cast("double"))


def strong(b: Bench) -> DataFrame:
    """One system, more parts; the smooth model's first features are computed in one task."""
    s = systems.quartz(b.spark, b.sf_dir)
    for f, spec in FAMILIES.items():
        for p in PARTS:
            b.inference("strong", "quartz", s, spec, p, setup="single" if f == "smooth" else "distributed")
    return measures.speed_up(measures.scaling(measures.inference_time(b.table().filter("workload = 'strong' AND NOT failed"), b.warm), "strong"))


def weak(b: Bench) -> DataFrame:
    """As many copies of the system as parts."""
    for f, spec in FAMILIES.items():
        for p in PARTS:
            b.inference("weak", "quartz", systems.quartz(b.spark, b.sf_dir, p), spec, p, setup="single" if f == "smooth" else "distributed")
    return measures.scaling(measures.inference_time(b.table().filter("workload = 'weak' AND NOT failed"), b.warm), "weak")


def reach(b: Bench, layers=(2, 4, 6, 8, 10)) -> DataFrame:
    """Interaction range by the number of layers at 5 angstrom, 8 parts, one width for all families."""
    s = systems.quartz(b.spark, b.sf_dir)
    for f, spec in FAMILIES.items():
        for n in layers:
            b.inference("reach", "quartz", s, replace(spec, layers=n, cutoff=5000), 8, forces=False)
    times = b.table().filter("workload = 'reach' AND NOT failed").groupBy("family", "reach").agg(F.min("wall_us").alias("wall_us"))
    return measures.against_range(times, layers[0] * 5000)


def size(b: Bench, widths=(1, 2, 4, 8)) -> DataFrame:
    """Width at a fixed number of layers: parameters, time and modelled bytes."""
    s = systems.quartz(b.spark, b.sf_dir)
    for w in widths:
        b.inference("size", "quartz", s, replace(MODEL, width=w), 8, forces=False)
    parameters = F.col("layers") * (F.col("width") * F.col("width") + 16 * F.col("width"))
    return b.table().filter("workload = 'size'").groupBy(parameters.alias("parameters")).agg(F.min("wall_us").alias("wall_us"), F.max("most_bytes").alias("most_bytes"))


def real(b: Bench, parts=(1, 4, 8)) -> DataFrame:
    """Five stand-ins on 1, 4 and 8 parts: microseconds for an atom and step, atoms, and what passes the budget."""
    from halograph.queries.models import REAL, real_system

    for name in REAL:
        s, cutoff = real_system(name, b.spark, b.sf_dir)
        for p in parts:
            b.inference("real", name, s, replace(MODEL, cutoff=cutoff), p, forces=s.cell is not None)
    t = b.table().filter("workload = 'real'")
    failed = t.groupBy("system_id", "parts").agg(F.max("failed").alias("out_of_memory"))
    best = t.filter("NOT failed").withColumn("rank", F.row_number().over(measures.Window.partitionBy("system_id", "parts").orderBy("wall_us"))).filter("rank = 1")
    return failed.join(measures.step_time(best.drop("family")), ["system_id", "parts"], "left").drop("workload")


def spatial(b: Bench, parts=(4, 8)) -> DataFrame:
    """Graph partitioning against padded boxes with one spec: time, both with the building of the graph, and modelled bytes."""
    for name, build, spec in (("quartz", systems.quartz, MODEL), ("liquid", systems.liquid, replace(MODEL, cutoff=1000))):
        s = build(b.spark, b.sf_dir)
        for p in parts:
            for how in ("slab", "block3d"):
                b.padded("spatial", name, s, spec, p, how)
            for rep in range(b.reps):
                scratch = Scratch(b.spark)
                began = time.time()
                graph = build_partitioned_graph(s, spec, p, scratch=scratch)
                forward(graph, spec).write.format("noop").mode("overwrite").save()
                wall = int((time.time() - began) * 1e6)
                b.note("spatial", name, spec, "graph", p, rep, wall, graph.nodes.count())
                scratch.drop()
    return b.table().filter("workload = 'spatial'").groupBy("system_id", "parts", "method").agg(F.min("wall_us").alias("wall_us"), (F.min("wall_us") / F.max("atoms")).alias("us_per_atom"))


def partitioners(b: Bench, methods=partition.METHODS) -> DataFrame:
    """Time of every partitioner against the walls', on eight parts."""
    s = systems.quartz(b.spark, b.sf_dir)
    for m in methods:
        b.inference("partitioners", "quartz", s, MODEL, 8, method=m)
    times = b.table().filter("workload = 'partitioners'").groupBy("system_id", "method").agg(F.min("wall_us").alias("wall_us"))
    return measures.partitioner_ratio(times)


def rival(b: Bench) -> DataFrame:
    """The rival under padding against the families under graph partitioning, matched in parameters."""
    s = systems.quartz(b.spark, b.sf_dir)
    b.padded("rival", "quartz", s, replace(MODEL, family="rival").matched_to(160), 8)
    for spec in FAMILIES.values():
        b.inference("rival", "quartz", s, spec.matched_to(160), 8, forces=False)
    return b.table().filter("workload = 'rival'").groupBy("family").agg(F.min("wall_us").alias("wall_us"), F.max("most_bytes").alias("most_bytes"))


def million(b: Bench, copies: int = 7) -> DataFrame:
    """One evaluation, with forces, of about a million atoms on eight parts, and the days a nanosecond would take."""
    b.inference("million", "quartz", systems.quartz(b.spark, b.sf_dir, copies), MODEL, 8, reps=1)
    us = F.col("wall_us") / F.col("atoms")
    return b.table().filter("workload = 'million'").select("atoms", (F.col("wall_us") / 1e6).alias("seconds"), us.alias("us_per_atom"), (us * F.col("atoms") * 1e6 / 8.64e10).alias("days_per_nanosecond"))


def shapes(b: Bench) -> DataFrame:
    """As many atom steps in two shapes: many atoms for few steps, few atoms for many."""
    spec = replace(MODEL, layers=1, cutoff=3000)
    for copies, steps in ((4, 1), (1, 4)):
        s = systems.quartz(b.spark, b.sf_dir, copies)
        atoms, scratch, began = s.atoms.count(), Scratch(b.spark), time.time()
        md_run(s, spec, 8, steps, scratch=scratch).write.format("noop").mode("overwrite").save()
        b.note("shapes", f"{copies} copies", spec, "wall", 8, 0, int((time.time() - began) * 1e6), atoms, steps)
        scratch.drop()
    return measures.step_time(b.table().filter("workload = 'shapes'"))


WORKLOADS = {f.__name__: f for f in (capacity, strong, weak, reach, size, real, spatial, partitioners, rival, million, shapes)}


def main() -> None:
    parser = argparse.ArgumentParser()
    parser.add_argument("names", nargs="*", default=list(WORKLOADS))
    parser.add_argument("--sf", default="/root/testdata/sf0.1")
    parser.add_argument("--reps", type=int, default=2, help="20 with --warm 10 is what the experiments use")
    parser.add_argument("--warm", type=int, default=1)
    parser.add_argument("--cpus", default="8")
    a = parser.parse_args()
    spark = (
        SparkSession.builder.master(f"local[{a.cpus}]").config("spark.sql.shuffle.partitions", a.cpus).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "12g").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    bench = Bench(spark, a.sf, a.reps, a.warm)
    for name in a.names:
        for row in WORKLOADS[name](bench).collect():
            print(json.dumps({"workload": name, **row.asDict()}, default=str), flush=True)


if __name__ == "__main__":
    main()
