"""Cost and accuracy measures. Capacities and memory are modelled numbers, not those of a device."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from halograph.graph.halo import with_owners
from halograph.graph.partition import wall_partition
from halograph.graph.runtime import PartitionedGraph, owned_system_edges
from halograph.potentials import PotentialSpec, potential
from halograph.sources.systems import System

#: Bytes of a stored number.
NUMBER = 8


def step_time(runs: DataFrame) -> DataFrame:
    """Microseconds for each atom and step of every run."""
    key = [c for c in ("workload", "system_id", "family", "parts") if c in runs.columns]
    return runs.groupBy(*key).agg((F.sum("wall_us") / F.sum(F.col("atoms") * F.col("steps"))).alias("us_per_atom_step"), F.max("atoms").alias("atoms"))


def inference_time(runs: DataFrame, warm: int = 10) -> DataFrame:
    """Mean of the repetitions, numbered from 0, after the first ``warm``."""
    key = [c for c in ("workload", "system_id", "family", "parts", "layers", "width") if c in runs.columns]
    return runs.filter(F.col("rep") >= warm).groupBy(*key).agg(F.avg("wall_us").alias("wall_us"), F.max("atoms").alias("atoms"))


def scaling(times: DataFrame, mode: str) -> DataFrame:
    """Time against that of one part, with the ideal: 1/p for ``strong`` (same system), 1 for ``weak`` (same share)."""
    first = F.first_value("wall_us").over(Window.partitionBy("family").orderBy("parts"))
    return times.withColumns({"relative": F.col("wall_us") / first, "ideal": ideal(F.col("parts"), mode)})


def ideal(p: Column, mode: str) -> Column:
    return {"strong": 1 / p, "weak": F.lit(1.0), "capacity": p.cast("double")}[mode]


def against_range(times: DataFrame, base: int) -> DataFrame:
    """Time as a multiple of that at the base interaction range, and the slope of a straight line through all ranges."""
    zero = F.max(F.when(F.col("reach") == base, F.col("wall_us"))).over(Window.partitionBy("family"))
    rel = times.withColumn("relative", F.col("wall_us") / zero)
    return rel.join(rel.groupBy("family").agg(F.regr_slope("relative", "reach").alias("slope")), "family")


def speed_up(times: DataFrame) -> DataFrame:
    """Speed-up over one part, its share of the ideal, and the fall of time per atom."""
    first = F.first_value("wall_us").over(Window.partitionBy("family").orderBy("parts"))
    per_atom = F.col("wall_us") / F.col("atoms")
    first_atom = F.first_value(per_atom).over(Window.partitionBy("family").orderBy("parts"))
    return times.withColumns({"speed_up": first / F.col("wall_us"), "efficiency": first / F.col("wall_us") / F.col("parts"), "per_atom_gain": first_atom / per_atom})


def partitioner_ratio(times: DataFrame) -> DataFrame:
    """Time of every partitioner as a multiple of the walls'."""
    wall = F.max(F.when(F.col("method") == "wall", F.col("wall_us"))).over(Window.partitionBy("system_id"))
    return times.withColumn("ratio", F.col("wall_us") / wall)


def layer_updates(graph: PartitionedGraph) -> DataFrame:
    """layer, computed, needed: node updates that each layer of the last run made, by its kept rows, and the atoms there are."""
    atoms = graph.nodes.agg(F.count(F.lit(1)).alias("needed"))
    out = None
    for k, layer in enumerate(graph.trace):
        row = layer.agg(F.count(F.lit(1)).alias("computed")).crossJoin(atoms).select(F.lit(k).cast("long").alias("layer"), "computed", "needed")  # one row each
        out = row if out is None else out.union(row)
    return out


def transfer_volume(buckets: DataFrame, width: int = 1) -> DataFrame:
    """rows and bytes sent in each layer, and the nodes that two parts or more need."""
    to = buckets.filter("kind = 'TO'")
    per_node = to.groupBy("atom_id").agg(F.count(F.lit(1)).alias("n"))
    return per_node.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("sent"), (F.coalesce(F.sum("n"), F.lit(0)) * width * NUMBER).alias("bytes"), F.count(F.when(F.col("n") > 1, 1)).alias("overlap"))


def partition_quality(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """border_nodes, edge_cut, peer_pairs, and balance of owned nodes: most, least and most over mean."""
    crossing = with_owners(edges, assign).filter("p_src <> part_id")
    cut = crossing.agg(F.count(F.lit(1)).alias("edge_cut"))
    border = crossing.select("part_id", "src").distinct().agg(F.count(F.lit(1)).alias("border_nodes"))
    peers = crossing.select("part_id", "p_src").distinct().agg(F.count(F.lit(1)).alias("peer_pairs"))
    sizes = assign.groupBy("part_id").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n").alias("most_nodes"), F.min("n").alias("least_nodes"), (F.max("n") / F.avg("n")).alias("imbalance"))
    return border.crossJoin(cut).crossJoin(peers).crossJoin(sizes)  # one row each


def _bytes(spec: PotentialSpec) -> Column:
    kept = (F.col("nodes") + F.col("halo")) * (spec.layers + 1) * spec.width + F.col("edges") * (6 + spec.width) + F.col("links") * 3
    return kept * NUMBER


def memory_model(graph: PartitionedGraph, spec: PotentialSpec) -> DataFrame:
    """part_id, nodes, halo, edges, links, bytes: what a part holds, by counts. Features of all layers are kept."""
    n = lambda df, name: df.groupBy("part_id").agg(F.count(F.lit(1)).alias(name))
    out = n(graph.nodes, "nodes").join(n(graph.halo, "halo"), "part_id", "left").join(n(graph.edges, "edges"), "part_id", "left")
    if graph.bonds is None:
        out = out.withColumn("links", F.lit(0).cast("long"))
    else:
        parts = graph.nodes.select("lane", "part_id").distinct()
        out = out.join(n(graph.bonds.links.select("lane").join(F.broadcast(parts), "lane"), "links"), "part_id", "left")  # a row for each part
    return out.na.fill(0).withColumn("bytes", _bytes(spec))


def memory_counts(system: System, spec: PotentialSpec, p: int) -> DataFrame:
    """The same by wall for a system that is not run: only edges are counted, and links by the degrees of their bonds."""
    assign = wall_partition(system.atoms, system.cell, p)
    edges = owned_system_edges(system, system.atoms.join(assign, "atom_id"), spec)
    n = F.count(F.lit(1))
    at_node = edges.groupBy("part_id", "dst").agg(n.alias("edges"), F.count(F.when(F.col("d2") <= spec.bond_cutoff**2, 1)).alias("ends"))
    per_part = at_node.groupBy("part_id").agg(F.sum("edges").alias("edges"))
    if potential(spec).uses_bonds:
        # as many bonds end at an atom as begin there; a link belongs to the part in which its second bond ends
        begins = edges.filter(F.col("d2") <= spec.bond_cutoff**2).groupBy("part_id", "src").agg(n.alias("begin"))
        into = at_node.groupBy(F.col("dst").alias("src")).agg(F.sum("ends").alias("ends"))
        links = begins.join(into, "src").groupBy("part_id").agg(F.sum(F.col("begin") * (F.col("ends") - 1)).alias("links"))
        per_part = per_part.join(links, "part_id", "left")
    else:
        per_part = per_part.withColumn("links", F.lit(0).cast("long"))
    halo = edges.filter("p_src <> part_id").select("part_id", "src").distinct().groupBy("part_id").agg(n.alias("halo"))
    nodes = assign.groupBy("part_id").agg(n.alias("nodes"))
    return nodes.join(halo, "part_id", "left").join(per_part, "part_id", "left").na.fill(0).withColumn("bytes", _bytes(spec))


def over_budget(memory: DataFrame, budget: int) -> DataFrame:
    """out_of_memory: whether any part passes the budget."""
    return memory.agg((F.max("bytes") > budget).alias("out_of_memory"), F.max("bytes").alias("most_bytes"))


def max_capacity(build, budget: int, start: int = 1) -> tuple[int, int]:
    """(size, atoms) of the largest system whose every part fits: sizes are doubled until one fails, then bisected.
    build(size) gives (atoms, most bytes)."""
    best, low, high = (0, 0), 1, start
    while True:
        atoms, most = build(high)
        if most > budget:
            break
        best, low, high = (high, atoms), high + 1, 2 * high
    high -= 1
    while low <= high:
        mid = (low + high) // 2
        atoms, most = build(mid)
        if most <= budget:
            best, low = (mid, atoms), mid + 1
        else:
            high = mid - 1
    return best


def ns_days(us: float, n: int, dt_fs: float) -> float:
    """Days that a nanosecond takes at so many microseconds for each atom and step."""
    return us * n * (1e6 / dt_fs) / 8.64e10


def exactness(a: DataFrame, b: DataFrame, key: str = "atom_id") -> DataFrame:
    """rows, missing, max_error: how far two results are apart; all zero but rows when equal."""
    values = [c for c in a.columns if c != key and c in b.columns and c != "part_id"]
    both = a.select(key, *[F.col(c).alias(f"a_{c}") for c in values]).join(b.select(key, *[F.col(c).alias(f"b_{c}") for c in values]), key, "full_outer")
    gap = F.greatest(F.lit(0), *[F.abs(F.col(f"a_{c}") - F.col(f"b_{c}")) for c in values])
    gone = F.col(f"a_{values[0]}").isNull() | F.col(f"b_{values[0]}").isNull()
    return both.agg(F.count(F.lit(1)).alias("rows"), F.count(F.when(gone, 1)).alias("missing"), F.coalesce(F.max(gap), F.lit(0)).alias("max_error"))


def growth_exponent(points: DataFrame, x: str, y: str) -> DataFrame:
    """Slope of log y over log x."""
    return points.agg(F.regr_slope(F.ln(y), F.ln(x)).alias("exponent"))
