"""Spatial partitioning with ghost atoms: every box is padded by the reach of all layers and computed on its own."""

from __future__ import annotations


from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from halograph.functions.ring import whole
from halograph.graph.halo import k_hop_halo
from halograph.graph.neighbors import neighbor_list
from halograph.graph.lanes import Lanes
from halograph.graph.runtime import conv_layer, initial_state, renewed, system_edges, weighted
from halograph.graph.scratch import Scratch
from halograph.potentials import PotentialSpec, potential
from halograph.sources.systems import Cell, System


def boxes(cell: Cell, p: int, decomposition: str = "slab") -> tuple[int, int, int]:
    """How many boxes along each axis: slabs along the longest, or blocks as cubic as p allows."""
    if decomposition == "slab":
        return tuple(p if k == cell.longest else 1 for k in range(3))
    n = [1, 1, 1]
    rest, f = p, 2
    while rest > 1:
        while rest % f == 0:
            k = max(range(3), key=lambda k: (cell.lengths[k] / n[k], -k))
            n[k] *= f
            rest //= f
        f += 1
    return tuple(n)


def _wall(k: int, i: int, n: int, cell: Cell) -> int:
    """First whole coordinate of slab i of n."""
    return -(-i * cell.lengths[k] // n)


def _places(axis: str, k: int, n: int, cell: Cell, pad: int) -> Column:
    """Boxes along one axis that hold x or an image of it within the pad: array of (box, image, own)."""
    x = F.col(axis) - cell.origin[k]
    own = F.greatest(F.lit(0), F.least(F.lit(n - 1), whole(x * n, cell.lengths[k]))).cast("int")
    reach = -(-pad // cell.lengths[k]) if cell.periodic[k] else 0
    if n == 1 and not cell.periodic[k]:
        return F.array(F.struct(own.alias("box"), F.lit(0).alias("image"), F.lit(True).alias("own")))
    options = []
    for image in range(-reach, reach + 1):
        at = x + image * cell.lengths[k]
        for i in range(n):
            low, high = _wall(k, i, n, cell), _wall(k, i + 1, n, cell)
            mine = (own == i) if image == 0 else F.lit(False)
            near = mine | (at >= low - pad) & (at < high + pad)
            options.append(F.when(near, F.struct(F.lit(i).alias("box"), F.lit(image).alias("image"), mine.alias("own"))))
    return F.array_compact(F.array(*options))


def padded(system: System, p: int, pad: int, decomposition: str = "slab") -> DataFrame:
    """box, atom_id, image, own, species, x, y, z: every copy of an atom in every padded box (positions unwrapped)."""
    cell, n = system.cell, boxes(system.cell, p, decomposition)
    out = system.atoms.select("atom_id", "species", "x", "y", "z")
    for k, a in enumerate("xyz"):
        out = out.withColumn(f"p{a}", F.explode(_places(a, k, n[k], cell, pad)))
    box = (F.col("px.box") * n[1] + F.col("py.box")) * n[2] + F.col("pz.box")
    moved = [(F.col(a) + F.col(f"p{a}.image").cast("long") * cell.lengths[k]).alias(a) for k, a in enumerate("xyz")]
    far = [F.col(f"p{a}.image").cast("long") + 1000 for a in "xyz"]
    image = (far[0] * 2000 + far[1]) * 2000 + far[2]
    return out.select(box.cast("int").alias("box"), "atom_id", image.alias("image"), (F.col("px.own") & F.col("py.own") & F.col("pz.own")).alias("own"), "species", *moved)


def ghost_count(system: System, p: int, reach: int, decomposition: str = "slab") -> DataFrame:
    """copies, ghosts: atoms computed in all padded boxes, and those beyond the atoms themselves."""
    all_ = padded(system, p, reach, decomposition).agg(F.count(F.lit(1)).alias("copies"), F.sum(F.col("own").cast("long")).alias("n"))
    return all_.select("copies", (F.col("copies") - F.col("n")).alias("ghosts"))


def _layers(nodes: DataFrame, edges: DataFrame, spec: PotentialSpec, lanes: Lanes) -> DataFrame:
    """All layers of every box in its lane, with no exchange at all: lane, part_id, atom_id and features of all copies."""
    model = potential(spec)
    state = lanes.keep(lanes.dealt(initial_state(nodes, model)), "first")
    edges = lanes.keep(lanes.dealt(edges), "edges")
    for _ in range(spec.layers):
        state = lanes.keep(renewed(conv_layer(state, None, edges, model, ["lane"]), model), "state")
    return state


def run_spatial(system: System, spec: PotentialSpec, p: int, *, decomposition: str = "slab", pad: int | None = None, scratch: Scratch | None = None) -> DataFrame:
    """part_id, atom_id and features of the owned atoms after all layers, without any exchange between boxes.

    ``pad`` is layers * cutoff unless given; less makes the result wrong for more than one layer. Atom-graph models whose
    setup is local.
    """
    model = potential(spec)
    lanes = Lanes(p, scratch or Scratch(system.atoms.sparkSession))
    copies = padded(system, p, spec.interaction_range if pad is None else pad, decomposition)
    # Boxes become one open system: each is moved far from all others, so one neighbour list serves them. A copy of an
    # atom has a number of its own.
    stride = 4 * (max(system.cell.lengths) + 2 * spec.interaction_range + spec.cutoff)
    copies = lanes.scratch.keep(copies.withColumnRenamed("atom_id", "atom").withColumn("atom_id", F.monotonically_increasing_id()), "copies")
    apart = copies.select("atom_id", "species", (F.col("x") + F.col("box").cast("long") * stride).alias("x"), "y", "z", F.col("box").alias("part_id"))
    edges = neighbor_list(apart, Cell(system.cell.lengths, (False,) * 3), spec.cutoff, carry=("part_id",)).withColumnRenamed("dst_part_id", "part_id").drop("src_part_id")
    edges = weighted(edges, model).withColumn("lane", lanes.lane(F.col("part_id")))
    nodes = apart.select(lanes.lane(F.col("part_id")).alias("lane"), "part_id", "atom_id", "species")
    state = _layers(nodes, edges, spec, lanes)
    mine = copies.filter("own").select("atom_id", "atom")
    return state.join(mine, "atom_id").select("part_id", F.col("atom").alias("atom_id"), *model.state)


def run_spatial_hops(system: System, spec: PotentialSpec, assign: DataFrame, p: int, scratch: Scratch | None = None) -> DataFrame:
    """The same with padding by hops: each part holds all nodes within as many hops as there are layers."""
    model = potential(spec)
    lanes = Lanes(p, scratch or Scratch(system.atoms.sparkSession))
    edges = lanes.scratch.keep(weighted(system_edges(system, spec), model), "edges")
    halo = k_hop_halo(edges, assign, spec.layers)
    inside = lanes.scratch.keep(assign.select("part_id", "atom_id").union(halo.select("part_id", "atom_id")), "inside")
    lane = lanes.lane(F.col("part_id"))
    local = edges.join(inside.withColumnRenamed("atom_id", "dst"), "dst").withColumn("lane", lane)
    state = _layers(inside.join(system.atoms.select("atom_id", "species"), "atom_id").withColumn("lane", lane), local, spec, lanes)
    return state.join(assign, ["part_id", "atom_id"], "left_semi").drop("lane")
