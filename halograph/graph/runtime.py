"""Graph-parallel inference: layers over parts that lie in lanes, with one shuffle of border features each, both ways."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from halograph.graph.bondgraph import BondTables, build_bonds
from halograph.graph.halo import assign_buckets
from halograph.graph.lanes import Lanes, within_lanes
from halograph.graph.neighbors import explicit_graph, neighbor_list
from halograph.graph.partition import partition
from halograph.graph.scratch import Scratch
from halograph.potentials import Potential, PotentialSpec, check_adjoints, potential
from halograph.sources.systems import System

AXES = "xyz"


@dataclass
class PartitionedGraph:
    """All parts of a system in tables bucketed by lane, a lane for each part; edges lie where their destination lives."""

    lanes: Lanes
    nodes: DataFrame  # lane, part_id, atom_id, species
    edges: DataFrame  # lane, part_id, edge columns, w, p_src
    halo: DataFrame  # part_id, atom_id, hop, owner
    outbox: DataFrame  # lane, to_lane, atom_id: what an owner sends in every layer
    assign: DataFrame
    bonds: BondTables | None = None
    trace: list[DataFrame] = field(default_factory=list)
    bond_trace: list[DataFrame] = field(default_factory=list)

    @property
    def p(self) -> int:
        return self.lanes.p

    @property
    def buckets(self) -> DataFrame:
        return assign_buckets(self.assign, self.halo)


def system_edges(system: System, spec: PotentialSpec) -> DataFrame:
    if system.edges is not None:
        return explicit_graph(system.edges)
    return neighbor_list(system.atoms, system.cell, spec.cutoff)


def weighted(edges: DataFrame, model: Potential) -> DataFrame:
    return edges if "w" in edges.columns else edges.withColumn("w", model.edge_weight())


def owned_system_edges(system: System, atoms: DataFrame, spec: PotentialSpec, skin: int = 0) -> DataFrame:
    """Edges with the part of both ends, p_src and part_id. A neighbour list carries them along from the atoms (with
    part_id), so edges are not moved to look them up; a given graph has to be joined."""
    if system.edges is None:
        found = neighbor_list(atoms, system.cell, spec.cutoff, skin=skin, carry=("part_id",))
        return found.withColumnsRenamed({"src_part_id": "p_src", "dst_part_id": "part_id"})
    end = lambda e, name: atoms.select(F.col("atom_id").alias(e), F.col("part_id").alias(name))
    return explicit_graph(system.edges).join(end("dst", "part_id"), "dst").join(end("src", "p_src"), "src")


def build_partitioned_graph(system: System, spec: PotentialSpec, p: int, *, method: str = "wall", assign: DataFrame | None = None, scratch: Scratch | None = None, skin: int = 0) -> PartitionedGraph:
    """Neighbour list, owners, borders, outboxes and, for models that use it, the bond graph, for all parts at once.

    Edges are written once, in their lanes; all later steps but the outboxes stay inside lanes.
    """
    model, scratch = potential(spec), scratch or Scratch(system.atoms.sparkSession)
    lanes = Lanes(p, scratch)
    if assign is None:
        assign = partition(system.atoms, None if method in GEOMETRIC else system_edges(system, spec), system.cell, p, method, scratch)
    atoms = system.atoms.join(assign, "atom_id")
    edges = weighted(owned_system_edges(system, atoms, spec, skin), model)
    edges = lanes.keep(lanes.dealt(edges.withColumn("lane", lanes.lane(F.col("part_id")))), "edges")
    nodes = lanes.keep(lanes.dealt(atoms.select(lanes.lane(F.col("part_id")).alias("lane"), "part_id", "atom_id", "species")), "nodes")
    crossing = edges.filter("p_src <> part_id").select("lane", "part_id", F.col("src").alias("atom_id"), F.col("p_src").alias("owner")).distinct()
    with within_lanes(edges.sparkSession):
        halo = scratch.keep(crossing.select("part_id", "atom_id", F.lit(1).alias("hop"), "owner", "lane"), "halo")
    outbox = halo.select(lanes.lane(F.col("owner")).alias("lane"), F.col("lane").alias("to_lane"), "atom_id")
    graph = PartitionedGraph(lanes, nodes, edges, halo.drop("lane"), lanes.keep(lanes.dealt(outbox), "outbox"), assign)
    if model.uses_bonds:
        short = edges if system.edges is not None else edges.filter(F.col("d2") <= (spec.bond_cutoff + skin) ** 2)
        graph.bonds = build_bonds(short, lanes)
    return graph


#: Partition rules that need no edges.
GEOMETRIC = ("wall", "hash", "random", "blocks", "rcb", "morton")


def initial_state(nodes: DataFrame, model: Potential, setup: str = "distributed") -> DataFrame:
    """The first features of nodes (atom_id, species and lane and part where they have them). ``single`` computes them in
    one task, as a one-time step on one device."""
    where = [c for c in ("lane", "part_id", "atom_id") if c in nodes.columns]
    if setup == "single":
        nodes = nodes.coalesce(1)
    first = nodes.select(*where, "species", *[c.alias(n) for n, c in model.init_node().items()])
    if model.spec.family == "smooth":
        counts = nodes.groupBy("species").agg(F.count(F.lit(1)).alias("n"))
        if setup == "single":
            counts = counts.coalesce(1)
        scaled = lambda s: model.a.mod(F.col(s) * model.a.mod(F.col("n").cast(model.a.kind)))
        # a row for each species
        first = first.join(F.broadcast(counts), "species").select(*where, *[(scaled(s) if s.startswith("h") else F.col(s)).alias(s) for s in model.state])
    return first.select(*where, *model.state)


def exchange(state: DataFrame, outbox: DataFrame, lanes: Lanes, key: str = "atom_id") -> DataFrame:
    """What each lane receives, the state of its border nodes from their owners: the one shuffle of a layer."""
    values = [c for c in state.columns if c not in ("lane", "part_id", key)]
    sent = outbox.join(state.drop("part_id").hint("shuffle_hash"), ["lane", key])
    return lanes.dealt(sent.select(F.col("to_lane").alias("lane"), key, *values))


def at_source(edges: DataFrame, state: DataFrame, received: DataFrame | None, on: list[str], values: list[str], end: str = "src", key: str = "atom_id") -> DataFrame:
    """Edges with the values of the node at one end: from the part's own state, or from what it received."""
    own = state.select(*on, F.col(key).alias(end), *values)
    if received is None:
        return edges.join(own.hint("shuffle_hash") if on else own, [*on, end])
    came = received.select(*on, F.col(key).alias(end), *[F.col(v).alias(f"r_{v}") for v in values])
    both = edges.join(own.hint("shuffle_hash"), [*on, end], "left").join(came.hint("shuffle_hash"), [*on, end], "left")
    return both.withColumns({v: F.coalesce(v, f"r_{v}") for v in values}).drop(*[f"r_{v}" for v in values])


def message_sums(edges: DataFrame, state: DataFrame, received: DataFrame | None, model: Potential, on: list[str]) -> DataFrame:
    carried = at_source(edges, state, received, on, model.state)
    return carried.groupBy(*on, F.col("dst").alias("atom_id")).agg(*[F.sum(c).alias(f"sum_{n}") for n, c in model.message().items()])


def conv_layer(state: DataFrame, received: DataFrame | None, edges: DataFrame, model: Potential, on: list[str], bond_sums: DataFrame | None = None) -> DataFrame:
    """Old state, message sums and, as new_<name>, the new state of the owned nodes. With lanes nothing is shuffled."""
    hint = (lambda df: df.hint("shuffle_hash")) if on else (lambda df: df)
    joined = state.join(hint(message_sums(edges, state, received, model, on)), [*on, "atom_id"], "left")
    names = list(model.message())
    if model.uses_bonds:
        joined = joined.join(hint(bond_sums), [*on, "atom_id"], "left")
        names.append("bond")
    summed = joined.withColumns({f"sum_{n}": F.coalesce(f"sum_{n}", model.a.zero()) for n in names})
    return summed.select("*", *[c.alias(f"new_{n}") for n, c in model.update().items()])


def renewed(layer: DataFrame, model: Potential) -> DataFrame:
    """The state after a layer."""
    where = [c for c in ("lane", "part_id", "atom_id") if c in layer.columns]
    return layer.select(*where, *[F.col(f"new_{s}").alias(s) for s in model.state])


def first_bonds(bonds: BondTables, model: Potential) -> DataFrame:
    return bonds.owned.select("lane", "bid", "dst", model.a.mod(F.col("w")).alias("b"))


def bond_layer(state: DataFrame, bonds: BondTables, lanes: Lanes, model: Potential) -> DataFrame:
    """New state b of the owned bonds (lane, bid, dst, b): border bonds receive theirs from their owners first."""
    received = exchange(state.drop("dst"), bonds.outbox, lanes, "bid")
    carried = at_source(bonds.links, state, received, ["lane"], ["b"], "f_bid", "bid")
    sums = carried.groupBy("lane", F.col("e_bid").alias("bid")).agg(F.sum(model.a.mod(model.bond_message())).alias("sum_b"))
    joined = state.join(sums.hint("shuffle_hash"), ["lane", "bid"], "left").withColumn("sum_b", F.coalesce("sum_b", model.a.zero()))
    return joined.select("lane", "bid", "dst", model.bond_update().alias("b"))


def forward(graph: PartitionedGraph, spec: PotentialSpec, *, setup: str = "distributed") -> DataFrame:
    """lane, part_id, atom_id and features after all layers.

    Every layer is written in its lanes, with message sums and both states, so a layer is one job whose only shuffle is the
    exchange of border rows; graph.trace keeps them for the way back.
    """
    model, lanes = potential(spec), graph.lanes
    state = initial_state(graph.nodes, model, setup)
    if setup == "single" or spec.family == "smooth":
        state = lanes.keep(lanes.dealt(state), "first")
    graph.trace, graph.bond_trace = [], []
    bond = None
    if model.uses_bonds:
        bond = lanes.keep(first_bonds(graph.bonds, model), "bonds")
        graph.bond_trace.append(bond)
    for _ in range(spec.layers):
        sums = None
        if model.uses_bonds:
            bond = lanes.keep(bond_layer(bond, graph.bonds, lanes, model), "bonds")
            graph.bond_trace.append(bond)
            sums = bond.groupBy("lane", F.col("dst").alias("atom_id")).agg(F.sum("b").alias("sum_bond"))
        layer = conv_layer(state, exchange(state, graph.outbox, lanes), graph.edges, model, ["lane"], sums)
        graph.trace.append(lanes.keep(layer, "layer"))
        state = renewed(graph.trace[-1], model)
    return state


def energy(state: DataFrame, model: Potential) -> DataFrame:
    """Sum of the readout over owned nodes; border copies never enter."""
    return state.agg(F.coalesce(F.sum(model.readout()), model.a.zero()).alias("energy"))


def energy_per_species(state: DataFrame, graph: PartitionedGraph, model: Potential) -> DataFrame:
    return state.join(graph.nodes.select("lane", "atom_id", "species"), ["lane", "atom_id"]).groupBy("species").agg(F.count(F.lit(1)).alias("atoms"), F.sum(model.readout()).alias("energy"))


def _ends(first: list[Column], second: list[Column], names: list[str]) -> Column:
    """Two rows of one edge, for its source and its destination."""
    row = lambda values: F.struct(*[v.alias(n) for n, v in zip(names, values)])
    return F.explode(F.array(row(first), row(second))).alias("e")


def to_owners(partial: DataFrame, graph: PartitionedGraph, key: str, values: list[str]) -> list[DataFrame]:
    """Adjoint of the exchange. Partial sums (lane, key, home, own, values) in two tables: those of a lane's own nodes where
    they are, and those for other owners, sent home and added up there."""
    lanes = graph.lanes
    own = partial.filter("own").select("lane", key, *values)
    away = lanes.dealt(partial.filter("NOT own").select(lanes.lane(F.col("home")).alias("lane"), key, *values))
    return [own, away.groupBy("lane", key).agg(*[F.sum(v).alias(v) for v in values])]


def _added(df: DataFrame, parts: list[DataFrame], key: str, into: dict[str, str], model: Potential, reduce: set[str]) -> DataFrame:
    """df with the values of every part added to its columns, reduced where they are ring elements."""
    for k, part in enumerate(parts):
        df = df.join(part.select("lane", key, *[F.col(v).alias(f"_{k}_{v}") for v in into]).hint("shuffle_hash"), ["lane", key], "left")
    total = {}
    for v, name in into.items():
        c = F.col(name)
        for k in range(len(parts)):
            c = c + F.coalesce(f"_{k}_{v}", model.a.zero())
        total[name] = model.a.mod(c) if name in reduce else c
    return df.withColumns(total).drop(*[f"_{k}_{v}" for k in range(len(parts)) for v in into])


def backward(graph: PartitionedGraph, spec: PotentialSpec) -> DataFrame:
    """forces(atom_id, fx, fy, fz) of the energy summed over all channels, by the reverse pass over the kept layers.

    From the last layer to the first, slopes of the energy go from each destination to its edges' sources, and every edge
    pulls at both its ends. What a part finds for nodes of others goes home and is added there: one shuffle of border rows
    for the states, one for the slopes, in every layer. Models without adjoints of their own are refused.
    """
    model, lanes = potential(spec), graph.lanes
    check_adjoints(model)
    states, zero = model.state, model.a.zero()
    forces = [f"f{a}" for a in AXES]
    first = [(model.a.one() if s in model.channels else zero).alias(f"g_{s}") for s in states]
    g = graph.nodes.select("lane", "part_id", "atom_id", *first, *[zero.alias(f) for f in forces])
    gb = graph.bonds.owned.select("lane", "bid", "dst", zero.alias("gb")) if model.uses_bonds else None
    for k in range(spec.layers - 1, -1, -1):
        layer = graph.trace[k]
        slopes = layer.drop("part_id").join(g.select("lane", "atom_id", *[f"g_{s}" for s in states]).hint("shuffle_hash"), ["lane", "atom_id"])
        names = list(model.sum_adjoints())
        steep = lanes.keep(slopes.select("lane", "atom_id", *states, *[c.alias(f"s_{n}") for n, c in model.sum_adjoints().items()], *[c.alias(f"c_{n}") for n, c in model.state_adjoints().items()]), "slopes")
        state = steep.select("lane", "atom_id", *states)
        near = graph.edges.join(steep.select("lane", F.col("atom_id").alias("dst"), *[f"s_{n}" for n in names]).hint("shuffle_hash"), ["lane", "dst"])
        over = at_source(near, state, exchange(state, graph.outbox, lanes), ["lane"], states)
        over = over.withColumns({"q": model.weight_adjoint()} | {f"p{a}": c for a in AXES if (c := model.displacement_adjoint(a)) is not None})
        back = [c for c in model.source_adjoints().values()]
        pulls = [model.pull(a) for a in AXES]
        cols = ["atom_id", "home", *[f"a_{s}" for s in states], *forces]
        both = _ends([F.col("src"), F.col("p_src"), *back, *pulls], [F.col("dst"), F.col("part_id"), *[zero] * len(states), *[-c for c in pulls]], cols)
        values = [*[f"a_{s}" for s in states], *forces]
        partial = over.select("lane", "part_id", both).select("lane", "e.*", (F.col("e.home") == F.col("part_id")).alias("own"))
        partial = lanes.keep(partial.groupBy("lane", "atom_id", "home", "own").agg(*[F.sum(v).alias(v) for v in values]), "partial")
        parts = to_owners(partial, graph, "atom_id", values)
        carried = steep.select("lane", "atom_id", *[F.col(f"c_{s}").alias(f"g_{s}") for s in states]).hint("shuffle_hash")
        g = g.select("lane", "part_id", "atom_id", *forces).join(carried, ["lane", "atom_id"])
        g = _added(g, parts, "atom_id", {f"a_{s}": f"g_{s}" for s in states} | {f: f for f in forces}, model, {f"g_{s}" for s in states})
        if model.uses_bonds:
            gb, angles = _bond_backward(graph, model, gb, graph.bond_trace[k], steep)
            g = _added(g, to_owners(angles, graph, "atom_id", forces), "atom_id", {f: f for f in forces}, model, set())
        g = lanes.keep(g.select("lane", "part_id", "atom_id", *[f"g_{s}" for s in states], *forces), "gradient")
    if model.uses_bonds and spec.layers:  # the first state of a bond is its weight
        lengths = graph.bonds.owned.join(gb.select("lane", "bid", F.col("gb").alias("q")).hint("shuffle_hash"), ["lane", "bid"])
        pulls = [model.pull(a) for a in AXES]
        both = _ends([F.col("src"), F.col("p_src"), *pulls], [F.col("dst"), F.col("part_id"), *[-c for c in pulls]], ["atom_id", "home", *forces])
        partial = lengths.select("lane", "part_id", both).select("lane", "e.*", (F.col("e.home") == F.col("part_id")).alias("own"))
        partial = lanes.keep(partial.groupBy("lane", "atom_id", "home", "own").agg(*[F.sum(f).alias(f) for f in forces]), "partial")
        g = lanes.keep(_added(g, to_owners(partial, graph, "atom_id", forces), "atom_id", {f: f for f in forces}, model, set()), "gradient")
    return g.select("atom_id", *forces)


def _bond_backward(graph: PartitionedGraph, model: Potential, gb: DataFrame, before: DataFrame, steep: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(slopes in the bonds' states before a layer, partial forces of its links), from the slopes after it."""
    lanes, bonds = graph.lanes, graph.bonds
    heard = steep.select("lane", F.col("atom_id").alias("dst"), "s_bond").hint("shuffle_hash")
    gb = lanes.keep(gb.join(heard, ["lane", "dst"]).select("lane", "bid", "dst", model.a.mod(F.col("gb") + F.col("s_bond")).alias("gb")), "bond slopes")
    late = bonds.links.join(gb.select("lane", F.col("bid").alias("e_bid"), "gb").hint("shuffle_hash"), ["lane", "e_bid"])
    over = at_source(late, before, exchange(before.drop("dst"), bonds.outbox, lanes, "bid"), ["lane"], ["b"], "f_bid", "bid")
    f_end = bonds.before.select("lane", F.col("bid").alias("f_bid"), F.col("src").alias("f_src"), F.col("p_src").alias("f_home"), *[F.col(f"d{a}").alias(f"f{a}") for a in AXES])
    e_end = bonds.owned.select("lane", F.col("bid").alias("e_bid"), "part_id", F.col("src").alias("center"), F.col("p_src").alias("home"), "dst", *[F.col(f"d{a}").alias(f"e{a}") for a in AXES])
    angles = over.withColumn("slope", model.angle_adjoint()).join(f_end.hint("shuffle_hash"), ["lane", "f_bid"]).join(e_end.hint("shuffle_hash"), ["lane", "e_bid"])
    forces = [f"f{a}" for a in AXES]
    by_e, by_f = ([model.angle_pull(F.col("slope"), F.col(f"{s}{a}")) for a in AXES] for s in "ef")
    row = lambda values: F.struct(*[v.alias(n) for n, v in zip(["atom_id", "home", *forces], values)])
    three = F.explode(F.array(row([F.col("f_src"), F.col("f_home"), *[-x for x in by_e]]), row([F.col("center"), F.col("home"), *[x - y for x, y in zip(by_e, by_f)]]), row([F.col("dst"), F.col("part_id"), *by_f]))).alias("e")
    partial = angles.select("lane", "part_id", three).select("lane", "e.*", (F.col("e.home") == F.col("part_id")).alias("own"))
    pulled = lanes.keep(partial.groupBy("lane", "atom_id", "home", "own").agg(*[F.sum(f).alias(f) for f in forces]), "angles")
    # the first bond of a link belongs to the part of the atom in its middle
    back = over.withColumn("gain", model.bond_source_adjoint()).join(e_end.select("lane", "e_bid", "part_id", "home").hint("shuffle_hash"), ["lane", "e_bid"])
    back = back.groupBy("lane", F.col("f_bid").alias("bid"), "home", (F.col("home") == F.col("part_id")).alias("own")).agg(F.sum("gain").alias("gain"))
    parts = to_owners(lanes.keep(back, "bond gains"), graph, "bid", ["gain"])
    return lanes.keep(_added(gb, parts, "bid", {"gain": "gb"}, model, {"gb"}), "bond slopes"), pulled


def direct_forces(graph: PartitionedGraph, state: DataFrame, model: Potential) -> DataFrame:
    """forces read from the features: each edge pushes its destination by w * h_src along its displacement."""
    read = state.select("lane", "atom_id", model.a.mod(model.readout()).alias("h"))
    push = at_source(graph.edges, read, exchange(read, graph.outbox, graph.lanes), ["lane"], ["h"]).withColumn("q", model.a.mod(F.col("w") * F.col("h")))
    pulls = push.groupBy("lane", F.col("dst").alias("atom_id")).agg(*[F.sum(F.col("q") * F.col(f"d{a}")).alias(f"f{a}") for a in AXES])
    out = graph.nodes.join(pulls.hint("shuffle_hash"), ["lane", "atom_id"], "left").select("lane", "atom_id", *[F.coalesce(f"f{a}", model.a.zero()).alias(f"f{a}") for a in AXES])
    return graph.lanes.keep(out, "forces").drop("lane")


def infer(system: System, spec: PotentialSpec, p: int, *, method: str = "wall", scratch: Scratch | None = None, setup: str = "distributed") -> tuple[PartitionedGraph, DataFrame]:
    """(graph, final state) of a system split into p parts."""
    graph = build_partitioned_graph(system, spec, p, method=method, scratch=scratch)
    return graph, forward(graph, spec, setup=setup)

