"""Exchange, layers, models, forces, dynamics, baselines, measures and workloads on the given tables."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from halograph.baselines.single import run_single
from halograph.baselines.spatial import ghost_count, run_spatial, run_spatial_hops
from halograph.catalog import query
from halograph.dynamics import SOFT, md_run
from halograph.functions.ring import PRIME, mod
from halograph.graph import halo, neighbors, partition
from halograph.graph.runtime import backward, bond_layer, build_partitioned_graph, conv_layer, direct_forces, energy, energy_per_species, exchange, first_bonds, forward, infer, initial_state, renewed
from halograph.graph.scratch import Scratch
from halograph.measures import exactness, growth_exponent, layer_updates, max_capacity, memory_counts, memory_model, over_budget, transfer_volume
from halograph.potentials import PotentialSpec, RingPotential, potential, register_potential
from halograph.sources import systems
from halograph.twins import sql as q

P = 8
BOND = 3000
LONG = 5000
RING = PotentialSpec("ring", layers=3, cutoff=LONG)
#: A shorter cutoff for the heavier models.
SHORT = replace(RING, cutoff=3500, layers=2)


def _state(names: str, k: int) -> str:
    return f"SELECT atom_id, {names} FROM s{k}"


def _result(state):
    return state.drop("lane", "part_id")


def _union(rows):
    out = None
    for r in rows:
        out = r if out is None else out.unionByName(r)
    return out


@query("exchange_layer", q.select(q.quartz() + q.edges(BOND) + q.walls(P) + q.owners() + q.init(), "SELECT a.part_id, s.atom_id, h0 FROM s0 s JOIN halo a USING (atom_id)"))
def exchange_layer(spark, sf_dir):
    """What every part receives in a layer: the features of its border nodes."""
    spec = replace(RING, cutoff=BOND)
    g = build_partitioned_graph(systems.quartz(spark, sf_dir), spec, P)
    parts = g.nodes.select("lane", "part_id").distinct()
    return exchange(initial_state(g.nodes, potential(spec)), g.outbox, g.lanes).join(parts, "lane").drop("lane")


@query("conv_one_layer", q.select(q.quartz() + q.edges(BOND) + q.ring(1), _state("h0", 1)))
def conv_one_layer(spark, sf_dir):
    spec = replace(RING, cutoff=BOND, layers=1)
    g = build_partitioned_graph(systems.quartz(spark, sf_dir), spec, P)
    model = potential(spec)
    first = initial_state(g.nodes, model)
    return _result(renewed(g.lanes.keep(conv_layer(first, exchange(first, g.outbox, g.lanes), g.edges, model, ["lane"]), "layer"), model))


@query("forward_ring_L3", q.select(q.quartz() + q.edges(LONG) + q.ring(3), _state("h0", 3)))
def forward_ring(spark, sf_dir):
    return _result(infer(systems.quartz(spark, sf_dir), RING, P)[1])


@query("forward_ring_wide", q.select(q.quartz() + q.edges(BOND) + q.ring(2, 3), _state("h0, h1, h2", 2)))
def forward_ring_wide(spark, sf_dir):
    return _result(infer(systems.quartz(spark, sf_dir), replace(RING, cutoff=BOND, layers=2, width=3), P)[1])


@query("forward_no_layer", q.select(q.quartz() + q.init(), _state("h0", 0)))
def forward_no_layer(spark, sf_dir):
    return _result(infer(systems.quartz(spark, sf_dir), replace(RING, cutoff=BOND, layers=0), P)[1])


@query("forward_more_parts_than_cells", q.select(q.quartz() + q.edges(BOND) + q.ring(2), _state("h0", 2)))
def forward_thin_walls(spark, sf_dir):
    """Walls thinner than the cutoff: nodes have several peers, the answer stays."""
    return _result(infer(systems.quartz(spark, sf_dir), replace(RING, cutoff=BOND, layers=2), 60)[1])


@query("forward_successor", q.select(q.successor() + q.ring(3), _state("h0", 3)))
def forward_successor(spark, sf_dir):
    return _result(infer(systems.successor(spark, sf_dir), RING, P)[1])


@query("forward_chain", q.select(q.chain() + q.ring(3), _state("h0", 3)))
def forward_chain(spark, sf_dir):
    return _result(infer(systems.chain(spark, sf_dir), RING, P)[1])


@query("forward_hub", q.select(q.hub() + q.ring(2), _state("h0", 2)))
def forward_hub(spark, sf_dir):
    return _result(infer(systems.hub(spark, sf_dir), replace(RING, layers=2), P)[1])


@query("forward_clusters", q.select(q.clusters() + q.ring(2), _state("h0", 2)))
def forward_clusters(spark, sf_dir):
    return _result(infer(systems.clusters(spark, sf_dir), replace(RING, layers=2), P)[1])


BONDED = replace(RING, family="invariant_bond", layers=2, cutoff=LONG, bond_cutoff=2000)


@query("forward_bonds_L2", q.select(q.quartz() + q.edges(LONG) + q.line(2000) + q.invariant_bond(2), _state("h0", 2)))
def forward_bonds(spark, sf_dir):
    return _result(infer(systems.quartz(spark, sf_dir), BONDED, P)[1])


@query("bond_one_layer", q.select(q.quartz() + q.edges(LONG) + q.line(2000) + q.invariant_bond(1), "SELECT src, dst, ix, iy, iz, b FROM b1"))
def bond_one_layer(spark, sf_dir):
    g, model = build_partitioned_graph(systems.quartz(spark, sf_dir), BONDED, P), potential(BONDED)
    state = g.lanes.keep(bond_layer(g.lanes.keep(first_bonds(g.bonds, model), "first"), g.bonds, g.lanes, model), "second")
    return g.bonds.owned.select("lane", "bid", *neighbors.EDGE_KEY).join(state.drop("dst"), ["lane", "bid"]).drop("lane", "bid")


@query("bonds_off_equals_ring", q.select(q.quartz() + q.edges(LONG) + q.ring(2), _state("h0", 2)))
def bonds_off(spark, sf_dir):
    return _result(infer(systems.quartz(spark, sf_dir), replace(BONDED, bond_cutoff=0), P)[1])


@query("energy_total", q.select(q.quartz() + q.edges(LONG) + q.ring(3), "SELECT CAST(sum(h0) AS BIGINT) AS energy FROM s3"))
def energy_total(spark, sf_dir):
    return energy(infer(systems.quartz(spark, sf_dir), RING, P)[1], potential(RING))


@query("energy_per_species", q.select(q.quartz() + q.edges(LONG) + q.ring(3), "SELECT species, count(*) AS atoms, CAST(sum(h0) AS BIGINT) AS energy FROM s3 GROUP BY species"))
def energy_species(spark, sf_dir):
    g, state = infer(systems.quartz(spark, sf_dir), RING, P)
    return energy_per_species(state, g, potential(RING))


FORCE = "SELECT atom_id, fx, fy, fz FROM forces"


def _forces(spark, sf_dir, spec):
    return backward(infer(systems.quartz(spark, sf_dir), spec, P)[0], spec)


@query("forces_conservative", q.select(q.quartz() + q.edges(3500) + q.ring(2) + q.ring_forces(2), FORCE))
def forces_conservative(spark, sf_dir):
    return _forces(spark, sf_dir, SHORT)


@query("forces_many_body", q.select(q.quartz() + q.edges(3500) + q.ring(2, 1, q.many_body_update(3)) + q.ring_forces(2, f"1 + 2 * a + 3 * (a * a % {PRIME})"), FORCE))
def forces_many_body(spark, sf_dir):
    return _forces(spark, sf_dir, replace(SHORT, family="many_body"))


@query("forces_light", q.select(q.quartz() + q.edges(3500) + q.light(2) + q.light_forces(2, 3500), FORCE))
def forces_light(spark, sf_dir):
    return _forces(spark, sf_dir, replace(SHORT, family="light"))


@query("forces_smooth", q.select(q.quartz() + q.edges(3500, weight="smooth") + q.light(2, True) + q.light_forces(2, 3500, True), FORCE))
def forces_smooth(spark, sf_dir):
    return _forces(spark, sf_dir, replace(SHORT, family="smooth"))


@query("forces_invariant_bond", q.select(q.quartz() + q.edges(3500) + q.line(2000) + q.invariant_bond(2) + q.bond_forces(2, 3500), FORCE))
def forces_invariant_bond(spark, sf_dir):
    return _forces(spark, sf_dir, replace(SHORT, family="invariant_bond", bond_cutoff=2000))


@query("forces_sum_to_zero", "SELECT CAST(0 AS BIGINT) AS fx, CAST(0 AS BIGINT) AS fy, CAST(0 AS BIGINT) AS fz")
def forces_sum(spark, sf_dir):
    return forces_conservative(spark, sf_dir).agg(*[F.sum(f).alias(f) for f in ("fx", "fy", "fz")])


DIRECT = "SELECT a.atom_id, " + ", ".join(f"CAST(coalesce(sum(w * h0 % {PRIME} * d{x}), 0) AS BIGINT) AS f{x}" for x in "xyz") + " FROM atoms a LEFT JOIN edges e ON e.dst = a.atom_id LEFT JOIN s2 ON s2.atom_id = e.src GROUP BY a.atom_id"


@query("forces_direct", q.select(q.quartz() + q.edges(3500) + q.ring(2), DIRECT))
def forces_direct(spark, sf_dir):
    g, state = infer(systems.quartz(spark, sf_dir), SHORT, P)
    return direct_forces(g, state, potential(SHORT))


class Damped(RingPotential):
    """A user's own model, h' = 3 h + 5 A, with the adjoints that its own update needs."""

    def update(self):
        return {h: mod(F.col(h) * 3 + mod(F.col(f"sum_{h}")) * 5) for h in self.channels}

    def sum_adjoints(self):
        return {h: mod(F.col(f"g_{h}") * 5) for h in self.channels}

    def state_adjoints(self):
        return {h: mod(F.col(f"g_{h}") * 3) for h in self.channels}


register_potential("damped_plug_in", Damped)


@query("plug_in_custom", q.select(q.quartz() + q.edges(3500) + q.ring(2, 1, "3 * h + 5 * a"), _state("h0", 2)))
def plug_in_custom(spark, sf_dir):
    return _result(infer(systems.quartz(spark, sf_dir), replace(SHORT, family="damped_plug_in"), P)[1])


@query("model_invariant_bond", q.select(q.quartz() + q.edges(BOND) + q.line(2000) + q.invariant_bond(2), _state("h0", 2)))
def model_invariant_bond(spark, sf_dir):
    return _result(infer(systems.quartz(spark, sf_dir), replace(BONDED, cutoff=BOND), P)[1])


@query("model_light_equivariant", q.select(q.quartz() + q.edges(3500) + q.light(2), "SELECT atom_id, h0, vx AS vx0, vy AS vy0, vz AS vz0 FROM v2"))
def model_light(spark, sf_dir):
    return _result(infer(systems.quartz(spark, sf_dir), replace(SHORT, family="light"), P)[1])


@query("model_many_body", q.select(q.quartz() + q.edges(3500) + q.ring(2, 1, q.many_body_update(3)), _state("h0", 2)))
def model_many_body(spark, sf_dir):
    return _result(infer(systems.quartz(spark, sf_dir), replace(SHORT, family="many_body", nu=3), P)[1])


@query("model_many_body_nu1", q.select(q.quartz() + q.edges(3500) + q.ring(2), _state("h0", 2)))
def model_many_body_one(spark, sf_dir):
    return _result(infer(systems.quartz(spark, sf_dir), replace(SHORT, family="many_body", nu=1), P)[1])


@query("model_smooth", q.select(q.quartz() + q.edges(3500, weight="smooth") + q.light(2, True), "SELECT atom_id, h0, vx AS vx0, vy AS vy0, vz AS vz0 FROM v2"))
def model_smooth(spark, sf_dir):
    return _result(infer(systems.quartz(spark, sf_dir), replace(SHORT, family="smooth"), P)[1])


@query("setup_single_vs_distributed", "SELECT count(*) AS rows, CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS max_error FROM orders")
def setup_modes(spark, sf_dir):
    spec = replace(SHORT, family="smooth")
    g = build_partitioned_graph(systems.quartz(spark, sf_dir), spec, P)
    return exactness(_result(forward(g, spec, setup="single")), _result(forward(g, spec)))


@query("rotation_invariance", "SELECT count(*) AS rows, CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS max_error FROM part")
def rotation(spark, sf_dir):
    """A quarter turn about z leaves the scalars of the equivariant model as they are."""
    spec = replace(SHORT, family="light", cutoff=2829)
    s = systems.lattice(spark, sf_dir)
    lx, ly, lz = s.cell.lengths
    bumped = s.atoms.withColumn("x", (F.col("x") + F.pmod(F.col("atom_id"), F.lit(7)) * 11) % lx)
    turned = bumped.select("atom_id", "species", ((F.lit(ly) - F.col("y")) % ly).alias("x"), F.col("x").alias("y"), "z")
    a = run_single(replace(s, atoms=bumped), spec).select("atom_id", "h0")
    return exactness(a, run_single(replace(s, atoms=turned, cell=replace(s.cell, lengths=(ly, lx, lz))), spec).select("atom_id", "h0"))


MD = 2


@query("md_two_steps", md_run.twin(MD))
def md_two_steps(spark, sf_dir):
    return md_run(systems.cloud(spark, sf_dir), replace(RING, cutoff=100, layers=1), P, MD).filter(F.col("step") == MD)


@query("md_periodic", md_run.twin(MD, BOND, q.quartz(), True, 2))
def md_periodic(spark, sf_dir):
    """Two layers on the periodic crystal; positions are wrapped and the graph is built anew in every step."""
    return md_run(systems.quartz(spark, sf_dir), replace(RING, cutoff=BOND, layers=2), P, MD).filter(F.col("step") == MD)


def _md_pair(spark, sf_dir, spec, skin, soft=SOFT):
    """The same run with a graph built in every step and with one that is kept within its skin."""
    s = systems.quartz(spark, sf_dir)
    moved = lambda run: run.filter(F.col("step") == MD).select("atom_id", *[F.pmod(F.col(a), F.lit(s.cell.lengths[k])).alias(a) for k, a in enumerate("xyz")], "vx", "vy", "vz")
    return exactness(moved(md_run(s, spec, P, MD, soft=soft)), moved(md_run(s, spec, P, MD, skin=skin, soft=soft)))


@query("md_skin", "SELECT count(*) AS rows, CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS max_error FROM orders")
def md_skin(spark, sf_dir):
    return _md_pair(spark, sf_dir, replace(RING, cutoff=BOND, layers=2), 400)


@query("md_bonds", "SELECT count(*) AS rows, CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS max_error FROM orders")
def md_bonds(spark, sf_dir):
    """The model with bonds: a kept graph renews bonds and links as well."""
    return _md_pair(spark, sf_dir, replace(RING, family="invariant_bond", cutoff=BOND, bond_cutoff=2000, layers=1), 400, SOFT * BOND**2 // 32)


@query("single_device", q.select(q.quartz() + q.edges(BOND) + q.ring(2), _state("h0", 2)))
def single_device(spark, sf_dir):
    return _result(run_single(systems.quartz(spark, sf_dir), replace(RING, cutoff=BOND, layers=2)))


BASE2 = q.quartz() + q.edges(BOND) + q.ring(2)


@query("spatial_slab", q.select(BASE2, _state("h0", 2)))
def spatial_slab(spark, sf_dir):
    return _result(run_spatial(systems.quartz(spark, sf_dir), replace(RING, cutoff=BOND, layers=2), P))


@query("spatial_block3d", q.select(BASE2, _state("h0", 2)))
def spatial_block(spark, sf_dir):
    return _result(run_spatial(systems.quartz(spark, sf_dir), replace(RING, cutoff=BOND, layers=2), 8, decomposition="block3d"))


@query("spatial_hops", q.select(BASE2, _state("h0", 2)))
def spatial_hops(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    return _result(run_spatial_hops(s, replace(RING, cutoff=BOND, layers=2), partition.wall_partition(s.atoms, s.cell, P), P))


@query("spatial_underpadded", "SELECT true AS differs")
def spatial_underpadded(spark, sf_dir):
    """Padding of one cutoff under two layers: the short-range assumption fails and results differ."""
    spec = replace(RING, cutoff=BOND, layers=2)
    s = systems.quartz(spark, sf_dir)
    return exactness(run_single(s, spec), run_spatial(s, spec, P, pad=BOND)).select((F.col("max_error") > 0).alias("differs"))


@query("rival_matched", q.select(q.quartz() + q.edges(BOND) + q.ring(2, 4), _state("h0, h1, h2, h3", 2)))
def rival_matched(spark, sf_dir):
    """The rival at the width that matches 160 parameters, under padded inference."""
    spec = replace(RING, family="rival", cutoff=BOND, layers=2).matched_to(160)
    return _result(run_spatial(systems.quartz(spark, sf_dir), spec, P))


@query("kernel_arrow", q.select(BASE2, _state("h0", 2)))
def kernel_arrow(spark, sf_dir):
    from halograph.operators.kernels import fused_forward

    spec = replace(RING, cutoff=BOND, layers=2)
    return _result(fused_forward(build_partitioned_graph(systems.quartz(spark, sf_dir), spec, P), spec))


@query("kernel_arrow_many_body", q.select(q.quartz() + q.edges(BOND) + q.ring(2, 1, q.many_body_update(3)), _state("h0", 2)))
def kernel_arrow_many_body(spark, sf_dir):
    from halograph.operators.kernels import fused_forward

    spec = replace(RING, family="many_body", cutoff=BOND, layers=2)
    return _result(fused_forward(build_partitioned_graph(systems.quartz(spark, sf_dir), spec, P), spec))


@query("redundancy", q.select(q.quartz(), "SELECT layer, count(*) AS computed, count(*) AS needed FROM atoms, range(2) t(layer) GROUP BY layer"))
def zero_redundancy(spark, sf_dir):
    """Node updates that each layer really made, counted from its kept rows, against the atoms there are."""
    spec = replace(RING, cutoff=BOND, layers=2)
    g, _ = infer(systems.quartz(spark, sf_dir), spec, P)
    return layer_updates(g)


RANGES = (1, 2, 4, 8)


def _copies(how: str, pad: int) -> str:
    """Copies of all atoms in padded boxes: the product of what each axis gives, over its distinct coordinates."""
    n = {"slab": f"(CASE WHEN '{{a}}' = 'x' THEN {P} ELSE 1 END)", "block3d": "n{a}"}[how]
    per = lambda a: f"SELECT {a}, count(*) AS c{a} FROM (SELECT DISTINCT {a} FROM atoms), cell, boxes, range(16) b(i), generate_series(-16, 16) m(k) WHERE i < {n.format(a=a)} AND {a} + k * l{a} >= -((-i * l{a}) // {n.format(a=a)}) - {pad} AND {a} + k * l{a} < -((-(i + 1) * l{a}) // {n.format(a=a)}) + {pad} GROUP BY {a}"
    return f"SELECT CAST(sum(cx * cy * cz) AS BIGINT) AS copies FROM atoms JOIN ({per('x')}) USING (x) JOIN ({per('y')}) USING (y) JOIN ({per('z')}) USING (z)"


#: Boxes of p = 8 as near to cubes as halving the longest side gives.
_BOXES = [
    ("half1", "SELECT lx, ly, lz, 1 AS nx, 1 AS ny, 1 AS nz FROM cell"),
    *[
        (f"half{k + 1}", f"SELECT lx, ly, lz, nx * (CASE WHEN w = 0 THEN 2 ELSE 1 END) AS nx, ny * (CASE WHEN w = 1 THEN 2 ELSE 1 END) AS ny, nz * (CASE WHEN w = 2 THEN 2 ELSE 1 END) AS nz FROM (SELECT *, CASE WHEN lx / nx >= ly / ny AND lx / nx >= lz / nz THEN 0 WHEN ly / ny >= lz / nz THEN 1 ELSE 2 END AS w FROM half{k})")
        for k in (1, 2, 3)
    ],
    ("boxes", "SELECT nx, ny, nz FROM half4"),
]


@query(
    "redundancy_vs_range",
    q.select(
        q.quartz() + _BOXES,
        " UNION ALL ".join(
            [f"SELECT {n * LONG} AS reach, '{how}' AS method, copies * {n} AS computed, (SELECT count(*) FROM atoms) * {n} AS needed FROM ({_copies(how, n * LONG)})" for n in RANGES for how in ("slab", "block3d")]
            + [f"SELECT {n * LONG}, 'graph', count(*) * {n}, count(*) * {n} FROM atoms" for n in RANGES]
        ),
    ),
)
def redundancy_vs_range(spark, sf_dir):
    """Node updates made and needed as the range grows with the layers: padded slabs grow linearly, padded blocks faster,
    graph partitioning, counted from the rows of the layers that it ran, not at all."""
    s = systems.quartz(spark, sf_dir)
    needed = s.atoms.count()
    graph = build_partitioned_graph(s, RING, P)
    rows = []
    for n in RANGES:
        for how in ("slab", "block3d"):
            rows.append(ghost_count(s, P, n * LONG, how).select(F.lit(n * LONG).alias("reach"), F.lit(how).alias("method"), (F.col("copies") * n).alias("computed"), F.lit(needed * n).alias("needed")))
        forward(graph, replace(RING, layers=n))
        rows.append(layer_updates(graph).agg(F.sum("computed").alias("computed"), F.sum("needed").alias("needed")).select(F.lit(n * LONG).alias("reach"), F.lit("graph").alias("method"), "computed", "needed"))
    return _union(rows)


def _ghost_sql() -> str:
    """Slabs of S1 for p = 4: atoms within the reach of a slab, over the periodic images that matter."""
    pad = 10_000
    images = "SELECT atom_id, x + i * lx AS x, i FROM atoms, cell, generate_series(-1, 1) t(i)"
    walls = "SELECT k, -(-k * lx // 4) AS low, -(-(k + 1) * lx // 4) AS high FROM cell, range(4) r(k)"
    return q.select(q.quartz() + [("im", images)], f"SELECT 10000 AS reach, count(*) AS copies FROM im JOIN (SELECT k, CAST(ceil(k * lx / 4.0) AS BIGINT) AS low, CAST(ceil((k + 1) * lx / 4.0) AS BIGINT) AS high FROM cell, range(4) r(k)) w ON im.x >= low - {pad} AND im.x < high + {pad}")


@query("ghost_growth", _ghost_sql())
def ghost_growth(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    # slabs pad along one axis only; the other two wrap inside the slab
    open_yz = replace(s, cell=replace(s.cell, periodic=(True, False, False)))
    return ghost_count(open_yz, 4, 10_000, "slab").select(F.lit(10_000).alias("reach"), "copies")


@query("transfer_volume", q.select(q.quartz() + q.edges(BOND) + q.walls(P) + q.owners(), "SELECT CAST(count(*) AS BIGINT) AS sent, CAST(count(*) * 32 AS BIGINT) AS bytes, (SELECT count(*) FROM (SELECT atom_id FROM halo GROUP BY atom_id HAVING count(*) > 1)) AS overlap FROM halo"))
def transfers(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    a = partition.wall_partition(s.atoms, s.cell, P)
    return transfer_volume(halo.assign_buckets(a, halo.border_nodes(neighbors.neighbor_list(s.atoms, s.cell, BOND), a)), 4)


NARROW = (2, 4, 8, 16, 32)
#: Both ends' coordinates on an edge once; parts by expression, so no assignment is joined.
_MANY = [
    ("xs", "SELECT e.src, s.x AS sx, t.x AS tx, lx FROM edges e JOIN atoms s ON s.atom_id = e.src JOIN atoms t ON t.atom_id = e.dst, cell"),
    ("halos", " UNION ALL ".join(f"SELECT DISTINCT {p} AS parts, least({p - 1}, tx * {p} // lx) AS part_id, src AS atom_id FROM xs WHERE least({p - 1}, sx * {p} // lx) <> least({p - 1}, tx * {p} // lx)" for p in NARROW)),
    ("per_node", "SELECT parts, atom_id, count(*) AS n FROM halos GROUP BY parts, atom_id"),
]


@query("narrow_walls_overlap", q.select(q.quartz() + q.edges(LONG) + _MANY, "SELECT parts, CAST(sum(n) AS BIGINT) AS sent, CAST(sum(n) * 8 AS BIGINT) AS bytes, count(*) FILTER (n > 1) AS overlap FROM per_node GROUP BY parts"))
def narrow_walls(spark, sf_dir):
    """Thinner walls: more to send in each layer and more nodes that several parts need."""
    s = systems.quartz(spark, sf_dir)
    edges = Scratch(spark).keep(neighbors.neighbor_list(s.atoms, s.cell, LONG), "edges")
    return _union(transfer_volume(halo.assign_buckets(a, halo.border_nodes(edges, a))).withColumn("parts", F.lit(p)) for p in NARROW for a in [partition.wall_partition(s.atoms, s.cell, p)])


@query("memory_model", q.select(q.quartz() + q.edges(BOND) + q.walls(P) + q.owners(), "SELECT a.part_id, a.n AS nodes, h.n AS halo, e.n AS edges, CAST(0 AS BIGINT) AS links, CAST((a.n + h.n) * 4 + e.n * 7 AS BIGINT) * 8 AS bytes FROM (SELECT part_id, count(*) AS n FROM assign GROUP BY part_id) a JOIN (SELECT part_id, count(*) AS n FROM halo GROUP BY part_id) h USING (part_id) JOIN (SELECT part_id, count(*) AS n FROM owned GROUP BY part_id) e USING (part_id)"))
def memory(spark, sf_dir):
    spec = replace(RING, cutoff=BOND)
    return memory_model(build_partitioned_graph(systems.quartz(spark, sf_dir), spec, P), spec)


def capacity_points(spark, family: str, parts: tuple[int, ...], budget: int) -> list[tuple]:
    """(family, parts, atoms, multiple of one part's capacity): the largest supercell whose every part stays within the
    budget of modelled bytes. Sizes are doubled until one fails and then halved in between; bytes come from real counts."""
    spec = replace(SHORT, family=family, bond_cutoff=2000)
    out, first = [], None
    for p in parts:

        def build(size: int) -> tuple[int, int]:
            n = size * 18 * 9  # layers of three by three cells
            s = systems.System("quartz", *systems.rod(spark.range(n).select(F.col("id").alias("k")), n, 3))
            m = memory_counts(s, spec, p).agg(F.sum("nodes"), F.max("bytes")).first()
            return m[0] or 0, m[1] or 0

        _, atoms = max_capacity(build, budget, start=4 * p)
        first = first or atoms or 1
        out.append((family, p, atoms, atoms / first))
    return out


@query("capacity_curve")
def capacity_curve(spark, sf_dir):
    """Atoms that fit a budget for each part, that of a fifth of the table on one part, against the number of parts: close to
    proportional. No SQL, for it is a search; tests hold it against all sizes."""
    s = systems.quartz(spark, sf_dir)
    one = memory_counts(s, replace(SHORT, family="ring"), 1).agg(F.max("bytes")).first()[0] or 0
    return spark.createDataFrame([r for f, parts in (("ring", (1, 2, 4, 8)), ("invariant_bond", (1, 4))) for r in capacity_points(spark, f, parts, max(1_000_000, one // 5))], "family string, parts int, atoms long, relative double")


@query("out_of_memory", q.select(q.quartz() + q.edges(LONG) + q.walls(P) + q.owners() + q.part_counts(), "SELECT layers, max(bytes) > 30 * 8 * (SELECT max(n) FROM counts) AS out_of_memory, CAST(max(bytes) AS BIGINT) AS most_bytes FROM (SELECT layers, ((n + h) * (layers + 1) + e * 7) * 8 AS bytes FROM counts, (VALUES (2), (10)) t(layers)) GROUP BY layers"))
def out_of_memory(spark, sf_dir):
    """Modelled bytes of the fullest part against a budget in proportion to its atoms, for few and for many layers."""
    graph = build_partitioned_graph(systems.quartz(spark, sf_dir), RING, P)
    most = graph.nodes.groupBy("part_id").count().agg(F.max("count")).first()[0] or 0
    return _union(over_budget(memory_model(graph, replace(RING, layers=n)), 30 * 8 * most).withColumn("layers", F.lit(n)) for n in (2, 10))


@query("model_size_sweep", q.select(q.quartz() + q.edges(BOND) + q.walls(P) + q.owners() + q.part_counts(), "SELECT w AS width, 3 * (w * w + 16 * w) AS parameters, CAST(max((n + h) * 4 * w + e * (6 + w)) * 8 AS BIGINT) AS most_bytes FROM counts, (VALUES (1), (2), (4), (8), (16)) t(w) GROUP BY w"))
def model_size(spark, sf_dir):
    """Parameters and the modelled bytes of the fullest part as the model grows wider at a fixed number of layers."""
    spec = replace(RING, cutoff=BOND)
    graph = build_partitioned_graph(systems.quartz(spark, sf_dir), spec, P)
    wide = lambda w: replace(spec, width=w)
    return _union(memory_model(graph, wide(w)).agg(F.max("bytes").alias("most_bytes")).select(F.lit(w).alias("width"), F.lit(wide(w).n_parameters()).alias("parameters"), "most_bytes") for w in (1, 2, 4, 8, 16))


@query("exactness_all_partitioners", q.select(q.quartz(), "SELECT method, count(*) AS rows, CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS max_error FROM atoms, (VALUES ('wall'), ('hash'), ('random'), ('blocks'), ('rcb'), ('morton'), ('bfs'), ('labelprop'), ('greedy'), ('multilevel'), ('spectral')) m(method) GROUP BY method"))
def exact_partitioners(spark, sf_dir):
    """Whatever the partition, the answer is that of one device."""
    scratch, spec = Scratch(spark), replace(RING, cutoff=BOND, layers=2)
    s = systems.quartz(spark, sf_dir)
    one = run_single(s, spec, scratch)
    return _union(exactness(one, _result(infer(s, spec, P, method=m, scratch=scratch)[1])).withColumn("method", F.lit(m)) for m in partition.METHODS)


LAYERS = (1, 2, 4)


@query("transfer_constant_in_layers", q.select(q.quartz() + q.edges(BOND) + q.walls(P) + q.owners(), "SELECT layers, layer, sent FROM (SELECT count(*) AS sent FROM halo), (VALUES " + ", ".join(f"({n}, {k})" for n in LAYERS for k in range(n)) + ") t(layers, layer)"))
def transfer_constant(spark, sf_dir):
    """Rows that each layer of a run receives from other parts, counted where the layer reads them."""
    s, rows = systems.quartz(spark, sf_dir), []
    for n in LAYERS:
        spec = replace(RING, cutoff=BOND, layers=n)
        graph, _ = infer(s, spec, P)
        model = potential(spec)
        for k, layer in enumerate(graph.trace):
            sent = exchange(layer.select("lane", "atom_id", *model.state), graph.outbox, graph.lanes)
            rows.append(sent.agg(F.count(F.lit(1)).alias("sent")).select(F.lit(n).alias("layers"), F.lit(k).alias("layer"), "sent"))
    return _union(rows)


_RULES = {
    "wall": f"SELECT atom_id, least({P - 1}, x * {P} // lx) AS part_id FROM atoms, cell",
    "hash": f"SELECT atom_id, atom_id % {P} AS part_id FROM atoms",
    "random": f"SELECT atom_id, ((atom_id % 2147483647 * 48271 + 12345) % 2147483647) // 1024 % {P} AS part_id FROM atoms",
    "blocks": "SELECT atom_id, (x * 2 // lx * 2 + y * 2 // ly) * 2 + z * 2 // lz AS part_id FROM atoms, cell",
    "rcb": "SELECT atom_id, a * 4 + b * 2 + c AS part_id FROM r3",
    "morton": "SELECT atom_id, ntile(8) OVER (ORDER BY code, atom_id) - 1 AS part_id FROM coded",
}


def _comparison_sql() -> str:
    from halograph.queries.graphs import MORTON, RCB

    names = list(_RULES)
    # one row for an atom with its part by every rule, so an edge looks each end up once
    joined = " JOIN ".join(f"(SELECT atom_id, CAST(part_id AS INT) AS {m}_part FROM ({body}))" + (" USING (atom_id)" if k else "") for k, (m, body) in enumerate(_RULES.items()))
    pair = ", ".join(f"s.{m}_part AS s_{m}, t.{m}_part AS t_{m}" for m in names)
    ctes = q.quartz() + q.edges(BOND) + RCB + MORTON + [
        ("wide_parts", f"SELECT * FROM {joined}"),
        ("both_ends", f"SELECT e.src, {pair} FROM edges e JOIN wide_parts s ON s.atom_id = e.src JOIN wide_parts t ON t.atom_id = e.dst"),
        ("crossed", " UNION ALL ".join(f"SELECT '{m}' AS method, t_{m} AS part_id, src AS atom_id FROM both_ends WHERE s_{m} <> t_{m}" for m in names)),
        ("halos", "SELECT DISTINCT * FROM crossed"),
        ("per_node", "SELECT method, atom_id, count(*) AS n FROM halos GROUP BY method, atom_id"),
        ("assigns", " UNION ALL ".join(f"SELECT '{m}' AS method, {m}_part AS part_id FROM wide_parts" for m in names)),
        ("sizes", "SELECT method, max(n) AS most_nodes, min(n) AS least_nodes FROM (SELECT method, part_id, count(*) AS n FROM assigns GROUP BY ALL) GROUP BY method"),
        ("cuts", "SELECT method, count(*) AS edge_cut FROM crossed GROUP BY method"),
    ]
    return q.select(ctes, "SELECT method, CAST(sum(n) AS BIGINT) AS sent, count(*) FILTER (n > 1) AS overlap, any_value(edge_cut) AS edge_cut, any_value(most_nodes) AS most_nodes, any_value(least_nodes) AS least_nodes FROM per_node JOIN sizes USING (method) JOIN cuts USING (method) GROUP BY method")


def _compared(spark, sf_dir, methods, s=None, cutoff: int = BOND):
    from halograph.measures import partition_quality

    scratch = Scratch(spark)
    s = s or systems.quartz(spark, sf_dir)
    edges = scratch.keep(neighbors.neighbor_list(s.atoms, s.cell, cutoff) if s.edges is None else neighbors.explicit_graph(s.edges), "edges")
    rows = []
    for m in methods:
        a = scratch.keep(partition.partition(s.atoms, edges, s.cell, P, m, scratch), "assign")
        sent = transfer_volume(halo.assign_buckets(a, halo.border_nodes(edges, a))).drop("bytes")
        rows.append(sent.crossJoin(partition_quality(edges, a).select("edge_cut", "most_nodes", "least_nodes")).withColumn("method", F.lit(m)))  # one row each
    return _union(rows)


@query("partitioner_comparison", _comparison_sql())
def partitioner_comparison(spark, sf_dir):
    """What walls send against other rules on the crystal, with cut and balance: walls and curves far less than hashing."""
    return _compared(spark, sf_dir, tuple(_RULES))


@query("partitioner_graph_methods")
def partitioner_graph_methods(spark, sf_dir):
    """The same for the rules that read the edges. No SQL, for they run in rounds; tests bound cut and balance."""
    return _compared(spark, sf_dir, ("bfs", "labelprop", "greedy", "multilevel", "spectral"))


CUTOFFS = (2000, 3000, 3500, 4000, 4500)
_LINKS = [
    ("ends", " UNION ALL ".join(f"SELECT {c} AS cutoff, * FROM edges WHERE d2 <= {c * c}" for c in CUTOFFS)),
    ("ins", "SELECT cutoff, dst AS v, count(*) AS n FROM ends GROUP BY ALL"),
    ("outs", "SELECT cutoff, src AS v, count(*) AS n FROM ends GROUP BY ALL"),
    ("points", "SELECT cutoff, CAST(sum(i.n) AS BIGINT) AS bonds, CAST(sum(i.n * o.n) - sum(i.n) AS BIGINT) AS links FROM ins i JOIN outs o USING (cutoff, v) GROUP BY cutoff"),
]


def _three_body(spark, sf_dir):
    from halograph.graph.bondgraph import line_graph

    s = systems.quartz(spark, sf_dir)
    edges = Scratch(spark).keep(neighbors.neighbor_list(s.atoms, s.cell, CUTOFFS[-1]), "edges")
    return _union(neighbors.bonds(edges, c).agg(F.count(F.lit(1)).alias("bonds")).crossJoin(line_graph(neighbors.bonds(edges, c)).agg(F.count(F.lit(1)).alias("links"))).withColumn("cutoff", F.lit(c)) for c in CUTOFFS)


@query("three_body_counts", q.select(q.quartz() + q.edges(CUTOFFS[-1]) + _LINKS, "SELECT * FROM points"))
def three_body_counts(spark, sf_dir):
    """Bonds and links of the bond graph as the bond cutoff grows; SQL has them from the degrees: each pair in and out of
    an atom, less the ways back."""
    return _three_body(spark, sf_dir)


@query("three_body_growth", q.select(q.quartz() + q.edges(CUTOFFS[-1]) + _LINKS, "SELECT round(regr_slope(ln(links), ln(bonds / (SELECT count(*) FROM atoms))), 6) AS exponent FROM points"))
def three_body_growth(spark, sf_dir):
    """Exponent of links over bonds for each atom: about two."""
    n = systems.quartz(spark, sf_dir).atoms.count()
    points = _three_body(spark, sf_dir).select((F.col("bonds") / n).alias("degree"), "links")
    return growth_exponent(points, "degree", "links").select(F.round("exponent", 6).alias("exponent"))


REAL = {"quartz": q.quartz() + q.edges(BOND), "liquid": q.liquid() + q.edges(1000, False), "lattice": q.lattice() + q.edges(2000), "cloud": q.cloud() + q.edges(100, False), "successor": q.successor()}
#: The numbers of devices of the experiments.
DEVICES = (1, 4, 8)


def real_system(name: str, spark, sf_dir):
    """(system, cutoff) of the stand-in for a material of the experiments."""
    made = {"quartz": (systems.quartz, BOND), "liquid": (systems.liquid, 1000), "lattice": (systems.lattice, 2000), "cloud": (systems.cloud, 100), "successor": (systems.successor, BOND)}
    build, cutoff = made[name]
    return build(spark, sf_dir), cutoff


@query(
    "real_systems_summary",
    " UNION ALL ".join(f"SELECT '{n}' AS system, parts, * EXCLUDE (parts) FROM (" + q.select(c + q.ring(2), f"SELECT (SELECT count(*) FROM atoms) AS atoms, (SELECT count(*) FROM edges) AS edges, CAST((SELECT sum(h0) FROM s2) AS BIGINT) AS energy, parts FROM (VALUES {', '.join(f'({p})' for p in DEVICES)}) d(parts)") + ")" for n, c in REAL.items()),
)
def real_systems(spark, sf_dir):
    """Stand-ins for the materials of the experiments on 1, 4 and 8 parts, one model: atoms, edges and energy."""
    rows = []
    for name in REAL:
        s, cutoff = real_system(name, spark, sf_dir)
        spec = replace(RING, cutoff=cutoff, layers=2)
        for p in DEVICES:
            g, state = infer(s, spec, p)
            row = g.nodes.agg(F.count(F.lit(1)).alias("atoms")).crossJoin(g.edges.agg(F.count(F.lit(1)).alias("edges"))).crossJoin(energy(state, potential(spec)))
            rows.append(row.select(F.lit(name).alias("system"), F.lit(p).alias("parts"), "atoms", "edges", "energy"))
    return _union(rows)
