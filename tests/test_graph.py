"""The worked chain, shapes the experiments report, and plans."""

from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from halograph.baselines.single import run_single
from halograph.baselines.spatial import boxes, run_spatial
from halograph.graph import bondgraph, halo, neighbors, partition
from halograph.graph.lanes import bucket_hash, lane_keys, within_lanes
from halograph.graph.runtime import backward, build_partitioned_graph, conv_layer, energy, exchange, forward, infer
from halograph.graph.scratch import Scratch
from halograph.measures import exactness, max_capacity, ns_days, scaling, transfer_volume
from halograph.plans import assert_no_cartesian, count_exchanges, pushed_filters
from halograph.potentials import PotentialSpec, potential
from halograph.sources import systems, xyz
from halograph.sources.systems import Cell, System
from halograph.sources.tables import read


@pytest.fixture
def chain(spark):
    """Six nodes in a row, 1000 apart, an open box, two parts."""
    atoms = spark.createDataFrame([(i, 0, 1000 * i, 0, 0) for i in range(6)], "atom_id long, species int, x long, y long, z long")
    s = System("row", atoms, Cell((6000, 10, 10), (False,) * 3))
    edges = neighbors.neighbor_list(s.atoms, s.cell, 1000)
    return s, edges, partition.wall_partition(s.atoms, s.cell, 2)


def pairs(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())


def test_worked_chain(chain):
    s, edges, assign = chain
    assert edges.count() == 10
    assert pairs(assign, "atom_id", "part_id") == [(0, 0), (1, 0), (2, 0), (3, 1), (4, 1), (5, 1)]
    h = halo.border_nodes(edges, assign)
    assert pairs(h, "part_id", "atom_id") == [(0, 3), (1, 2)]
    assert pairs(halo.k_hop_halo(edges, assign, 2).filter("hop = 2"), "part_id", "atom_id") == [(0, 4), (1, 1)]
    assert pairs(halo.border_edges(edges, h, assign), "part_id", "src", "dst") == [(0, 2, 3), (0, 4, 3), (1, 1, 2), (1, 3, 2)]
    assert pairs(halo.border_edges(edges, h, assign, "induced"), "part_id", "src", "dst") == [(0, 4, 3), (1, 1, 2)]
    b = halo.assign_buckets(assign, h)
    layout = {r.part_id: (r.nodes, r.markers) for r in halo.pack_layout(b, 2).collect()}
    assert layout == {0: ([0, 1, 2, 3], [0, 2, 2, 3, 3, 4]), 1: ([4, 5, 3, 2], [0, 2, 3, 3, 4, 4])}
    assert bondgraph.line_graph(edges).count() == 8
    assert bondgraph.bond_graph(edges, assign).groupBy("part_id").count().count() == 2


def test_deduplicated_layout_reads_as_the_spans(spark, sf_dir):
    """Walls so thin that nodes have several peers: each node once, and the index gives every span again."""
    s = systems.quartz(spark, sf_dir)
    edges, assign = neighbors.neighbor_list(s.atoms, s.cell, 3000), partition.wall_partition(s.atoms, s.cell, 24)
    b = Scratch(spark).keep(halo.assign_buckets(assign, halo.border_nodes(edges, assign)), "buckets")
    spans = {r.part_id: r for r in halo.pack_layout(b, 24).collect()}
    once = {r.part_id: r for r in halo.pack_layout(b, 24, "dedup").collect()}
    assert any(len(once[k].nodes) < len(spans[k].nodes) for k in spans)
    for k, r in once.items():
        assert len(set(r.nodes)) == len(r.nodes) and [r.nodes[i] for i in r["index"]] == spans[k].nodes and r.markers == spans[k].markers


@pytest.mark.parametrize("p", [1, 2, 3, 6, 9])
def test_answer_does_not_depend_on_parts(chain, p):
    s, edges, _ = chain
    explicit = replace(s, edges=edges.select("src", "dst", F.lit(1).cast("long").alias("w")))
    state = infer(explicit, PotentialSpec(layers=2), p)[1]
    assert [r.h0 for r in state.orderBy("atom_id").collect()] == [5, 8, 9, 9, 8, 5]


def test_isolated_nodes_and_empty_systems(spark):
    nodes = spark.createDataFrame([(1, 3), (2, 4)], "atom_id long, species int")
    none = spark.createDataFrame([], "src long, dst long, w long")
    assert [r.h0 for r in infer(System("none", nodes, None, none), PotentialSpec(layers=3), 2)[1].orderBy("atom_id").collect()] == [4, 5]
    empty = System("empty", nodes.limit(0), None, none)
    assert infer(empty, PotentialSpec(layers=1), 2)[1].count() == 0


def test_two_atoms_in_one_place_and_on_a_wall(spark):
    atoms = spark.createDataFrame([(0, 0, 500, 0, 0), (1, 0, 500, 0, 0), (2, 0, 1000, 0, 0)], "atom_id long, species int, x long, y long, z long")
    cell = Cell((2000, 10, 10), (False,) * 3)
    assert neighbors.neighbor_list(atoms, cell, 400).count() == 2
    assert [r.part_id for r in partition.wall_partition(atoms, cell, 2).orderBy("atom_id").collect()] == [0, 0, 1]


def test_broadcast_neighbours_are_refused_for_large_systems(spark):
    atoms = spark.range(21_000).select(F.col("id").alias("atom_id"), F.lit(0).alias("species"), *[F.col("id").alias(a) for a in "xyz"])
    with pytest.raises(ValueError):
        neighbors.neighbor_list(atoms, Cell((1, 1, 1), (False,) * 3), 5, method="broadcast")


def test_padding_redundancy_grows_and_graph_partitioning_does_not(spark, sf_dir):
    from halograph.catalog import QUERIES

    rows = {(r.method, r.reach): (r.computed, r.needed) for r in QUERIES["redundancy_vs_range"](spark, sf_dir).collect()}
    for how in ("slab", "block3d"):
        line = [rows[how, r][0] / rows[how, r][1] for r in (5000, 10000, 20000, 40000)]
        assert line == sorted(line) and line[0] > 1 and line[-1] > 2 * line[0]
    assert all(rows["graph", r][0] == rows["graph", r][1] for r in (5000, 10000, 20000, 40000))


def test_thin_walls_overlap(spark, sf_dir):
    from halograph.catalog import QUERIES

    rows = {r.parts: (r.sent, r.overlap) for r in QUERIES["narrow_walls_overlap"](spark, sf_dir).collect()}
    assert rows[2][1] == 0 and rows[32][1] > 0 and rows[32][0] > rows[8][0] > rows[4][0]


def test_walls_send_less_than_hashing(spark, sf_dir):
    from halograph.catalog import QUERIES

    sent = {r.method: r.sent for r in QUERIES["partitioner_comparison"](spark, sf_dir).collect()}
    assert sent["wall"] * 3 < sent["hash"] and sent["wall"] * 3 < sent["random"]
    graph = {r.method: r for r in QUERIES["partitioner_graph_methods"](spark, sf_dir).collect()}
    n = systems.quartz(spark, sf_dir).atoms.count()
    for m in ("labelprop", "greedy", "multilevel", "spectral"):
        assert graph[m].most_nodes <= 1.5 * n / 8 and graph[m].sent < sent["hash"], m
    assert graph["bfs"].sent < sent["hash"]


def test_three_body_exponent_is_about_two(spark, sf_dir):
    from halograph.catalog import QUERIES

    assert 1.7 < QUERIES["three_body_growth"](spark, sf_dir).first()[0] < 2.4


def test_capacity_is_the_largest_size_that_fits(spark):
    """Against every size in turn, and in proportion to the parts."""
    from halograph.measures import memory_counts
    from halograph.queries.models import SHORT, capacity_points

    budget = 300_000
    (_, _, one, _), (_, _, two, more) = capacity_points(spark, "ring", (1, 2), budget)
    for p, best in ((1, one), (2, two)):
        fits = []
        for size in range(1, best // 162 + 3):
            s = System("rod", *systems.rod(spark.range(size * 162).select(F.col("id").alias("k")), size * 162, 3))
            fits.append((memory_counts(s, replace(SHORT, family="ring"), p).agg(F.max("bytes")).first()[0] or 0) <= budget)
        assert fits.index(False) * 162 == best
    assert 1.5 < more < 2.5


def test_memory_counts_agree_with_a_graph_that_is_built(spark, sf_dir):
    from halograph.measures import memory_counts, memory_model

    spec = PotentialSpec("invariant_bond", layers=1, cutoff=3000, bond_cutoff=2000)
    s = systems.quartz(spark, sf_dir)
    cols = ("part_id", "nodes", "halo", "edges", "links", "bytes")
    assert pairs(memory_counts(s, spec, 3), *cols) == pairs(memory_model(build_partitioned_graph(s, spec, 3), spec), *cols)


def test_spatial_needs_full_padding(spark, sf_dir):
    spec = PotentialSpec(layers=2, cutoff=3000)
    s = systems.quartz(spark, sf_dir)
    one = Scratch(spark).keep(run_single(s, spec), "one")
    assert exactness(one, run_spatial(s, spec, 3).drop("part_id")).first().max_error == 0
    assert exactness(one, run_spatial(s, spec, 3, pad=3000).drop("part_id")).first().max_error > 0
    assert boxes(s.cell, 8, "block3d")[0] >= 2 and boxes(s.cell, 4) == (4, 1, 1) and boxes(s.cell, 8, "block3d") != (8, 1, 1)


def test_plans(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    edges = neighbors.neighbor_list(s.atoms, s.cell, 3000)
    assert_no_cartesian(edges)
    assert count_exchanges(edges) <= 2
    assert "GreaterThan" in str(pushed_filters(read(spark, sf_dir, "lineitem").filter("l_quantity > 49").select("l_orderkey")))


def test_lanes_are_the_buckets_of_the_parts(spark):
    values = [0, 1, 7, 100, 12345, 2**31 - 1]
    assert [r[0] for r in spark.createDataFrame([(v,) for v in values], "v int").select(F.hash("v")).collect()] == [bucket_hash(v) for v in values]
    for p in (1, 2, 8, 60):
        assert [bucket_hash(k) % p for k in lane_keys(p)] == list(range(p))


def test_a_layer_shuffles_border_rows_and_nothing_else(spark, sf_dir):
    """One exchange in the plan of a layer, also without broadcasts, and it carries the rows of the outboxes."""
    s = systems.quartz(spark, sf_dir)
    spec = PotentialSpec("light", layers=2, cutoff=3000)
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        graph = build_partitioned_graph(s, spec, 4)
        forward(graph, spec)
        model = potential(spec)
        state = graph.trace[0].select("lane", "part_id", "atom_id", *model.state)
        with within_lanes(spark):
            layer = conv_layer(state, exchange(state, graph.outbox, graph.lanes), graph.edges, model, ["lane"])
            assert count_exchanges(layer) == 1
            assert count_exchanges(exchange(state, graph.outbox, graph.lanes)) == 1
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    sent = exchange(state, graph.outbox, graph.lanes).count()
    assert sent == transfer_volume(graph.buckets).first().sent == graph.outbox.count() < graph.edges.count() / 10
    assert transfer_volume(graph.buckets).first().overlap == 0


@pytest.mark.parametrize("family", ["ring", "many_body", "light", "smooth", "invariant_bond"])
def test_forces_are_minus_the_slope_of_the_energy(spark, family):
    """Central differences in doubles, on a small crystal in three parts, so that border slopes have to come home."""
    n = 180
    keys = spark.range(n).select(F.col("id").alias("k"))
    atoms, cell = systems.rod(keys, n, 1)
    # a narrow rod would meet its own images: open sides
    cell = Cell(cell.lengths, (True, False, False))
    atoms = Scratch(spark).keep(atoms.select("atom_id", "species", *[F.col(a).cast("double").alias(a) for a in "xyz"]), "atoms")
    spec = PotentialSpec(family, layers=2, cutoff=3500, bond_cutoff=2500, arithmetic="real", width=2 if family != "invariant_bond" else 1)

    def run(rows):
        s = System("rod", rows, cell)
        graph = build_partitioned_graph(s, spec, 3)
        return graph, energy(forward(graph, spec), potential(spec)).first()[0]

    graph, _ = run(atoms)
    forces = {r.atom_id: r for r in backward(graph, spec).collect()}
    for a in "xyz":
        assert abs(sum(f[f"f{a}"] for f in forces.values())) < 1e-6 * max(abs(f[f"f{a}"]) for f in forces.values())
    for atom, axis in ((0, "x"), (59, "y"), (100, "z")):
        step = 1e-2
        up, down = (run(atoms.withColumn(axis, F.when(F.col("atom_id") == atom, F.col(axis) + d).otherwise(F.col(axis))))[1] for d in (step, -step))
        want = -(up - down) / (2 * step)
        assert abs(forces[atom][f"f{axis}"] - want) <= 1e-4 * max(abs(want), abs(forces[atom].fx), abs(forces[atom].fy), abs(forces[atom].fz)), (family, atom, axis)


def test_a_plug_in_without_adjoints_has_no_conservative_forces(spark, chain):
    from halograph.potentials import Potential, RingPotential, register_potential

    class Bare(Potential):
        pass

    class Changed(RingPotential):
        def update(self):
            return {h: F.col(h) * 2 + F.col(f"sum_{h}") for h in self.channels}

    s, edges, _ = chain
    for name, cls in (("bare", Bare), ("changed", Changed)):
        register_potential(name, cls)
        spec = PotentialSpec(name, layers=1, cutoff=1000)
        graph, state = infer(s, spec, 2)
        assert state.count() == 6
        with pytest.raises(NotImplementedError):
            backward(graph, spec)


def test_md_keeps_its_energy(spark):
    """Doubles, small steps: the sum of kinetic and potential energy drifts far less than either changes."""
    from halograph.dynamics import md_run

    n = 180
    atoms, cell = systems.rod(spark.range(n).select(F.col("id").alias("k")), n, 1)
    s = System("rod", atoms, Cell(cell.lengths, (True, False, False)))
    spec = PotentialSpec("many_body", layers=1, cutoff=3500, nu=2, arithmetic="real")
    md_run(s, spec, 2, 4, soft=1e-4).count()
    total = [p + k for _, p, k in md_run.energies]
    change = max(k for _, _, k in md_run.energies)
    assert change > 0 and max(abs(t - total[0]) for t in total) < 0.05 * change


def test_files_of_systems(spark, sf_dir, tmp_path):
    f = tmp_path / "a.xyz"
    f.write_text("2\ncell\n0 8 1 2 3\n1 14 -4 5 6\n")
    assert pairs(xyz.read(spark, str(f)), "atom_id", "species", "x") == [(0, 8, 1), (1, 14, -4)]


def test_measures(spark):
    assert round(ns_days(9.6, 250_000, 1.0), 1) == 27.8
    assert max_capacity(lambda n: (n * 10, n * 100), 550) == (5, 50) and max_capacity(lambda n: (n, 9), 5) == (0, 0)
    t = spark.createDataFrame([("a", 1, 10), ("a", 2, 6)], "family string, parts int, wall_us long")
    assert [r.relative for r in scaling(t, "weak").orderBy("parts").collect()] == [1.0, 0.6]
    assert PotentialSpec(layers=2).matched_to(160).width == 4


def test_md_with_skin_gives_the_same_path(spark, sf_dir):
    from halograph.dynamics import md_run

    s, spec = systems.cloud(spark, sf_dir), PotentialSpec(cutoff=100, layers=1)
    runs = [Scratch(spark).keep(md_run(s, spec, 2, 2, skin=k).filter("step = 2"), "run") for k in (0, 40)]
    assert exactness(*runs).first().max_error == 0


def test_model_sees_the_source_state(spark, sf_dir):
    assert potential(PotentialSpec("light", width=2)).state == ["h0", "vx0", "vy0", "vz0", "h1", "vx1", "vy1", "vz1"]
