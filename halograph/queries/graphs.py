"""Neighbour lists, partitions, borders, layouts and bond graphs on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from halograph.catalog import query
from halograph.graph import bondgraph, halo, neighbors, partition
from halograph.graph.runtime import system_edges
from halograph.graph.scratch import Scratch
from halograph.measures import partition_quality
from halograph.potentials import PotentialSpec
from halograph.sources import systems
from halograph.twins import sql as q

BOND = 3000
P = 4
KEY = "src, dst, ix, iy, iz"
EDGE = f"{KEY}, dx, dy, dz, d2"


def quartz_bonds(spark, sf_dir: str) -> tuple[systems.System, DataFrame, DataFrame]:
    s = systems.quartz(spark, sf_dir)
    return s, neighbors.neighbor_list(s.atoms, s.cell, BOND), partition.wall_partition(s.atoms, s.cell, P)


BASE = q.quartz() + q.edges(BOND)
PARTED = BASE + q.walls(P) + q.owners()


@query("nl_quartz", q.select(BASE, f"SELECT {EDGE} FROM edges"))
def nl_quartz(spark, sf_dir):
    return quartz_bonds(spark, sf_dir)[1]


@query("nl_quartz_degree", q.select(q.quartz() + q.edges(5000), "SELECT degree, count(*) AS atoms FROM (SELECT dst, count(*) AS degree FROM edges GROUP BY dst) GROUP BY degree"))
def nl_quartz_degree(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    return neighbors.neighbor_list(s.atoms, s.cell, 5000).groupBy("dst").agg(F.count(F.lit(1)).alias("degree")).groupBy("degree").agg(F.count(F.lit(1)).alias("atoms"))


@query("nl_cloud_open", q.select(q.cloud() + q.edges(100, False), f"SELECT {EDGE} FROM edges"))
def nl_cloud_open(spark, sf_dir):
    s = systems.cloud(spark, sf_dir)
    return neighbors.neighbor_list(s.atoms, s.cell, 100)


@query("nl_cloud_broadcast", q.select(q.cloud() + q.edges(100, False), f"SELECT {EDGE} FROM edges"))
def nl_cloud_broadcast(spark, sf_dir):
    s = systems.cloud(spark, sf_dir)
    return neighbors.neighbor_list(s.atoms, s.cell, 100, method="broadcast")


@query("nl_liquid", q.select(q.liquid() + q.edges(2000, False), "SELECT dst, count(*) AS degree, CAST(sum(d2) AS BIGINT) AS total_d2 FROM edges GROUP BY dst"))
def nl_liquid(spark, sf_dir):
    s = systems.liquid(spark, sf_dir)
    return neighbors.neighbor_list(s.atoms, s.cell, 2000).groupBy("dst").agg(F.count(F.lit(1)).alias("degree"), F.sum("d2").alias("total_d2"))


@query("nl_lattice_smallcell", q.select(q.lattice(2) + q.rod_edges(5000, 2), f"SELECT {EDGE} FROM edges"))
def nl_lattice_smallcell(spark, sf_dir):
    s = systems.lattice(spark, sf_dir, 2)  # a rod of 4000 by 4000, less than the cutoff: several images of one atom
    return neighbors.neighbor_list(s.atoms, s.cell, 5000)


CUTS = (2000, 2829, 3465)


@query("nl_lattice_degrees", q.select(q.lattice() + q.edges(CUTS[-1]), "SELECT cutoff, degree, count(*) AS atoms FROM (" + " UNION ALL ".join(f"SELECT {c} AS cutoff, dst, count(*) AS degree FROM edges WHERE d2 <= {c * c} GROUP BY dst" for c in CUTS) + ") GROUP BY cutoff, degree"))
def nl_lattice_degrees(spark, sf_dir):
    """6, 18 and 26 neighbours inside the lattice, fewer beside the empty sites of its last layer."""
    s, out = systems.lattice(spark, sf_dir), None
    for c in CUTS:
        d = neighbors.neighbor_list(s.atoms, s.cell, c).groupBy("dst").agg(F.count(F.lit(1)).alias("degree"))
        one = d.groupBy("degree").agg(F.count(F.lit(1)).alias("atoms")).withColumn("cutoff", F.lit(c))
        out = one if out is None else out.union(one)
    return out


@query("bonds_two_cutoffs", q.select(q.quartz() + q.edges(5000), "SELECT count(*) AS edges, count(*) FILTER (d2 <= 9000000) AS bonds, count(*) FILTER (d2 <= 4000000) AS short_bonds FROM edges"))
def bonds_two_cutoffs(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    e = neighbors.neighbor_list(s.atoms, s.cell, 5000)
    within = lambda r: F.count(F.when(F.col("d2") <= r * r, 1))
    return e.agg(F.count(F.lit(1)).alias("edges"), within(3000).alias("bonds"), within(2000).alias("short_bonds"))


@query("explicit_graph", q.select(q.successor(), "SELECT src, dst, w FROM edges"))
def explicit_graph(spark, sf_dir):
    return neighbors.explicit_graph(systems.successor(spark, sf_dir).edges).select("src", "dst", "w")


@query("walls_width", q.select(q.quartz() + q.walls(P), "SELECT atom_id, part_id FROM assign"))
def walls_width(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    return partition.wall_partition(s.atoms, s.cell, P)


@query("walls_count", q.select(q.quartz(), "SELECT atom_id, CAST(ntile(7) OVER (ORDER BY x, atom_id) - 1 AS INT) AS part_id FROM atoms"))
def walls_count(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    return partition.wall_partition(s.atoms, s.cell, 7, balance="count")


@query("walls_id_axis", q.select(q.successor() + q.id_walls(5), "SELECT atom_id, part_id FROM assign"))
def walls_id_axis(spark, sf_dir):
    return partition.wall_partition(systems.successor(spark, sf_dir).atoms, None, 5, axis="id")


@query("walls_forced_axis", q.select(q.quartz() + q.walls(3, "y"), "SELECT atom_id, part_id FROM assign"))
def walls_forced_axis(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    return partition.wall_partition(s.atoms, s.cell, 3, axis="y")


@query("walls_quantile")  # sketched walls: near-equal counts, rows only
def walls_quantile(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    return partition.wall_partition(s.atoms, s.cell, P, balance="quantile").groupBy("part_id").count()


@query("border_nodes", q.select(PARTED, "SELECT * FROM halo"))
def border_nodes(spark, sf_dir):
    s, e, a = quartz_bonds(spark, sf_dir)
    return halo.border_nodes(e, a)


@query("expanded_nodes", q.select(PARTED, "SELECT part_id, atom_id, part_id AS owner FROM assign UNION ALL SELECT part_id, atom_id, owner FROM halo"))
def expanded_nodes(spark, sf_dir):
    s, e, a = quartz_bonds(spark, sf_dir)
    return halo.expanded_nodes(e, a)


@query(
    "halo_two_hop",
    q.select(PARTED + [("far", "SELECT DISTINCT h.part_id, e.src AS atom_id FROM halo h JOIN edges e ON e.dst = h.atom_id")], "SELECT part_id, atom_id, hop, owner FROM halo UNION ALL SELECT f.part_id, f.atom_id, 2, a.part_id FROM far f JOIN assign a USING (atom_id) WHERE a.part_id <> f.part_id AND NOT EXISTS (SELECT 1 FROM halo h WHERE h.part_id = f.part_id AND h.atom_id = f.atom_id)"),
)
def halo_two_hop(spark, sf_dir):
    s, e, a = quartz_bonds(spark, sf_dir)
    return halo.k_hop_halo(e, a, 2)


UNOWNED = [("border", "SELECT h.part_id, h.owner, e.* FROM halo h JOIN edges e ON e.dst = h.atom_id")]


@query("border_edges_unowned", q.select(PARTED + UNOWNED, f"SELECT part_id, owner, {EDGE} FROM border"))
def border_edges_unowned(spark, sf_dir):
    s, e, a = quartz_bonds(spark, sf_dir)
    return halo.border_edges(e, halo.border_nodes(e, a), a)


@query("border_edges_induced", q.select(PARTED + UNOWNED, f"SELECT part_id, owner, {EDGE} FROM border b WHERE NOT EXISTS (SELECT 1 FROM assign a WHERE a.part_id = b.part_id AND a.atom_id = b.src) AND NOT EXISTS (SELECT 1 FROM halo h WHERE h.part_id = b.part_id AND h.atom_id = b.src)"))
def border_edges_induced(spark, sf_dir):
    s, e, a = quartz_bonds(spark, sf_dir)
    return halo.border_edges(e, halo.border_nodes(e, a), a, "induced")


@query("owned_edges", q.select(PARTED, f"SELECT part_id, {EDGE} FROM owned"))
def owned_edges(spark, sf_dir):
    s, e, a = quartz_bonds(spark, sf_dir)
    return halo.owned_edges(e, a)


@query("buckets", q.select(PARTED + q.buckets(), "SELECT * FROM buckets"))
def buckets(spark, sf_dir):
    s, e, a = quartz_bonds(spark, sf_dir)
    return halo.assign_buckets(a, halo.border_nodes(e, a))


@query("bucket_duality", "SELECT CAST(0 AS BIGINT) AS violations")
def bucket_duality(spark, sf_dir):
    return halo.check_bucket_duality(buckets(spark, sf_dir))


SLOT = f"CASE kind WHEN 'PURE' THEN 0 WHEN 'TO' THEN peer + 1 ELSE peer + {P + 1} END"
GRID = f"SELECT a.i AS part_id, b.k AS k FROM range({P}) a(i), range({2 * P + 2}) b(k)"


@query("layout_markers", q.select(PARTED + q.buckets() + [("grid", GRID)], f"SELECT CAST(part_id AS INT) AS part_id, CAST(k AS INT) AS k, (SELECT count(*) FROM buckets b WHERE b.part_id = g.part_id AND {SLOT} < g.k) AS marker FROM grid g"))
def layout_markers(spark, sf_dir):
    return halo.markers(buckets(spark, sf_dir), P)


@query("layout_nodes", q.select(PARTED + q.buckets(), f"SELECT part_id, row_number() OVER (PARTITION BY part_id ORDER BY {SLOT}, atom_id) - 1 AS pos, atom_id FROM buckets"))
def layout_nodes(spark, sf_dir):
    return halo.pack_layout(buckets(spark, sf_dir), P).select("part_id", F.posexplode("nodes").alias("pos", "atom_id")).withColumn("pos", F.col("pos").cast("long"))


@query(
    "layout_dedup",
    q.select(PARTED + q.buckets() + [("ranked", f"SELECT part_id, atom_id, row_number() OVER (PARTITION BY part_id ORDER BY {SLOT}, atom_id) AS r FROM buckets")], "SELECT part_id, row_number() OVER (PARTITION BY part_id ORDER BY min(r)) - 1 AS pos, atom_id FROM ranked GROUP BY part_id, atom_id"),
)
def layout_dedup(spark, sf_dir):
    packed = halo.pack_layout(buckets(spark, sf_dir), P, "dedup")
    return packed.select("part_id", F.posexplode("nodes").alias("pos", "atom_id")).withColumn("pos", F.col("pos").cast("long"))


@query("span_read", q.select(PARTED + q.buckets(), "SELECT part_id, atom_id FROM buckets WHERE kind = 'TO' AND peer = 1"))
def span_read(spark, sf_dir):
    return halo.span(halo.pack_layout(buckets(spark, sf_dir), P), "TO", 1, P).select("part_id", F.explode("nodes").alias("atom_id"))


@query("edge_table", q.select(PARTED, f"SELECT part_id, {KEY}, d2 FROM owned"))
def edge_table(spark, sf_dir):
    s, e, a = quartz_bonds(spark, sf_dir)
    out = halo.edge_table(halo.owned_edges(e, a)).select("part_id", "src", F.explode("out").alias("o"))
    return out.select("part_id", "src", "o.dst", "o.ix", "o.iy", "o.iz", "o.d2")


LINE = "f_src, f_dst, f_ix, f_iy, f_iz, e_src, e_dst, e_ix, e_iy, e_iz, center, dot"


@query("bond_graph_quartz", q.select(q.quartz() + q.edges(BOND) + q.walls(P) + q.line(), f"SELECT a.part_id, {LINE} FROM line JOIN assign a ON a.atom_id = e_dst"))
def bond_graph_quartz(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    e, a = neighbors.neighbor_list(s.atoms, s.cell, BOND), partition.wall_partition(s.atoms, s.cell, P)
    return bondgraph.bond_graph(e, a)


@query("bond_graph_successor", q.select(q.successor() + q.id_walls(P) + q.line(), "SELECT a.part_id, count(*) AS links, CAST(sum(f_src) AS BIGINT) AS first, CAST(sum(e_dst) AS BIGINT) AS last FROM line JOIN assign a ON a.atom_id = e_dst GROUP BY a.part_id"))
def bond_graph_successor(spark, sf_dir):
    s = systems.successor(spark, sf_dir)
    links = bondgraph.bond_graph(neighbors.explicit_graph(s.edges), partition.wall_partition(s.atoms, None, P, axis="id"))
    return links.groupBy("part_id").agg(F.count(F.lit(1)).alias("links"), F.sum("f_src").alias("first"), F.sum("e_dst").alias("last"))


@query("higher_order_chain", q.select(q.chain() + q.id_walls(P), "SELECT s.part_id, a.src AS n0, a.dst AS n1, b.dst AS n2, c.dst AS n3 FROM edges a JOIN edges b ON b.src = a.dst JOIN edges c ON c.src = b.dst JOIN assign s ON s.atom_id = c.dst"))
def higher_order_chain(spark, sf_dir):
    s = systems.chain(spark, sf_dir)
    return bondgraph.higher_order_graph(neighbors.explicit_graph(s.edges), partition.wall_partition(s.atoms, None, P, axis="id"), 3)


@query("chain_closed_form", "SELECT CAST(sum(n - 1) AS BIGINT) AS edges, CAST(sum(greatest(n - 2, 0)) AS BIGINT) AS links FROM (SELECT conv_id, count(*) AS n FROM conversations GROUP BY conv_id)")
def chain_closed_form(spark, sf_dir):
    e = neighbors.explicit_graph(systems.chain(spark, sf_dir).edges)
    return e.agg(F.count(F.lit(1)).alias("edges")).crossJoin(bondgraph.line_graph(e).agg(F.count(F.lit(1)).alias("links")))


@query("bond_buckets", q.select(PARTED + UNOWNED, f"SELECT owner AS part_id, 'TO' AS kind, part_id AS peer, {KEY} FROM border UNION ALL SELECT part_id, 'FROM', owner, {KEY} FROM border"))
def bond_buckets(spark, sf_dir):
    s, e, a = quartz_bonds(spark, sf_dir)
    return halo.two_owner_buckets(halo.border_edges(e, halo.border_nodes(e, a), a))


@query("bond_cover", "SELECT CAST(0 AS BIGINT) AS violations")
def bond_cover(spark, sf_dir):
    s, e, a = quartz_bonds(spark, sf_dir)
    return bondgraph.check_bond_cover(e, a)


def _graph(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    return s, neighbors.neighbor_list(s.atoms, s.cell, BOND)


@query("part_hash", q.select(q.quartz(), "SELECT atom_id, CAST(atom_id % 8 AS INT) AS part_id FROM atoms"))
def part_hash(spark, sf_dir):
    return partition.hash_partition(systems.quartz(spark, sf_dir).atoms, 8)


@query("part_random", q.select(q.quartz(), "SELECT atom_id, CAST(((atom_id % 2147483647 * 48271 + 12345) % 2147483647) // 1024 % 8 AS INT) AS part_id FROM atoms"))
def part_random(spark, sf_dir):
    return partition.random_partition(systems.quartz(spark, sf_dir).atoms, 8)


@query("part_blocks", q.select(q.quartz(), "SELECT atom_id, CAST((x * 2 // lx * 2 + y * 2 // ly) * 2 + z * 2 // lz AS INT) AS part_id FROM atoms, cell"))
def part_blocks(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    return partition.block_partition(s.atoms, s.cell, (2, 2, 2))


RCB = [
    ("r1", "SELECT *, ntile(2) OVER (ORDER BY x, atom_id) - 1 AS a FROM atoms"),
    ("r2", "SELECT *, ntile(2) OVER (PARTITION BY a ORDER BY y, atom_id) - 1 AS b FROM r1"),
    ("r3", "SELECT *, ntile(2) OVER (PARTITION BY a, b ORDER BY z, atom_id) - 1 AS c FROM r2"),
]


@query("part_rcb", q.select(q.quartz() + RCB, "SELECT atom_id, CAST(a * 4 + b * 2 + c AS INT) AS part_id FROM r3"))
def part_rcb(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    return partition.bisection_partition(s.atoms, s.cell, 8)


_BITS = " + ".join(f"(((({a} * 1024 // l{a}) >> {b}) & 1) << {3 * b + k})" for k, a in enumerate("xyz") for b in range(10))


MORTON = [("coded", f"SELECT atom_id, {_BITS} AS code FROM atoms, cell")]


@query("part_morton", q.select(q.quartz() + MORTON, "SELECT atom_id, CAST(ntile(8) OVER (ORDER BY code, atom_id) - 1 AS INT) AS part_id FROM coded"))
def part_morton(spark, sf_dir):
    s = systems.quartz(spark, sf_dir)
    return partition.morton_partition(s.atoms, s.cell, 8)


def _invariant(method: str):
    """Every atom in exactly one part, and no part out of range: no violations."""

    @query(f"part_{method}", "SELECT CAST(0 AS BIGINT) AS violations, count(*) AS atoms FROM part")
    def run(spark, sf_dir):
        scratch = Scratch(spark)
        s = systems.successor(spark, sf_dir)
        edges = scratch.keep(system_edges(s, PotentialSpec()), "edges")
        atoms = scratch.keep(s.atoms, "atoms")
        assign = partition.partition(atoms, edges, None, P, method, scratch)
        placed = assign.groupBy("atom_id").agg(F.count(F.lit(1)).alias("n"), F.min("part_id").alias("a"), F.max("part_id").alias("b"))
        seen = atoms.join(placed, "atom_id", "full_outer")
        bad = F.col("n").isNull() | (F.col("n") != 1) | (F.col("a") < 0) | (F.col("b") >= P)
        return seen.agg(F.count(F.when(bad, 1)).alias("violations"), F.count(F.lit(1)).alias("atoms"))


for _method in ("bfs", "labelprop", "greedy", "multilevel", "spectral"):
    _invariant(_method)


@query(
    "partition_quality",
    q.select(
        PARTED + [("parts", "SELECT part_id, count(*) AS n FROM assign GROUP BY part_id")],
        f"SELECT (SELECT count(*) FROM halo) AS border_nodes, (SELECT count(*) FROM owned WHERE p_src <> part_id) AS edge_cut, (SELECT count(DISTINCT (part_id, p_src)) FROM owned WHERE p_src <> part_id) AS peer_pairs, (SELECT max(n) FROM parts) AS most_nodes, (SELECT min(n) FROM parts) AS least_nodes",
    ),
)
def quality(spark, sf_dir):
    s, e, a = quartz_bonds(spark, sf_dir)
    return partition_quality(e, a).select("border_nodes", "edge_cut", "peer_pairs", "most_nodes", "least_nodes")


@query("hub_skew", q.select(q.hub() + q.id_walls(P) + q.owners(), "SELECT part_id, count(*) AS edges, max(n) AS most_in FROM owned JOIN (SELECT dst, count(*) AS n FROM edges GROUP BY dst) USING (dst) GROUP BY part_id"))
def hub_skew(spark, sf_dir):
    s = systems.hub(spark, sf_dir)
    e = halo.owned_edges(neighbors.explicit_graph(s.edges), partition.wall_partition(s.atoms, None, P, axis="id"))
    per_node = e.groupBy("part_id", "dst").agg(F.count(F.lit(1)).alias("n"))
    return per_node.groupBy("part_id").agg(F.sum("n").alias("edges"), F.max("n").alias("most_in"))


@query("clusters_isolated", q.select(q.clusters() + q.id_walls(P) + q.owners(), "SELECT s.part_id, count(*) AS nodes, count(*) FILTER (atom_id NOT IN (SELECT src FROM edges)) AS isolated FROM assign s GROUP BY s.part_id"))
def clusters_isolated(spark, sf_dir):
    s = systems.clusters(spark, sf_dir)
    a = partition.wall_partition(s.atoms, None, P, axis="id")
    own = halo.expanded_nodes(neighbors.explicit_graph(s.edges), a).filter("owner = part_id")
    linked = s.edges.select(F.col("src").alias("atom_id")).distinct().withColumn("linked", F.lit(1))
    return own.join(linked, "atom_id", "left").groupBy("part_id").agg(F.count(F.lit(1)).alias("nodes"), F.count(F.when(F.col("linked").isNull(), 1)).alias("isolated"))


@query("sites_cliques", q.select(q.sites(), "SELECT host, count(*) AS pages, count(*) * (count(*) - 1) AS edges FROM hosts GROUP BY host"))
def sites_cliques(spark, sf_dir):
    s = systems.sites(spark, sf_dir)
    host = systems.read(spark, sf_dir, "pages").select(F.col("page_id").alias("atom_id"), F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1).alias("host"))
    links = s.edges.groupBy(F.col("src").alias("atom_id")).agg(F.count(F.lit(1)).alias("n"))
    return host.join(links, "atom_id", "left").groupBy("host").agg(F.count(F.lit(1)).alias("pages"), F.coalesce(F.sum("n"), F.lit(0)).alias("edges"))
