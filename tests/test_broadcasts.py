"""Joins of queries whose tables grow with the system: what they broadcast is looked up by part, never by node or edge."""

import re

import pytest
from pyspark.sql.readwriter import DataFrameWriter

from halograph.catalog import QUERIES
from halograph.plans import plan_text

NAMES = """nl_quartz nl_quartz_degree bonds_two_cutoffs op_lateral_topk op_sample_degree op_udf nl_lattice_degrees border_nodes border_edges_unowned border_edges_induced buckets
bucket_duality bond_buckets bond_cover bond_graph_quartz halo_two_hop layout_dedup layout_markers op_cube op_pivot op_roundtrip partition_quality partitioner_comparison
partitioner_graph_methods""".split()
#: Keys of tables with a row for each part, span or range of rows.
OF_PARTS = {"part_id", "slot", "to", "_p"}


@pytest.mark.parametrize("name", NAMES)
def test_nodes_and_edges_are_not_broadcast(spark, sf_dir, monkeypatch, name):
    plans, write = [], DataFrameWriter.parquet

    def parquet(self, *args, **kwargs):
        plans.append(plan_text(self._df))
        return write(self, *args, **kwargs)

    monkeypatch.setattr(DataFrameWriter, "parquet", parquet)
    plans.append(plan_text(QUERIES[name](spark, sf_dir)))
    keys = {k for p in plans for found in re.findall(r"BroadcastHashJoin \[([^\]]*)\]", p) for k in re.findall(r"(\w+)#", found)}
    assert keys <= OF_PARTS


def test_growth_writes_every_node_once(spark, monkeypatch):
    """A round of breadth-first growth writes the nodes it found, not all that are known; parts are those of a plain search."""
    from halograph.graph.partition import growth_partition
    from halograph.graph.scratch import Scratch

    near = {i: set() for i in range(31)}  # a path of 20 nodes, a ring of 7 from its node 12 on, a pair apart, two nodes alone
    for a, b in [*((i, i + 1) for i in range(19)), (12, 20), *((i, i + 1) for i in range(20, 26)), (26, 12), (27, 28)]:
        near[a].add(b), near[b].add(a)
    want = {i: j for j, i in reversed(list(enumerate((0, 15))))}
    ring = dict(want)
    while ring:
        found = {}
        for a, j in ring.items():
            for b in near[a] - want.keys():
                found[b] = min(j, found.get(b, j))
        want |= (ring := found)

    written, write = {}, DataFrameWriter.parquet

    def parquet(self, path, *args, **kwargs):
        write(self, path, *args, **kwargs)
        written[path] = self._df.columns, self._spark.read.parquet(path).count()

    monkeypatch.setattr(DataFrameWriter, "parquet", parquet)
    atoms = spark.createDataFrame([(i,) for i in near], "atom_id long")
    edges = spark.createDataFrame([(a, b) for a in near for b in near[a] if a < b], "src long, dst long")
    got = {r.atom_id: r.part_id for r in growth_partition(atoms, edges, 2, Scratch(spark)).collect()}
    assert got == {i: want.get(i, i % 2) for i in near}
    assert sum(n for columns, n in written.values() if columns == ["atom_id", "part_id"]) == len(want)
