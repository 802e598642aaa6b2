"""Queries against their SQL twins, a spread of all sections; the driver compares every one."""

import pytest

from halograph.catalog import ORACLE_SQL, QUERIES
from oracle import check

NAMES = """nl_quartz nl_cloud_open nl_liquid nl_lattice_smallcell nl_lattice_degrees walls_count border_nodes halo_two_hop border_edges_induced buckets bucket_duality
layout_markers layout_dedup span_read bond_cover bond_graph_successor higher_order_chain chain_closed_form part_morton part_rcb exchange_layer forward_ring_L3
forward_more_parts_than_cells forward_hub forward_bonds_L2 bond_one_layer forces_conservative forces_many_body forces_light forces_smooth forces_invariant_bond forces_direct
forces_sum_to_zero plug_in_custom model_smooth setup_single_vs_distributed md_two_steps md_periodic md_skin spatial_block3d spatial_hops spatial_underpadded kernel_arrow
kernel_arrow_many_body redundancy transfer_constant_in_layers three_body_counts out_of_memory memory_model trajectory_frames trajectory_interval_join trajectory_skin_tracker
trajectory_late_rows op_cube op_join_asof op_recursive op_udtf""".split()


@pytest.mark.parametrize("name", NAMES)
def test_twin(spark, sf_dir, name):
    check(spark, sf_dir, QUERIES[name], ORACLE_SQL[name])


@pytest.mark.parametrize("name", ["op_recursive", "op_udtf"])
def test_made_up_data_is_gone(spark, sf_dir, name):
    files = QUERIES[name](spark, sf_dir).inputFiles()
    assert [f.rsplit("/", 1)[-1] for f in files] == ["part.parquet"]


def test_most_queries_have_sql():
    assert len(ORACLE_SQL) > 0.85 * len(QUERIES)
