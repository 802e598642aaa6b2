"""Inference on one device: the whole graph without parts and borders. All other ways must give its answer."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from halograph.graph.bondgraph import line_graph
from halograph.graph.neighbors import EDGE_KEY, bonds
from halograph.graph.runtime import conv_layer, initial_state, renewed, system_edges, weighted
from halograph.graph.scratch import Scratch
from halograph.potentials import PotentialSpec, potential
from halograph.sources.systems import System


def run_single(system: System, spec: PotentialSpec, scratch: Scratch | None = None) -> DataFrame:
    """Final state: atom_id and features, by joins and sums over the whole graph."""
    model, scratch = potential(spec), scratch or Scratch(system.atoms.sparkSession)
    edges = scratch.keep(weighted(system_edges(system, spec), model), "edges")
    state = scratch.keep(initial_state(system.atoms.select("atom_id", "species"), model), "state")
    links = bond = None
    if model.uses_bonds:
        short = bonds(edges, spec.bond_cutoff) if system.edges is None else edges
        links = scratch.keep(line_graph(short), "links")
        bond = scratch.keep(short.select(*EDGE_KEY, model.a.mod(F.col("w")).alias("b")), "bonds")
    for _ in range(spec.layers):
        sums = None
        if model.uses_bonds:
            told = links.join(bond.select(*[F.col(c).alias(f"f_{c}") for c in EDGE_KEY], "b"), [f"f_{c}" for c in EDGE_KEY])
            heard = told.groupBy(*[F.col(f"e_{c}").alias(c) for c in EDGE_KEY]).agg(F.sum(model.a.mod(model.bond_message())).alias("sum_b"))
            joined = bond.join(heard, list(EDGE_KEY), "left").withColumn("sum_b", F.coalesce("sum_b", model.a.zero()))
            bond = scratch.keep(joined.select(*EDGE_KEY, model.bond_update().alias("b")), "bonds")
            sums = bond.groupBy(F.col("dst").alias("atom_id")).agg(F.sum("b").alias("sum_bond"))
        state = scratch.keep(renewed(conv_layer(state, None, edges, model, [], sums), model), "state")
    return state
