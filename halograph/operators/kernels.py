"""A fused kernel: each part runs a layer as one vectorised function over Arrow batches instead of a column plan."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from halograph.functions.ring import PRIME
from halograph.graph.lanes import within_lanes
from halograph.graph.runtime import PartitionedGraph, exchange, initial_state
from halograph.potentials import PotentialSpec, potential

#: Families that the kernel knows, with the correlation order it takes for them.
FUSED = {"ring": lambda spec: 1, "many_body": lambda spec: spec.nu}


def fused_forward(graph: PartitionedGraph, spec: PotentialSpec) -> DataFrame:
    """Final state (lane, part_id, atom_id, features) of a ring or many-body model; a part has to fit a task.

    Nodes and edges of a part lie in one lane already, so a layer moves border rows and no edges."""
    if spec.family not in FUSED or spec.arithmetic != "ring":
        raise ValueError(f"the fused kernel knows {', '.join(FUSED)}; other models run as column plans")
    model, lanes = potential(spec), graph.lanes
    names, prime, order = model.channels, PRIME, FUSED[spec.family](spec)
    state = initial_state(graph.nodes, model)
    edges = graph.edges.select("lane", "src", "dst", "w")

    def layer(nodes: pa.Table, links: pa.Table) -> pa.Table:
        part = nodes.column("part_id").combine_chunks()
        own = part.is_valid().to_numpy(zero_copy_only=False)
        ids = nodes.column("atom_id").to_numpy()
        by_id = np.argsort(ids)
        at = lambda c: by_id[np.searchsorted(ids, links.column(c).to_numpy(), sorter=by_id)]
        src, dst, w = (at("src"), at("dst"), links.column("w").to_numpy()) if links.num_rows else (np.zeros(0, np.int64),) * 3
        mask = pa.array(own)
        out = [nodes.column(c).filter(mask) for c in ("lane", "part_id", "atom_id")]
        for h in names:
            v = nodes.column(h).to_numpy()
            a = np.zeros(len(v), np.int64)
            np.add.at(a, dst, w * v[src])
            a %= prime
            power, total = a, v + a
            for _ in range(order - 1):
                power = power * a % prime
                total = total + power
            out.append(pa.array((total % prime)[own], pa.int64()))
        return pa.table(out, names=["lane", "part_id", "atom_id", *names])

    schema = "lane int, part_id int, atom_id long, " + ", ".join(f"{h} long" for h in names)
    for _ in range(spec.layers):
        received = exchange(state, graph.outbox, lanes).withColumn("part_id", F.lit(None).cast("int"))
        nodes = lanes.dealt(state.unionByName(received.select(state.columns)))
        with within_lanes(graph.nodes.sparkSession):
            state = lanes.keep(nodes.groupBy("lane").cogroup(edges.groupBy("lane")).applyInArrow(layer, schema), "fused")
    return state
