"""Borders of a partition: which nodes and edges a part needs from others, and the buckets that carry them.

Tables of nodes and edges are merged, never broadcast: they grow with the system, whatever their files' bytes.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from halograph.graph.neighbors import EDGE_KEY


def with_owners(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """Edges with the part of each end: p_src and part_id (of the destination)."""
    src = assign.select(F.col("atom_id").alias("src"), F.col("part_id").alias("p_src"))
    dst = assign.select(F.col("atom_id").alias("dst"), "part_id")
    return edges.join(dst.hint("merge"), "dst").join(src.hint("merge"), "src")


def owned_edges(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """Every edge belongs to the part that owns its destination, and to no other."""
    return edges.join(assign.select(F.col("atom_id").alias("dst"), "part_id").hint("merge"), "dst")


def border_nodes(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """halo(part_id, atom_id, hop = 1, owner): nodes outside a part with an edge into it."""
    crossing = with_owners(edges, assign).filter("p_src <> part_id")
    return crossing.select("part_id", F.col("src").alias("atom_id"), F.lit(1).alias("hop"), F.col("p_src").alias("owner")).distinct()


def expanded_nodes(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """part_id, atom_id, owner: owned nodes, with or without edges, and border nodes."""
    own = assign.select("part_id", "atom_id", F.col("part_id").alias("owner"))
    return own.union(border_nodes(edges, assign).select("part_id", "atom_id", "owner"))


def k_hop_halo(edges: DataFrame, assign: DataFrame, k: int) -> DataFrame:
    """halo to k hops: each node once, at the fewest hops over which it reaches the part."""
    known = assign.select("part_id", "atom_id")
    frontier, found = known, None
    for hop in range(1, k + 1):
        step = edges.select("src", "dst").join(frontier.withColumnRenamed("atom_id", "dst").hint("merge"), "dst").select("part_id", F.col("src").alias("atom_id")).distinct()
        frontier = step.join(known.hint("merge"), ["part_id", "atom_id"], "left_anti")
        ring = frontier.withColumn("hop", F.lit(hop))
        found = ring if found is None else found.union(ring)
        known = known.union(frontier)
    return found.join(assign.select("atom_id", F.col("part_id").alias("owner")).hint("merge"), "atom_id").select("part_id", "atom_id", "hop", "owner")


def border_edges(edges: DataFrame, halo: DataFrame, assign: DataFrame, rule: str = "unowned") -> DataFrame:
    """Edges into a part's border nodes. ``unowned``: all of them, for their destination is another part's.

    ``induced`` leaves those whose source the part also has (owned or border), the literal set difference.
    """
    near = halo.filter("hop = 1").select("part_id", F.col("atom_id").alias("dst"), "owner")
    found = edges.join(near.hint("merge"), "dst").select("part_id", "owner", *[c for c in edges.columns])
    if rule == "unowned":
        return found
    inside = assign.select("part_id", F.col("atom_id").alias("src")).union(halo.filter("hop = 1").select("part_id", F.col("atom_id").alias("src")))
    return found.join(inside.hint("merge"), ["part_id", "src"], "left_anti").select(found.columns)


def assign_buckets(assign: DataFrame, halo: DataFrame) -> DataFrame:
    """buckets(part_id, kind, peer, atom_id): PURE nodes stay, TO nodes go to a peer, FROM nodes come from one.

    TO and FROM are the same halo rows read from either side, so they agree by construction.
    """
    near = halo.filter("hop = 1")
    to = near.select(F.col("owner").alias("part_id"), F.lit("TO").alias("kind"), F.col("part_id").alias("peer"), "atom_id")
    come = near.select("part_id", F.lit("FROM").alias("kind"), F.col("owner").alias("peer"), "atom_id")
    pure = assign.join(near.select("atom_id").distinct().hint("merge"), "atom_id", "left_anti").select("part_id", F.lit("PURE").alias("kind"), F.col("part_id").alias("peer"), "atom_id")
    return pure.union(to).union(come)


def check_bucket_duality(buckets: DataFrame) -> DataFrame:
    """violations: nodes that one side sends and the other does not receive, or the reverse."""
    to = buckets.filter("kind = 'TO'").select(F.col("part_id").alias("i"), F.col("peer").alias("j"), "atom_id", F.lit(1).alias("sent"))
    come = buckets.filter("kind = 'FROM'").select(F.col("peer").alias("i"), F.col("part_id").alias("j"), "atom_id", F.lit(1).alias("received"))
    both = to.join(come, ["i", "j", "atom_id"], "full_outer")
    return both.filter("sent IS NULL OR received IS NULL").agg(F.count(F.lit(1)).alias("violations"))


def _spans(buckets: DataFrame, p: int) -> DataFrame:
    """part_id, slot, length of each span: PURE, then TO of each peer, then FROM of each peer, empty spans too."""
    spark = buckets.sparkSession
    parts = spark.range(p).select(F.col("id").cast("int").alias("part_id"))
    slots = spark.range(2 * p + 1).select(F.col("id").cast("int").alias("slot"))
    kind = F.when(F.col("kind") == "PURE", 0).when(F.col("kind") == "TO", F.col("peer") + 1).otherwise(F.col("peer") + p + 1)
    lengths = buckets.groupBy("part_id", kind.cast("int").alias("slot")).agg(F.count(F.lit(1)).alias("length"))
    # p * (2p + 1) rows, of the driver's own making
    return parts.crossJoin(F.broadcast(slots)).join(lengths, ["part_id", "slot"], "left").select("part_id", "slot", F.coalesce("length", F.lit(0)).alias("length"))


def markers(buckets: DataFrame, p: int) -> DataFrame:
    """part_id, k, marker: where span k begins in the node array; the last marker is the array's length."""
    running = F.sum("length").over(Window.partitionBy("part_id").orderBy("slot"))
    ends = _spans(buckets, p).select("part_id", (F.col("slot") + 1).alias("k"), running.alias("marker"))
    parts = ends.select("part_id").distinct().select("part_id", F.lit(0).alias("k"), F.lit(0).cast("long").alias("marker"))
    return parts.union(ends)


def pack_layout(buckets: DataFrame, p: int, layout: str = "spans") -> DataFrame:
    """layout(part_id, nodes, markers): one row a part, for inspection; execution uses the long form.

    ``spans`` repeats a node for each peer that needs it; ``dedup`` has each node once, and index has the spans' places.
    """
    kind = F.when(F.col("kind") == "PURE", 0).when(F.col("kind") == "TO", F.col("peer") + 1).otherwise(F.col("peer") + p + 1)
    packed = buckets.groupBy("part_id").agg(F.array_sort(F.collect_list(F.struct(kind.alias("slot"), "atom_id"))).alias("rows"))
    spans = markers(buckets, p).groupBy("part_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "marker"))), lambda m: m["marker"]).alias("markers"))
    full = spans.join(packed.hint("merge"), "part_id", "left").select("part_id", F.coalesce(F.transform("rows", lambda r: r["atom_id"]), F.array().cast("array<bigint>")).alias("nodes"), "markers")
    if layout == "spans":
        return full
    return _deduplicated(buckets.select("part_id", kind.alias("slot"), "atom_id"), full.select("part_id", "markers"))


def _deduplicated(rows: DataFrame, spans: DataFrame) -> DataFrame:
    """part_id, nodes (each once, by first place), index (the place in nodes of every slot), markers. Places are counted in
    the long form, so the cost does not grow with the square of a part."""
    slots = Window.partitionBy("part_id").orderBy("slot", "atom_id")
    placed = rows.withColumn("r", F.row_number().over(slots))
    first = placed.withColumn("first", F.min("r").over(Window.partitionBy("part_id", "atom_id")))
    at = first.withColumn("at", F.dense_rank().over(Window.partitionBy("part_id").orderBy("first")) - 1)
    packed = at.groupBy("part_id").agg(
        F.transform(F.array_sort(F.collect_set(F.struct("at", "atom_id"))), lambda x: x["atom_id"]).alias("nodes"),
        F.transform(F.array_sort(F.collect_list(F.struct("r", "at"))), lambda x: x["at"].cast("long")).alias("index"),
    )
    none = F.array().cast("array<bigint>")
    return spans.join(packed.hint("merge"), "part_id", "left").select("part_id", F.coalesce("nodes", none).alias("nodes"), F.coalesce("index", none).alias("index"), "markers")


def span(layout: DataFrame, kind: str, peer: int, p: int) -> DataFrame:
    """part_id, nodes of one bucket, cut out of the node array by its markers."""
    k = {"PURE": 0, "TO": peer + 1, "FROM": peer + p + 1}[kind]
    return layout.select("part_id", F.slice("nodes", F.col("markers")[k] + 1, F.col("markers")[k + 1] - F.col("markers")[k]).alias("nodes"))


def edge_table(part_edges: DataFrame) -> DataFrame:
    """edge_table(part_id, src, out): the edges that start at each node."""
    return part_edges.groupBy("part_id", "src").agg(F.sort_array(F.collect_list(F.struct("dst", "ix", "iy", "iz", "d2"))).alias("out"))


def two_owner_buckets(border: DataFrame) -> DataFrame:
    """Buckets of border bonds: the owner of a bond sends it to each part that has its destination as a border node."""
    key = [F.col(c) for c in EDGE_KEY]
    to = border.select(F.col("owner").alias("part_id"), F.lit("TO").alias("kind"), F.col("part_id").alias("peer"), *key)
    return to.union(border.select("part_id", F.lit("FROM").alias("kind"), F.col("owner").alias("peer"), *key))
