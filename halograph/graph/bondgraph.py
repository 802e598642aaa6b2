"""Bond graphs: bonds are nodes, and two bonds are linked where the first ends at the atom where the second begins."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from halograph.graph.halo import border_edges, border_nodes, owned_edges
from halograph.graph.lanes import Lanes, within_lanes
from halograph.graph.neighbors import EDGE_KEY


def _side(bonds: DataFrame, prefix: str, *extra: str) -> DataFrame:
    keep = [c for c in (*EDGE_KEY, "dx", "dy", "dz") if c in bonds.columns]
    return bonds.select(*extra, *[F.col(c).alias(f"{prefix}_{c}") for c in keep])


def _backtracks() -> Column:
    """The second bond is the first one walked back."""
    back = F.col("f_src") == F.col("e_dst")
    for i in ("ix", "iy", "iz"):
        back = back & (F.col(f"f_{i}") == -F.col(f"e_{i}"))
    return back


def _linked(first: DataFrame, second: DataFrame, on: list[str], backtrack: bool) -> DataFrame:
    pairs = first.withColumn("center", F.col("f_dst")).join(second.withColumn("center", F.col("e_src")).hint("merge"), [*on, "center"])
    if not backtrack:
        pairs = pairs.filter(~_backtracks())
    dot = F.col("f_dx") * F.col("e_dx") + F.col("f_dy") * F.col("e_dy") + F.col("f_dz") * F.col("e_dz")
    keys = [F.col(f"{s}_{c}") for s in "fe" for c in EDGE_KEY]
    return pairs.select(*on, *keys, "center", dot.alias("dot"))


def line_graph(bonds: DataFrame, *, backtrack: bool = False) -> DataFrame:
    """The bond graph of the whole system, without partitions."""
    return _linked(_side(bonds, "f"), _side(bonds, "e"), [], backtrack)


def bond_graph(bonds: DataFrame, assign: DataFrame, *, backtrack: bool = False) -> DataFrame:
    """bond_edges(part_id, f key, e key, center, dot): each part links its owned bonds to all bonds before them.

    The bonds before are owned or border bonds, whose sources are two hops away at most. A link belongs to the part that
    owns its second bond, so every link of the system is made once.
    """
    own = owned_edges(bonds, assign)
    border = border_edges(bonds, border_nodes(bonds, assign), assign)
    columns = ["part_id", *bonds.columns]
    before = own.select(columns).union(border.select(columns))
    return _linked(_side(before, "f", "part_id"), _side(own, "e", "part_id"), ["part_id"], backtrack)


def higher_order_graph(bonds: DataFrame, assign: DataFrame | None = None, order: int = 3) -> DataFrame:
    """Walks of ``order`` bonds as nodes n0 ... n_order, each owned by the part of its last node; no step straight back."""
    walks = bonds.select(F.col("src").alias("n0"), F.col("dst").alias("n1"), *[F.col(i).alias(f"l{i}") for i in ("ix", "iy", "iz")])
    for k in range(1, order):
        nxt = bonds.select(F.col("src").alias(f"n{k}"), F.col("dst").alias(f"n{k + 1}"), "ix", "iy", "iz")
        back = F.col(f"n{k + 1}") == F.col(f"n{k - 1}")
        for i in ("ix", "iy", "iz"):
            back = back & (F.col(i) == -F.col(f"l{i}"))
        walks = walks.join(nxt.hint("merge"), f"n{k}").filter(~back).select(*[f"n{j}" for j in range(k + 2)], *[F.col(i).alias(f"l{i}") for i in ("ix", "iy", "iz")])
    nodes = [f"n{j}" for j in range(order + 1)]
    if assign is None:
        return walks.select(nodes)
    return walks.join(assign.select(F.col("atom_id").alias(f"n{order}"), "part_id").hint("merge"), f"n{order}").select("part_id", *nodes)


def check_bond_cover(bonds: DataFrame, assign: DataFrame) -> DataFrame:
    """violations: links of the whole bond graph that no part makes, or that are made more than once or wrongly."""
    keys = [f"{s}_{c}" for s in "fe" for c in EDGE_KEY]
    parts, whole = bond_graph(bonds, assign).select(keys), line_graph(bonds).select(keys)
    signed = parts.withColumn("n", F.lit(1)).union(whole.withColumn("n", F.lit(-1)))
    return signed.groupBy(keys).agg(F.sum("n").alias("n")).filter("n <> 0").agg(F.count(F.lit(1)).alias("violations"))


@dataclass
class BondTables:
    """The bond graph of all parts in their lanes; a bond has one number, bid, wherever it is."""

    owned: DataFrame  # lane, bid, part_id, p_src, edge columns, w
    before: DataFrame  # lane, bid, part_id, p_src, edge columns: owned bonds and, in the lanes that need them, border bonds
    outbox: DataFrame  # lane, to_lane, bid
    links: DataFrame  # lane, f_bid, e_bid, dot

    def refreshed(self, owned: DataFrame, before: DataFrame, lanes: Lanes) -> "BondTables":
        """The same bonds with new displacements; links whose bonds are no longer there rest."""
        end = lambda df, s: df.select("lane", F.col("bid").alias(f"{s}_bid"), *[F.col(f"d{a}").alias(f"{s}{a}") for a in "xyz"]).hint("shuffle_hash")
        joined = self.links.drop("dot").join(end(before, "f"), ["lane", "f_bid"]).join(end(owned, "e"), ["lane", "e_bid"])
        links = joined.select("lane", "f_bid", "e_bid", sum((F.col(f"f{a}") * F.col(f"e{a}") for a in "yz"), F.col("fx") * F.col("ex")).alias("dot"))
        return BondTables(owned, before, self.outbox, lanes.keep(links, "links"))


def build_bonds(short: DataFrame, lanes: Lanes) -> BondTables:
    """Bond tables from owned bonds in their lanes. Bonds are numbered once; border bonds go to the lanes whose links
    begin with them, and links are made and kept inside lanes."""
    owned = lanes.keep(short.withColumn("bid", F.monotonically_increasing_id()), "bonds")
    # Whoever owns a bond that starts here needs the bonds that end here: the border nodes of the bonds alone.
    with within_lanes(short.sparkSession):
        wanted = owned.filter("p_src <> part_id").select("lane", F.col("part_id").alias("to"), F.col("src").alias("dst"), F.col("p_src").alias("owner")).distinct()
        wanted = lanes.keep(lanes.dealt(wanted.select(lanes.lane(F.col("owner")).alias("lane"), F.col("lane").alias("to_lane"), "to", "dst")), "wanted")
    sent = lanes.keep(owned.join(wanted.hint("shuffle_hash"), ["lane", "dst"]).drop("part_id"), "sent")
    border = sent.select(F.col("to_lane").alias("lane"), "bid", F.col("to").alias("part_id"), *[c for c in owned.columns if c not in ("lane", "bid", "part_id")])
    before = lanes.keep(lanes.dealt(owned.unionByName(border)), "before")
    first = before.select("lane", F.col("bid").alias("f_bid"), F.col("dst").alias("center"), F.col("src").alias("f_src"), *[F.col(c).alias(f"f_{c}") for c in ("ix", "iy", "iz", "dx", "dy", "dz")])
    second = owned.select("lane", F.col("bid").alias("e_bid"), F.col("src").alias("center"), F.col("dst").alias("e_dst"), *[F.col(c).alias(f"e_{c}") for c in ("ix", "iy", "iz", "dx", "dy", "dz")])
    pairs = first.join(second.hint("shuffle_hash"), ["lane", "center"]).filter(~_backtracks())
    dot = sum((F.col(f"f_d{a}") * F.col(f"e_d{a}") for a in "yz"), F.col("f_dx") * F.col("e_dx"))
    links = lanes.keep(pairs.select("lane", "f_bid", "e_bid", dot.alias("dot")), "links")
    return BondTables(owned, before, sent.select("lane", "to_lane", "bid"), links)
