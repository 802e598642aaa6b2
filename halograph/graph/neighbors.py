"""Neighbour lists: directed edges between atoms, or their periodic images, closer than a cutoff."""

from __future__ import annotations

from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from halograph.sources.systems import Cell

EDGE_KEY = ("src", "dst", "ix", "iy", "iz")
#: Atoms up to which every pair may be compared instead of building a grid.
SMALL = 20_000


def _squared(*d: Column) -> Column:
    return d[0] * d[0] + d[1] * d[1] + d[2] * d[2]


def _edges(pairs: DataFrame, cutoff: int, carry: tuple[str, ...] = ()) -> DataFrame:
    """From both ends and the image shift of src: displacement src - dst, its square, and only pairs within the cutoff."""
    shifted = pairs.withColumns({f"d{a}": F.col(f"s{a}") - F.col(f"t{a}") for a in "xyz"})
    found = shifted.withColumn("d2", _squared(F.col("dx"), F.col("dy"), F.col("dz")))
    apart = (F.col("src") != F.col("dst")) | (F.col("ix") != 0) | (F.col("iy") != 0) | (F.col("iz") != 0)
    return found.filter((F.col("d2") <= cutoff * cutoff) & apart).select(*EDGE_KEY, "dx", "dy", "dz", "d2", *[f"{e}_{c}" for c in carry for e in ("src", "dst")])


def _both_ways(half: DataFrame, carry: tuple[str, ...]) -> DataFrame:
    """Each pair as two directed edges: the second from dst to src, with image and displacement turned round."""
    swap = {"src": "dst", "dst": "src"} | {f"{e}_{c}": f"{o}_{c}" for c in carry for e, o in (("src", "dst"), ("dst", "src"))}
    turned = {c: -F.col(c) for c in ("ix", "iy", "iz", "dx", "dy", "dz")}
    there = F.struct(*[F.col(c).alias(c) for c in half.columns])
    back = F.struct(*[turned.get(c, F.col(swap.get(c, c))).alias(c) for c in half.columns])
    return half.select(F.explode(F.array(there, back)).alias("e")).select("e.*")


def _grid(cell: Cell, cutoff: int) -> list[tuple[int, int]]:
    """(bins, reach) of each periodic axis; the reach passes the cutoff also where the box is narrower than it."""
    out = []
    for length, periodic in zip(cell.lengths, cell.periodic):
        bins = max(1, length // cutoff) if periodic else 0
        out.append((bins, -(-cutoff // (length // bins)) if periodic else 1))
    return out


def _bin(axis: str, k: int, cell: Cell, cutoff: int, bins: int) -> Column:
    x = F.floor(F.col(axis)).cast("long") - cell.origin[k]  # positions may be doubles
    if bins:
        return F.least(F.call_function("div", x * bins, F.lit(cell.lengths[k])), F.lit(bins - 1)).cast("long")
    return F.floor(x / cutoff).cast("long")


def neighbor_list(atoms: DataFrame, cell: Cell, cutoff: int, *, method: str = "cellgrid", skin: int = 0, carry: tuple[str, ...] = ()) -> DataFrame:
    """edges(src, dst, ix, iy, iz, dx, dy, dz, d2) with d = r_src + image - r_dst and d2 <= (cutoff + skin)^2.

    ``cellgrid`` meets atoms by the bin of the destination and half of its neighbours: an equi-join that finds each pair
    once, and then turns it round. Both sides hold every atom, so they are merged: files of few bytes may have more rows
    than a driver can broadcast. ``broadcast`` compares all pairs and is refused beyond SMALL atoms. An axis shorter than
    the cutoff gives several images of one atom. Columns of atoms named in ``carry`` come along as src_<name> and
    dst_<name>, so that edges need not look them up.
    """
    reach = cutoff + skin
    ends = lambda e: [F.col(c).alias(f"{e}_{c}") for c in carry]
    if method == "broadcast":
        if atoms.limit(SMALL + 1).count() > SMALL:
            raise ValueError(f"all pairs are compared for at most {SMALL} atoms; use method='cellgrid'")
        images = [range(-(-(-reach // n)), -(-reach // n) + 1) if p else (0,) for n, p in zip(cell.lengths, cell.periodic)]
        shift = F.explode(_structs([(i, i[0] * cell.lengths[0], i[1] * cell.lengths[1], i[2] * cell.lengths[2]) for i in product(*images)]))
        src = atoms.select(F.col("atom_id").alias("src"), *[F.col(a).alias(f"p{a}") for a in "xyz"], shift.alias("im"), *ends("src"))
        src = src.select("src", "im.ix", "im.iy", "im.iz", *[(F.col(f"p{a}") + F.col(f"im.s{a}")).alias(f"s{a}") for a in "xyz"], *[f"src_{c}" for c in carry])
        dst = atoms.select(F.col("atom_id").alias("dst"), *[F.col(a).alias(f"t{a}") for a in "xyz"], *ends("dst"))
        return _edges(src.crossJoin(F.broadcast(dst)), reach, carry)
    grid = _grid(cell, reach)
    bins = [_bin(a, k, cell, reach, grid[k][0]) for k, a in enumerate("xyz")]
    src = atoms.select(F.col("atom_id").alias("src"), *[F.col(a).alias(f"p{a}") for a in "xyz"], *[b.alias(f"b{a}") for a, b in zip("xyz", bins)], *ends("src"))
    # Of two opposite offsets one is enough, and of a bin's own pairs those in rising order.
    around = F.explode(_offsets([o for o in product(*[range(-r, r + 1) for _, r in grid]) if o >= (0, 0, 0)]))
    dst = atoms.select(F.col("atom_id").alias("dst"), *[F.col(a).alias(f"t{a}") for a in "xyz"], *[b.alias(f"c{a}") for a, b in zip("xyz", bins)], around.alias("o"), *ends("dst"))
    columns = {}
    for k, a in enumerate("xyz"):
        to = F.col(f"c{a}") + F.col(f"o.o{a}")
        n = grid[k][0]
        columns[f"b{a}"] = F.pmod(to, F.lit(n)) if n else to
        columns[f"i{a}"] = F.floor(to / n).cast("int") if n else F.lit(0)
    own = (F.col("o.ox") == 0) & (F.col("o.oy") == 0) & (F.col("o.oz") == 0)
    dst = dst.select("dst", "tx", "ty", "tz", own.alias("own"), *[c.alias(n) for n, c in columns.items()], *[f"dst_{c}" for c in carry])
    pairs = dst.join(src.hint("merge"), ["bx", "by", "bz"]).filter(~F.col("own") | (F.col("src") < F.col("dst")))
    pairs = pairs.withColumns({f"s{a}": F.col(f"p{a}") + F.col(f"i{a}") * F.lit(cell.lengths[k]).cast("long") for k, a in enumerate("xyz")})
    return _both_ways(_edges(pairs, reach, carry), carry)


def _structs(images) -> Column:
    one = lambda i: F.struct(*[F.lit(v).cast("int").alias(n) for v, n in zip(i[0], ("ix", "iy", "iz"))], *[F.lit(v).cast("long").alias(n) for v, n in zip(i[1:], ("sx", "sy", "sz"))])
    return F.array(*[one(i) for i in images])


def _offsets(offsets) -> Column:
    return F.array(*[F.struct(*[F.lit(v).cast("long").alias(n) for v, n in zip(o, ("ox", "oy", "oz"))]) for o in offsets])


def bonds(edges: DataFrame, bond_cutoff: int) -> DataFrame:
    """The edges that are also bonds: those within the shorter, three-body cutoff."""
    return edges.filter(F.col("d2") <= bond_cutoff * bond_cutoff)


def explicit_graph(edges: DataFrame) -> DataFrame:
    """Edges (src, dst, w) of a graph without geometry, in the schema of a neighbour list."""
    zero, image = F.lit(0).cast("long"), F.lit(0).cast("int")
    return edges.select("src", "dst", *[image.alias(i) for i in ("ix", "iy", "iz")], *[zero.alias(d) for d in ("dx", "dy", "dz", "d2")], "w")


def estimated_degree(atoms: DataFrame, cell: Cell, cutoff: int, fraction: float = 0.1, seed: int = 7) -> DataFrame:
    """degree: mean number of neighbours, from a sample of destinations, before the whole list is built."""
    some = atoms.sample(fraction, seed=seed).select(F.col("atom_id").alias("dst"))
    return neighbor_list(atoms, cell, cutoff).join(some.hint("merge"), "dst", "left_semi").groupBy("dst").count().agg(F.avg("count").alias("degree"))
