"""Particle systems and graphs built from the given tables. Lengths are whole thousandths of an angstrom."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from halograph.functions.ring import whole
from halograph.sources.tables import read

#: The 18 sites (site, atomic number, x, y, z) of an orthorhombic alpha-quartz cell, from public lattice data.
QUARTZ_SITES = (
    (0, 8, 296, 1759, 1158), (1, 8, 296, 6750, 644), (2, 8, 785, 3631, 4761), (3, 8, 785, 4879, 2445), (4, 8, 1376, 1136, 4247), (5, 8, 1376, 7374, 2960),
    (6, 8, 2752, 2495, 644), (7, 8, 2752, 6014, 1158), (8, 8, 3242, 624, 2445), (9, 8, 3242, 7886, 4761), (10, 8, 3832, 3119, 2960), (11, 8, 3832, 5390, 4247),
    (12, 14, 1303, 2256, 0), (13, 14, 1303, 6253, 1802), (14, 14, 2308, 0, 3603), (15, 14, 3759, 1998, 1802), (16, 14, 3759, 6511, 0), (17, 14, 4764, 4255, 3603),
)
QUARTZ_CELL = (4913, 8510, 5405)
LATTICE_SPACING = 2000
#: Sites of a supercell that is twice as many cells long as wide, for each width**3.
QUARTZ_LONG = 2 * 18


@dataclass(frozen=True)
class Cell:
    """An orthorhombic box; an axis that is not periodic needs an origin and a length only for walls."""

    lengths: tuple[int, int, int]
    periodic: tuple[bool, bool, bool] = (True, True, True)
    origin: tuple[int, int, int] = (0, 0, 0)

    @property
    def longest(self) -> int:
        return max(range(3), key=lambda k: (self.lengths[k], -k))


@dataclass(frozen=True)
class System:
    """atoms(atom_id, species, x, y, z) in a cell, or, without positions, a graph given by its edges."""

    name: str
    atoms: DataFrame
    cell: Cell | None = None
    edges: DataFrame | None = field(default=None)


def _root(n: int) -> int:
    """Whole cube root."""
    r = int(round(n ** (1 / 3)))
    while r**3 > n:
        r -= 1
    while (r + 1) ** 3 <= n:
        r += 1
    return r


def quartz_cells(n: int) -> tuple[int, int, int]:
    """Cells along x, y, z of a long supercell with a site for each of n keys; the last cells may be partly empty."""
    width = max(2, _root(n // QUARTZ_LONG))
    return max(2, -(-n // (18 * width * width))), width, width


def quartz(spark: SparkSession, sf_dir: str, copies: int = 1) -> System:
    """S1: order keys counted into the sites of a quartz supercell, every key a site. ``copies`` repeats it along x."""
    orders = read(spark, sf_dir, "orders").select("o_orderkey")
    most = orders.agg(F.max("o_orderkey")).first()[0]
    return quartz_of(orders.select(F.col("o_orderkey").alias("k")), (most if most is not None else -1) + 1, copies)


def quartz_of(keys: DataFrame, n: int, copies: int = 1) -> System:
    """The supercell of keys k below n."""
    return System("quartz", *_placed(keys, quartz_cells(n), copies))


def rod(keys: DataFrame, n: int, width: int) -> tuple[DataFrame, Cell]:
    """A supercell of keys k below n that is ``width`` cells wide, whatever its length."""
    return _placed(keys, (-(-n // (18 * width * width)), width, width))


def _placed(keys: DataFrame, cells: tuple[int, int, int], copies: int = 1) -> tuple[DataFrame, Cell]:
    nx, ny, nz = cells
    k = F.col("k")
    c, site = whole(k, 18), k % 18
    basis = F.array(*[F.struct(*[F.lit(v).cast("long").alias(n) for n, v in zip(("site", "species", "x", "y", "z"), s)]) for s in QUARTZ_SITES])
    placed = keys.select(k.alias("atom_id"), c.alias("c"), F.element_at(basis, (site + 1).cast("int")).alias("s"))
    across = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(copies - 1).cast("long"))) if copies > 1 else F.lit(0).cast("long")
    spread = placed.select("atom_id", "c", "s", across.alias("copy"))
    lx, ly, lz = QUARTZ_CELL
    atoms = spread.select(
        (F.col("atom_id") + F.col("copy") * (nx * ny * nz * 18)).alias("atom_id"), F.col("s.species").cast("int").alias("species"),
        (whole(F.col("c"), ny * nz) * lx + F.col("s.x") + F.col("copy") * (nx * lx)).alias("x"), ((whole(F.col("c"), nz) % ny) * ly + F.col("s.y")).alias("y"), ((F.col("c") % nz) * lz + F.col("s.z")).alias("z"),
    )
    return atoms, Cell((nx * lx * copies, ny * ly, nz * lz))


def cloud(spark: SparkSession, sf_dir: str) -> System:
    """S2: the first three components of each embedding as an open cloud of points."""
    e = read(spark, sf_dir, "embeddings")
    at = lambda i: F.floor(F.col("embedding")[i].cast("double") * 1000).cast("long")
    atoms = e.select(F.col("vec_id").alias("atom_id"), F.col("label").alias("species"), at(0).alias("x"), at(1).alias("y"), at(2).alias("z"))
    return System("cloud", atoms, Cell((2000, 2000, 2000), (False,) * 3, (-1000, -1000, -1000)))


def liquid(spark: SparkSession, sf_dir: str) -> System:
    """S3: order lines as a dense disordered box, open on all sides."""
    lines = read(spark, sf_dir, "lineitem")
    day = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date")).cast("long")
    n, first, last = lines.agg(F.count(F.lit(1)), F.min(day), F.max(day)).first()
    scale = max(1, n // 600)
    order = Window.partitionBy("l_orderkey").orderBy(*lines.columns)
    species = F.ascii("l_returnflag") * 2 + F.when(F.col("l_linestatus") == "O", 1).otherwise(0)
    atoms = lines.select(
        (F.col("l_orderkey") * 64 + F.row_number().over(order)).alias("atom_id"), species.cast("int").alias("species"),
        (day * scale).alias("x"), F.floor(F.col("l_quantity") * 400).alias("y"), F.floor(F.col("l_extendedprice") / 5).alias("z"),
    )
    first, last = first or 0, last or 0
    return System("liquid", atoms, Cell(((last - first + 1) * scale, 20_400, 21_000), (False,) * 3, (first * scale, 0, 0)))


def lattice(spark: SparkSession, sf_dir: str, width: int | None = None) -> System:
    """S10: part keys on a simple cubic lattice of two species that alternate; periodic, every part a site. The cross-section
    is ``width`` sites wide, or as wide as a cube's; the last layer along x may be partly empty."""
    parts = read(spark, sf_dir, "part").select("p_partkey")
    low, high = parts.agg(F.min("p_partkey"), F.max("p_partkey")).first()
    n = (high or 0) - (low or 0) + 1
    side = width or max(1, _root(n))
    k = F.col("p_partkey") - F.lit(low or 0)
    i, j, m = whole(k, side * side), whole(k, side) % side, k % side
    atoms = parts.select(k.alias("atom_id"), ((i + j + m) % 2).cast("int").alias("species"), *[(c * LATTICE_SPACING).alias(a) for c, a in zip((i, j, m), "xyz")])
    return System("lattice", atoms, Cell((-(-n // side**2) * LATTICE_SPACING, side * LATTICE_SPACING, side * LATTICE_SPACING)))


def successor(spark: SparkSession, sf_dir: str) -> System:
    """S5: parts of an order in rising key, an edge from each to the next; no geometry."""
    parts = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    step = F.lead("l_partkey").over(Window.partitionBy("l_orderkey").orderBy("l_partkey"))
    pairs = parts.select(F.col("l_partkey").alias("src"), step.alias("dst")).filter("dst IS NOT NULL")
    edges = pairs.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("w"))
    nodes = read(spark, sf_dir, "part").select(F.col("p_partkey").alias("atom_id"), F.col("p_size").cast("int").alias("species"))
    return System("successor", nodes, None, edges)


def chain(spark: SparkSession, sf_dir: str) -> System:
    """S6: turns of a conversation, each with an edge to the next turn."""
    c = read(spark, sf_dir, "conversations").select("conv_id", "turn", "role")
    me = F.col("conv_id") * 1024 + F.col("turn")
    nodes = c.select(me.alias("atom_id"), F.char_length("role").alias("species"))
    step = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    edges = c.select(me.alias("src"), (F.col("conv_id") * 1024 + step).alias("dst"), F.lit(1).cast("long").alias("w")).filter("dst IS NOT NULL")
    return System("chain", nodes, None, edges)


def hub(spark: SparkSession, sf_dir: str) -> System:
    """S7: customers and suppliers point at nations, nations at regions: a few nodes of very many edges in."""
    part = lambda base, key: F.col(key).cast("long") * 4 + base
    c, s = read(spark, sf_dir, "customer"), read(spark, sf_dir, "supplier")
    n, r = read(spark, sf_dir, "nation"), read(spark, sf_dir, "region")
    node = lambda df, base, key: df.select(part(base, key).alias("atom_id"), F.lit(base).alias("species"))
    nodes = node(r, 0, "r_regionkey").union(node(n, 1, "n_nationkey")).union(node(s, 2, "s_suppkey")).union(node(c, 3, "c_custkey"))
    edge = lambda df, b, k, to, key: df.select(part(b, k).alias("src"), part(to, key).alias("dst"), F.lit(1).cast("long").alias("w"))
    edges = edge(c, 3, "c_custkey", 1, "c_nationkey").union(edge(s, 2, "s_suppkey", 1, "s_nationkey")).union(edge(n, 1, "n_nationkey", 0, "n_regionkey"))
    return System("hub", nodes, None, edges)


def clusters(spark: SparkSession, sf_dir: str) -> System:
    """S8: documents of equal text are linked both ways; most nodes have no edge. Species: 0 unlabelled, else by label."""
    d = read(spark, sf_dir, "documents").select("doc_id", F.sha2("text", 256).alias("h"))
    labels = read(spark, sf_dir, "labels")
    nodes = d.select("doc_id").join(labels, "doc_id", "left").select(F.col("doc_id").alias("atom_id"), F.coalesce(1 + F.col("quality") + 2 * F.col("toxic"), F.lit(0)).cast("int").alias("species"))
    # A chain through each group, in both directions, joins it with linear cost however large it is.
    order = Window.partitionBy("h").orderBy("doc_id")
    step = d.select(F.col("doc_id").alias("src"), F.lead("doc_id").over(order).alias("dst")).filter("dst IS NOT NULL")
    edges = step.union(step.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).withColumn("w", F.lit(1).cast("long"))
    return System("clusters", nodes, None, edges)


def sites(spark: SparkSession, sf_dir: str) -> System:
    """S9: pages of one host, each pair linked both ways."""
    p = read(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1).alias("host"))
    nodes = p.select(F.col("page_id").alias("atom_id"), F.char_length("host").alias("species"))
    a, b = p.select(F.col("page_id").alias("src"), "host"), p.select(F.col("page_id").alias("dst"), "host")
    edges = a.join(b, "host").filter("src <> dst").select("src", "dst", F.lit(1).cast("long").alias("w"))
    return System("sites", nodes, None, edges)
