"""Partition rules: walls along the longest axis, and the other partitioners they are compared with.

Tables of nodes and edges are merged; only those with a row for each part are broadcast.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from halograph.functions.ring import whole
from halograph.graph.scratch import Scratch
from halograph.graph.shards import SHARD_NODES, Shards
from halograph.sources.systems import Cell


def _axis(cell: Cell | None, axis: str) -> str:
    return ("xyz"[cell.longest] if cell else "atom_id") if axis == "longest" else {"id": "atom_id"}.get(axis, axis)


def wall_partition(atoms: DataFrame, cell: Cell | None, p: int, *, axis: str = "longest", balance: str = "width") -> DataFrame:
    """assign(atom_id, part_id): slabs between parallel walls.

    ``width`` puts walls at equal distances; an atom on a wall belongs to the upper slab. ``count`` gives slabs of equal
    numbers (ties by atom_id) by rank in a global order; ``quantile`` does so nearly, by sketched walls, at any size.
    """
    a = _axis(cell, axis)
    x = F.floor(F.col(a)).cast("long")  # positions may be doubles
    if balance == "width":
        if a == "atom_id":
            low, high = atoms.agg(F.min(a), F.max(a)).first()
            low, length = low or 0, (high or 0) - (low or 0) + 1
        else:
            k = "xyz".index(a)
            low, length = cell.origin[k], cell.lengths[k]
        part = F.greatest(F.lit(0), F.least(F.lit(p - 1), whole((x - low) * p, length)))
        return atoms.select("atom_id", part.cast("int").alias("part_id"))
    if balance == "quantile":
        walls = atoms.agg(F.percentile_approx(a, [i / p for i in range(1, p)], 10_000)).first()[0] if p > 1 else []
        part = sum((F.when(x >= w, 1).otherwise(0) for w in walls or []), F.lit(0))
        return atoms.select("atom_id", part.cast("int").alias("part_id"))
    return equal_counts(atoms, [a], p)


def equal_counts(atoms: DataFrame, order: list[str], p: int) -> DataFrame:
    """assign by rank in a global order, in p nearly equal runs, without a single sorted partition.

    Rows are range-partitioned; ranks are local row numbers plus the count of all partitions before.
    """
    keys = [*order, "atom_id"] if "atom_id" not in order else order
    # Range bounds are sampled anew whenever a plan runs, so the numbered partitions are written once.
    ranged = atoms.select(*dict.fromkeys([*keys, "atom_id"])).repartitionByRange(*keys)
    dealt = Scratch(atoms.sparkSession).keep(ranged.withColumn("_p", F.spark_partition_id()), "ranged")
    sizes = sorted((r["_p"], r["count"]) for r in dealt.groupBy("_p").count().collect())  # one row for each partition
    before, total = {}, 0
    for part, n in sizes:
        before[part], total = total, total + n
    if not total:
        return atoms.select("atom_id", F.lit(0).alias("part_id"))
    start = F.create_map(*[F.lit(v).cast("long") for kv in before.items() for v in kv])
    rank = F.row_number().over(Window.partitionBy("_p").orderBy(*keys)) - 1 + start[F.col("_p").cast("long")]
    big, small = total % p, total // p  # the first parts have one more, as ntile does
    edge = big * (small + 1)
    part = F.when(rank < edge, whole(rank, small + 1)).otherwise(big + whole(rank - edge, max(1, small)))
    return dealt.select("atom_id", part.cast("int").alias("part_id"))


def hash_partition(atoms: DataFrame, p: int) -> DataFrame:
    return atoms.select("atom_id", F.pmod("atom_id", F.lit(p)).cast("int").alias("part_id"))


def random_partition(atoms: DataFrame, p: int, seed: int = 1) -> DataFrame:
    """A linear congruence of the identifier: random enough, the same everywhere."""
    mixed = F.pmod(F.pmod(F.col("atom_id"), F.lit(2_147_483_647)) * 48_271 + seed * 12_345, F.lit(2_147_483_647))
    return atoms.select("atom_id", F.pmod(whole(mixed, 1024), F.lit(p)).cast("int").alias("part_id"))


def block_partition(atoms: DataFrame, cell: Cell, blocks: tuple[int, int, int]) -> DataFrame:
    """3-D blocks of equal size."""
    at = [F.greatest(F.lit(0), F.least(F.lit(n - 1), whole((F.col(a) - cell.origin[k]) * n, cell.lengths[k]))) for k, (a, n) in enumerate(zip("xyz", blocks))]
    return atoms.select("atom_id", ((at[0] * blocks[1] + at[1]) * blocks[2] + at[2]).cast("int").alias("part_id"))


def bisection_partition(atoms: DataFrame, cell: Cell, p: int, scratch: Scratch | None = None) -> DataFrame:
    """Recursive halving at the median along x, y, z in turn; p is a power of two. Halves are cut by rank among all atoms of
    a part, from ranges of atoms, so no part is sorted by one task."""
    scratch = scratch or Scratch(atoms.sparkSession)
    out = atoms.select("atom_id", "x", "y", "z", F.lit(0).alias("part_id"))
    for level in range(p.bit_length() - 1):
        axis = "xyz"[level % 3]
        keys = ("part_id", axis, "atom_id")
        dealt = scratch.keep(out.repartitionByRange(*keys).withColumn("_p", F.spark_partition_id()), "ranged")
        sizes = dealt.groupBy("part_id", "_p").agg(F.count(F.lit(1)).alias("n"))  # about a row for each range and part
        part = Window.partitionBy("part_id")
        begins = sizes.select("part_id", "_p", F.coalesce(F.sum("n").over(part.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("begin"), F.sum("n").over(part).alias("all"))
        rank = F.col("begin") + F.row_number().over(Window.partitionBy("part_id", "_p").orderBy(axis, "atom_id")) - 1
        upper = (rank >= F.ceil(F.col("all") / 2)).cast("int")
        out = dealt.join(F.broadcast(begins), ["part_id", "_p"]).select("atom_id", "x", "y", "z", (F.col("part_id") * 2 + upper).alias("part_id"))
    return out.select("atom_id", "part_id")


def morton_code(cell: Cell, bits: int = 10):
    """Interleaved bits of the three scaled coordinates."""
    code = F.lit(0).cast("long")
    for k, a in enumerate("xyz"):
        scaled = F.greatest(F.lit(0), F.least(F.lit((1 << bits) - 1), whole((F.col(a) - cell.origin[k]) * (1 << bits), cell.lengths[k]))).cast("long")
        for b in range(bits):
            code = code + F.shiftleft(F.shiftright(scaled, b).bitwiseAND(1), 3 * b + k)
    return code


def morton_partition(atoms: DataFrame, cell: Cell, p: int) -> DataFrame:
    """Equal runs along a space-filling curve."""
    return equal_counts(atoms.withColumn("code", morton_code(cell)), ["code"], p)


def _undirected(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).filter("src <> dst").distinct()


def _shared(edges: DataFrame, scratch: Scratch, name: str, make):
    """What rules of one call read of the same edges, made once."""
    if scratch.shared.get("edges") is not edges:
        scratch.shared = {"edges": edges}
    if name not in scratch.shared:
        scratch.shared[name] = make()
    return scratch.shared[name]


def _both(edges: DataFrame, scratch: Scratch) -> DataFrame:
    return _shared(edges, scratch, "both", lambda: scratch.keep(_undirected(edges), "both"))


def _shards(atoms: DataFrame, edges: DataFrame, scratch: Scratch, shard_nodes: int) -> Shards:
    found = _shared(edges, scratch, f"shards of {shard_nodes}", lambda: (atoms, Shards(atoms, edges, scratch, shard_nodes)))
    return found[1] if found[0] is atoms else Shards(atoms, edges, scratch, shard_nodes)


def growth_partition(atoms: DataFrame, edges: DataFrame, p: int, scratch, shard_nodes: int = SHARD_NODES) -> DataFrame:
    """Breadth-first growth from p seeds spread over the identifiers; the smaller part wins a tie, islands go by hash."""
    low, high = atoms.agg(F.min("atom_id"), F.max("atom_id")).first()
    if low is None:
        return hash_partition(atoms, p)
    wanted = [low + (high - low) * i // p for i in range(p)]
    seeds = None
    for i, w in enumerate(wanted):
        one = atoms.filter(F.col("atom_id") >= w).agg(F.min("atom_id").alias("atom_id")).withColumn("part_id", F.lit(i))
        seeds = one if seeds is None else seeds.union(one)
    first = {r.atom_id: r.part_id for r in seeds.groupBy("atom_id").agg(F.min("part_id").alias("part_id")).collect()}  # a row for each part
    reached = scratch.keep(_shards(atoms, edges, scratch, shard_nodes).nearest(first, p), "grown")
    return atoms.select("atom_id").join(reached.hint("merge"), "atom_id", "left").select("atom_id", F.coalesce("part_id", F.pmod("atom_id", F.lit(p))).cast("int").alias("part_id"))


#: Shards in which a part admits nodes, each a share of its room.
SHARDS = 64


def _admitted(wish: DataFrame, size: DataFrame, room: int, *order) -> DataFrame:
    """atom_id, to of the wishes that parts have room for. Room is shared out over shards of nodes, so the wishes for a part
    are not put in order by one task."""
    shard = F.pmod(F.xxhash64("atom_id"), F.lit(SHARDS))
    turn = F.row_number().over(Window.partitionBy("to", "shard").orderBy(*order, "atom_id"))
    free = F.lit(room) - F.col("count")
    share = F.floor(free / SHARDS) + F.when(F.col("shard") < F.pmod(free, F.lit(SHARDS)), 1).otherwise(0)
    return wish.withColumn("shard", shard).withColumn("turn", turn).join(F.broadcast(size), "to").filter((free > 0) & (F.col("turn") <= share)).select("atom_id", "to")  # a row for each part


def label_partition(atoms: DataFrame, edges: DataFrame, p: int, scratch, rounds: int = 5, slack: float = 1.2) -> DataFrame:
    """Label propagation from a hash start: nodes move to the part most of their neighbours have, while it has room."""
    n = atoms.count()
    room = int(slack * n / p) + 1
    both = _both(edges, scratch)
    now = scratch.keep(wall_partition(atoms, None, p, axis="id"), "labels")
    for k in range(rounds):
        votes = both.join(now.select(F.col("atom_id").alias("src"), "part_id").hint("merge"), "src").groupBy(F.col("dst").alias("atom_id"), "part_id").count()
        best = votes.groupBy("atom_id").agg(F.max_by("part_id", F.struct("count", -F.col("part_id"))).alias("to"))
        wish = now.join(best.hint("merge"), "atom_id").filter((F.col("to") != F.col("part_id")) & (F.pmod(F.col("atom_id") + k, F.lit(2)) == 0))
        size = now.groupBy(F.col("part_id").alias("to")).count()
        now = scratch.keep(now.join(_admitted(wish, size, room).hint("merge"), "atom_id", "left").select("atom_id", F.coalesce("to", "part_id").alias("part_id")), "labels")
    return now


#: Nodes of a shard of the greedy pass, about.
GREEDY_NODES = 100_000


def greedy_partition(atoms: DataFrame, edges: DataFrame, p: int, shard_nodes: int = GREEDY_NODES, scratch: Scratch | None = None) -> DataFrame:
    """One pass over each shard of nodes in identifier order: the part with most neighbours placed so far, less a
    penalty for its size. Shards are ranges of identifiers, so each is a bounded stream of its own."""
    low, high, n = atoms.agg(F.min("atom_id"), F.max("atom_id"), F.count(F.lit(1))).first()
    low, high, shards = low or 0, high or 0, -(-n // shard_nodes) or 1
    shard = whole((F.col("atom_id") - low) * shards, high - low + 1)
    both = _both(edges, scratch) if scratch else _undirected(edges)
    near = both.groupBy(F.col("dst").alias("atom_id")).agg(F.sort_array(F.collect_list("src")).alias("near"))
    rows = atoms.select("atom_id").join(near.hint("merge"), "atom_id", "left").withColumn("shard", shard)

    def run(table):
        import pyarrow as pa

        table = table.sort_by("atom_id")
        ids, near = table.column("atom_id").to_pylist(), table.column("near").to_pylist()
        placed, sizes = {}, [0] * p
        room = len(ids) / p * 1.1 + 1
        for i, n in zip(ids, near):
            score = [0.0] * p
            for j in n or ():
                if (q := placed.get(j)) is not None:
                    score[q] += 1
            best = max(range(p), key=lambda q: (score[q] * max(0.0, 1 - sizes[q] / room), -sizes[q], -q))
            placed[i] = best
            sizes[best] += 1
        return pa.table({"atom_id": pa.array(ids, pa.int64()), "part_id": pa.array([placed[i] for i in ids], pa.int32())})

    return rows.groupBy("shard").applyInArrow(run, "atom_id long, part_id int")


def multilevel_partition(atoms: DataFrame, edges: DataFrame, p: int, scratch, levels: int = 3, refine: int = 2) -> DataFrame:
    """Coarsen by heavy-edge matching, split the coarse nodes by number, project back and refine by label moves."""
    fine = scratch.keep(atoms.select("atom_id", F.col("atom_id").alias("coarse")), "level")
    links = _both(edges, scratch).withColumn("w", F.lit(1).cast("long"))
    for _ in range(levels):
        # a node proposes to its heaviest neighbour; mutual proposals merge into the smaller identifier
        rank = F.struct("w", -F.col("dst"))
        best = links.groupBy("src").agg(F.max_by("dst", rank).alias("to"))
        mutual = best.alias("a").join(best.alias("b").hint("merge"), (F.col("a.to") == F.col("b.src")) & (F.col("b.to") == F.col("a.src"))).select(F.col("a.src").alias("coarse"), F.least("a.src", "a.to").alias("up"))
        mutual = scratch.keep(mutual, "mutual")
        fine = scratch.keep(fine.join(mutual.hint("merge"), "coarse", "left").select("atom_id", F.coalesce("up", "coarse").alias("coarse")), "level")
        name = lambda c: mutual.select(F.col("coarse").alias(c), F.col("up").alias(f"{c}_up"))
        lifted = links.join(name("src").hint("merge"), "src", "left").join(name("dst").hint("merge"), "dst", "left").select(F.coalesce("src_up", "src").alias("src"), F.coalesce("dst_up", "dst").alias("dst"), "w")
        links = scratch.keep(lifted.filter("src <> dst").groupBy("src", "dst").agg(F.sum("w").alias("w")), "links")
    coarse = fine.groupBy("coarse").count().select(F.col("coarse").alias("atom_id"))
    split = equal_counts(coarse, ["atom_id"], p)
    start = scratch.keep(fine.join(split.withColumnRenamed("atom_id", "coarse").hint("merge"), "coarse").select("atom_id", "part_id"), "split")
    return _refine(start, edges, p, scratch, refine)


def _refine(now: DataFrame, edges: DataFrame, p: int, scratch, rounds: int) -> DataFrame:
    both = _both(edges, scratch)
    room = int(1.1 * now.count() / p) + 1
    for k in range(rounds):
        seen = both.join(now.select(F.col("atom_id").alias("src"), F.col("part_id").alias("there")).hint("merge"), "src").groupBy(F.col("dst").alias("atom_id"), "there").count()
        joined = seen.join(now.hint("merge"), "atom_id")
        gain = joined.groupBy("atom_id", "part_id").agg(F.max_by("there", F.struct("count", -F.col("there"))).alias("to"), F.max("count").alias("most"), F.sum(F.when(F.col("there") == F.col("part_id"), F.col("count")).otherwise(0)).alias("own"))
        wish = gain.filter((F.col("most") > F.col("own")) & (F.pmod(F.col("atom_id") + k, F.lit(2)) == 0))
        size = now.groupBy(F.col("part_id").alias("to")).count()
        moved = _admitted(wish, size, room, F.col("own") - F.col("most"))
        now = scratch.keep(now.join(moved.hint("merge"), "atom_id", "left").select("atom_id", F.coalesce("to", "part_id").alias("part_id")), "refined")
    return now


def spectral_partition(atoms: DataFrame, edges: DataFrame, p: int, scratch, rounds: int = 12, shard_nodes: int = SHARD_NODES) -> DataFrame:
    """Equal runs along an approximate second eigenvector of the random walk, by power iteration with the mean removed."""
    vector = _shards(atoms, edges, scratch, shard_nodes).eigenvector(rounds)
    vector = scratch.keep(atoms.select("atom_id").join(vector.hint("merge"), "atom_id", "left"), "vector")
    return equal_counts(vector, ["v"], p)


def partition(atoms: DataFrame, edges: DataFrame, cell: Cell | None, p: int, method: str, scratch=None) -> DataFrame:
    """assign by the named rule."""
    blocks = {1: (1, 1, 1), 2: (2, 1, 1), 4: (2, 2, 1), 8: (2, 2, 2), 16: (4, 2, 2)}
    rules = {
        "wall": lambda: wall_partition(atoms, cell, p, axis="longest" if cell else "id"), "hash": lambda: hash_partition(atoms, p), "random": lambda: random_partition(atoms, p),
        "blocks": lambda: block_partition(atoms, cell, blocks[p]), "rcb": lambda: bisection_partition(atoms, cell, p, scratch), "morton": lambda: morton_partition(atoms, cell, p),
        "bfs": lambda: growth_partition(atoms, edges, p, scratch), "labelprop": lambda: label_partition(atoms, edges, p, scratch), "greedy": lambda: greedy_partition(atoms, edges, p, scratch=scratch),
        "multilevel": lambda: multilevel_partition(atoms, edges, p, scratch), "spectral": lambda: spectral_partition(atoms, edges, p, scratch),
    }
    return rules[method]()


METHODS = ("wall", "hash", "random", "blocks", "rcb", "morton", "bfs", "labelprop", "greedy", "multilevel", "spectral")
