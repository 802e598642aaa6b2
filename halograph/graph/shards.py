"""A graph in shards: ranges of node identifiers, each packed into one row that a task holds whole.

Rounds that walk over the edges walk on inside a shard as far as they get and tell other shards only what crosses to them,
so their number depends on how often a path leaves a shard, not on its length. Rows carry arrays as bytes.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Nodes of a shard, about.
SHARD_NODES = 100_000
#: Edges that a task gathers before it deals them out.
DEALT = 200_000
_FAR = (1 << 63) - 1


def _ints(blob, kind="i8"):
    import numpy as np

    return np.frombuffer(blob, dtype=kind)


def _by_shard(shard, *arrays):
    """shard, arrays of each shard that occurs."""
    import numpy as np

    order = np.argsort(shard, kind="stable")
    found, first = np.unique(shard[order], return_index=True)
    cut = [np.split(a[order], first[1:]) for a in arrays]
    return [(int(s), *[c[k] for c in cut]) for k, s in enumerate(found)]


class Shards:
    """starts: the least identifier of each shard but the first. packed(shard, ids, real, begin, near, cut, beyond): nodes in rising
    order, real where they are atoms; their neighbours inside the shard by place, those of node k from begin[k] to begin[k + 1]; and edges that leave it,
    from place cut[j] to identifier beyond[j]. Edges go both ways, each once; ends that are no atoms are nodes too."""

    def __init__(self, atoms: DataFrame, edges: DataFrame, scratch, shard_nodes: int = SHARD_NODES):
        self.spark, self.scratch = atoms.sparkSession, scratch
        n = atoms.count()
        k = max(1, -(-n // shard_nodes))
        walls = atoms.agg(F.percentile_approx("atom_id", [i / k for i in range(1, k)], max(10_000, 20 * k))).first()[0] if k > 1 else []
        self.starts = starts = sorted(set(walls or []))
        self.count = len(starts) + 1
        dealt, schema = DEALT, "shard long, a binary, b binary"

        def deal_edges(batches):
            import numpy as np
            import pyarrow as pa

            def out(held):
                a = np.concatenate([h[0] for h in held])
                b = np.concatenate([h[1] for h in held])
                low, high = np.minimum(a, b), np.maximum(a, b)
                order = np.lexsort((high, low))
                low, high = low[order], high[order]
                keep = (low != high) & np.concatenate([[True], (low[1:] != low[:-1]) | (high[1:] != high[:-1])])
                low, high = low[keep], high[keep]
                a, b = np.concatenate([low, high]), np.concatenate([high, low])
                rows = _by_shard(np.searchsorted(starts, a, side="right") if starts else np.zeros(len(a), np.int64), a, b)
                return pa.RecordBatch.from_pydict({"shard": pa.array([r[0] for r in rows], pa.int64()), "a": pa.array([r[1].tobytes() for r in rows], pa.binary()), "b": pa.array([r[2].tobytes() for r in rows], pa.binary())})

            held, size = [], 0
            for batch in batches:
                if batch.num_rows:
                    held.append([batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in (0, 1)])
                    size += batch.num_rows
                if size >= dealt:
                    yield out(held)
                    held, size = [], 0
            if held:
                yield out(held)

        def deal_nodes(batches):
            import numpy as np
            import pyarrow as pa

            for batch in batches:
                if not batch.num_rows:
                    continue
                ids = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
                rows = _by_shard(np.searchsorted(starts, ids, side="right") if starts else np.zeros(len(ids), np.int64), ids)
                yield pa.RecordBatch.from_pydict({"shard": pa.array([r[0] for r in rows], pa.int64()), "a": pa.array([r[1].tobytes() for r in rows], pa.binary()), "b": pa.array([b""] * len(rows), pa.binary())})

        def pack(table):
            import numpy as np
            import pyarrow as pa

            shard = table.column("shard")[0].as_py()
            a, b = [_ints(x) for x in table.column("a").to_pylist()], [_ints(x) for x in table.column("b").to_pylist()]
            ids = np.unique(np.concatenate(a))
            src = np.concatenate([x for x, y in zip(a, b) if len(y)] or [ids[:0]])
            dst = np.concatenate([y for y in b if len(y)] or [ids[:0]])
            order = np.lexsort((dst, src))
            src, dst = src[order], dst[order]
            once = np.ones(len(src), bool)
            once[1:] = (src[1:] != src[:-1]) | (dst[1:] != dst[:-1])
            src, dst = np.searchsorted(ids, src[once]), dst[once]
            inside = (np.searchsorted(starts, dst, side="right") if starts else np.zeros(len(dst), np.int64)) == shard
            near = np.searchsorted(ids, dst[inside]).astype(np.int32)
            begin = np.concatenate([[0], np.cumsum(np.bincount(src[inside], minlength=len(ids)))]).astype(np.int64)
            real = np.isin(ids, np.concatenate([x for x, y in zip(a, b) if not len(y)] or [ids[:0]]))
            parts = {"ids": ids, "real": real, "begin": begin, "near": near, "cut": src[~inside].astype(np.int32), "beyond": dst[~inside]}
            return pa.table({"shard": pa.array([shard], pa.int64())} | {k: pa.array([v.tobytes()], pa.binary()) for k, v in parts.items()})

        nodes = atoms.select(F.col("atom_id").cast("long")).filter("atom_id IS NOT NULL").mapInArrow(deal_nodes, schema)
        ends = edges.select(F.col("src").cast("long"), F.col("dst").cast("long")).filter("src <> dst").mapInArrow(deal_edges, schema)
        packed = nodes.union(ends).groupBy("shard").applyInArrow(pack, "shard long, ids binary, real binary, begin binary, near binary, cut binary, beyond binary")
        self.packed = scratch.keep(packed, "shards")

    def nearest(self, seeds: dict[int, int], p: int) -> DataFrame:
        """atom_id, part_id of the nodes that seeds (node: part below p) reach: by fewest hops, among equals the least part.

        A key is hops * p + part, so a hop adds p and the least key wins. A shard that is told of nodes walks from them by rising
        hops to the end and tells on what it found; shards that are told nothing are not read.
        """
        import bisect

        starts, count, spark = self.starts, self.count, self.spark
        told = [(bisect.bisect_right(starts, i), i.to_bytes(8, "little", signed=True), j.to_bytes(8, "little")) for i, j in seeds.items()]
        # version: round * count + shard of a state, -1 of what a shard is told
        inbox = spark.createDataFrame([(s, -1, i, k) for s, i, k in told], "shard long, version long, ids binary, keys binary")
        active, newest, paths, turn = sorted({s for s, _, _ in told}), {}, [], 0
        while active:

            def walk(graph, said):
                import numpy as np
                import pyarrow as pa

                shard, ids = graph.column("shard")[0].as_py(), _ints(graph.column("ids")[0].as_py())
                begin, near = _ints(graph.column("begin")[0].as_py()), _ints(graph.column("near")[0].as_py(), "i4")
                key, at, new = np.full(len(ids), _FAR, np.int64), [ids[:0]], [ids[:0]]
                for version, i, k in zip(said.column("version").to_pylist(), said.column("ids").to_pylist(), said.column("keys").to_pylist()):
                    if version >= 0:
                        key = _ints(k).copy()
                    else:
                        at.append(np.searchsorted(ids, _ints(i)))
                        new.append(_ints(k))
                at, new = np.concatenate(at), np.concatenate(new)
                better = new < key[at]
                at, new = at[better], new[better]
                order = np.argsort(new, kind="stable")
                at, new = at[order], new[order]
                changed, done, front, hops = np.zeros(len(ids), bool), 0, at[:0], 0
                while len(front) or done < len(at):
                    if not len(front):
                        hops = int(new[done]) // p
                    until = int(np.searchsorted(new, (hops + 1) * p))
                    if until > done:  # told of nodes at this many hops
                        i, k = at[done:until], new[done:until]
                        less = k < key[i]
                        np.minimum.at(key, i[less], k[less])
                        front, done = np.unique(np.concatenate([front, i[less]])), until
                    changed[front] = True
                    size = begin[front + 1] - begin[front]
                    edge = np.repeat(begin[front] - np.concatenate([[0], np.cumsum(size)[:-1]]) if len(size) else size, size) + np.arange(size.sum())
                    v, k = near[edge], np.repeat(key[front], size) + p
                    less = k < key[v]
                    v, k = v[less], k[less]
                    np.minimum.at(key, v, k)
                    front, hops = np.unique(v), hops + 1
                rows = [(shard, turn * count + shard, b"", key.tobytes())]
                cut, beyond = _ints(graph.column("cut")[0].as_py(), "i4"), _ints(graph.column("beyond")[0].as_py())
                out = changed[cut]
                to, k = beyond[out], key[cut[out]] + p
                order = np.lexsort((k, to))
                to, k = to[order], k[order]
                first = np.ones(len(to), bool)
                first[1:] = to[1:] != to[:-1]  # the least key for a node
                to, k = to[first], k[first]
                rows += [(s, -1, i.tobytes(), x.tobytes()) for s, i, x in _by_shard(np.searchsorted(starts, to, side="right"), to, k)] if len(to) else []
                kinds = (pa.int64(), pa.int64(), pa.binary(), pa.binary())
                return pa.table([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=["shard", "version", "ids", "keys"])

            if newest:
                held = [newest[s] for s in active if s in newest]
                inbox = spark.read.schema(inbox.schema).parquet(*paths).filter(F.col("version").isin(held)).union(inbox) if held else inbox
            graph = self.packed.filter(F.col("shard").isin(active))
            path = self.scratch.path("walk")
            graph.groupBy("shard").cogroup(inbox.groupBy("shard")).applyInArrow(walk, inbox.schema).write.parquet(path)
            paths.append(path)
            newest |= {s: turn * count + s for s in active}
            inbox = spark.read.schema(inbox.schema).parquet(path).filter("version = -1")
            active, turn = sorted(r[0] for r in inbox.select("shard").distinct().collect()), turn + 1  # a row for each shard

        def unpack(graph, state):
            import pyarrow as pa

            ids, key = _ints(graph.column("ids")[0].as_py()), _ints(state.column("keys")[0].as_py())
            met = key < _FAR
            return pa.table({"atom_id": pa.array(ids[met], pa.int64()), "part_id": pa.array(key[met] % p, pa.int32())})

        last = spark.read.schema(inbox.schema).parquet(*paths).filter(F.col("version").isin(list(newest.values())))
        graph = self.packed.filter(F.col("shard").isin(list(newest))).select("shard", "ids")
        return graph.groupBy("shard").cogroup(last.select("shard", "keys").groupBy("shard")).applyInArrow(unpack, "atom_id long, part_id int")

    def eigenvector(self, rounds: int) -> DataFrame:
        """atom_id, v: power iteration of the lazy random walk from values that the identifiers give, the mean by degree removed
        and the length made one after each round. A round sends the values of border nodes, once to each shard beside them."""
        starts, spark = self.starts, self.spark
        schema = "shard long, told boolean, ids binary, v binary, sums array<double>"
        read = lambda path: spark.read.schema(schema).parquet(path)
        mean, scale, path = 0.0, 1.0, None
        for turn in range(rounds + 1):

            def spin(graph, said):
                import numpy as np
                import pyarrow as pa

                shard, ids = graph.column("shard")[0].as_py(), _ints(graph.column("ids")[0].as_py())
                real = _ints(graph.column("real")[0].as_py(), "?")
                begin, near = _ints(graph.column("begin")[0].as_py()), _ints(graph.column("near")[0].as_py(), "i4")
                cut, beyond = _ints(graph.column("cut")[0].as_py(), "i4"), _ints(graph.column("beyond")[0].as_py())
                n, size = len(ids), np.diff(begin)
                degree = size + np.bincount(cut, minlength=n)
                if turn == 0:
                    v = np.where(real, (ids * 7919) % 1_000_003 / 1_000_003.0 - 0.5, 0.0)
                else:
                    at, far = [ids[:0]], [np.empty(0)]
                    for told, i, x in zip(*[said.column(c).to_pylist() for c in ("told", "ids", "v")]):
                        x = (_ints(x, "f8") - mean) / scale
                        if told:
                            at.append(_ints(i)), far.append(x)
                        else:
                            v = np.where(real, x, 0.0)
                    at, far = np.concatenate(at), np.concatenate(far)
                    order = np.argsort(at)
                    at, far = at[order], far[order]
                    place = np.searchsorted(at, beyond)
                    heard = np.append(at, 0)[place] == beyond
                    heard &= place < len(at)  # ends that are no atoms tell nothing
                    mine, there = cut[heard], np.append(far, 0.0)[place[heard]]
                    src = np.repeat(np.arange(n), size)
                    total = np.bincount(src, weights=v[near], minlength=n) + np.bincount(mine, weights=there, minlength=n)
                    some = np.bincount(src, weights=real[near], minlength=n) + np.bincount(mine, minlength=n) > 0
                    v = np.where(real, v / 2 + np.where(some, total / np.maximum(degree, 1), v) / 2, 0.0)
                sums = [float((v * degree).sum()), float(degree[real].sum()), float((v * v).sum()), float(real.sum())]
                rows = [(shard, False, b"", v.tobytes(), sums)]
                if turn < rounds:
                    out = real[cut]
                    pair = np.unique(np.searchsorted(starts, beyond[out], side="right") * n + cut[out]) if out.any() else cut[:0]
                    rows += [(s, True, ids[k].tobytes(), v[k].tobytes(), None) for s, k in _by_shard(pair // n, pair % n)] if len(pair) else []
                kinds = (pa.int64(), pa.bool_(), pa.binary(), pa.binary(), pa.list_(pa.float64()))
                return pa.table([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=["shard", "told", "ids", "v", "sums"])

            said = read(path) if path else spark.createDataFrame([], schema)
            path = self.scratch.path("vector")
            self.packed.groupBy("shard").cogroup(said.groupBy("shard")).applyInArrow(spin, schema).write.parquet(path)
            if turn:
                sums = [r.sums for r in read(path).filter("NOT told").orderBy("shard").select("sums").collect()]  # a row for each shard
                moved, degrees, squares, n = [sum(x) for x in zip(*sums)] if sums else (0.0,) * 4
                mean, scale = moved / max(degrees, 1), (squares / max(n, 1)) ** 0.5 or 1.0

        def unpack(graph, state):
            import pyarrow as pa

            real = _ints(graph.column("real")[0].as_py(), "?")
            v = (_ints(state.column("v")[0].as_py(), "f8") - mean) / scale
            return pa.table({"atom_id": pa.array(_ints(graph.column("ids")[0].as_py())[real], pa.int64()), "v": pa.array(v[real], pa.float64())})

        state = read(path).filter("NOT told").select("shard", "v")
        return self.packed.select("shard", "ids", "real").groupBy("shard").cogroup(state.groupBy("shard")).applyInArrow(unpack, "atom_id long, v double")
