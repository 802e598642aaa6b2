"""Molecular dynamics: velocity Verlet over partitioned inference, in whole numbers or, for models in doubles, in doubles."""

from __future__ import annotations

import re
from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from halograph.graph.runtime import PartitionedGraph, at_source, backward, build_partitioned_graph, energy, exchange, forward
from halograph.graph.scratch import Scratch
from halograph.potentials import PotentialSpec, potential
from halograph.sources.systems import Cell, System
from halograph.twins import sql as q

#: Force units that change a velocity by one in half a step.
SOFT = 50_000_000
AXES = "xyz"


def _wrapped(cell: Cell, atoms: DataFrame) -> DataFrame:
    return atoms.withColumns({a: F.pmod(F.col(a), F.lit(cell.lengths[k])) for k, a in enumerate(AXES) if cell.periodic[k]}) if any(cell.periodic) else atoms


def _kick(atoms: DataFrame, forces: DataFrame, soft: float, real: bool) -> DataFrame:
    """Half a step of force on the velocities; whole numbers are divided towards minus infinity."""

    def push(a: str) -> Column:
        v = F.col(f"f{a}") / F.lit(float(soft))
        return v if real else F.floor(v).cast("long")

    return atoms.join(forces, "atom_id").select("atom_id", "species", *AXES, *[(F.col(f"v{a}") + push(a)).alias(f"v{a}") for a in AXES])


def refreshed(graph: PartitionedGraph, atoms: DataFrame, cell: Cell, spec: PotentialSpec) -> PartitionedGraph:
    """The same graph at new positions. Positions travel as features do: own ones lie in the lane, border ones are sent.
    Edges beyond the cutoff rest, and so do bonds beyond theirs and links of such bonds."""
    lanes, model = graph.lanes, potential(spec)
    placed = lanes.keep(lanes.dealt(graph.nodes.join(atoms.select("atom_id", *AXES), "atom_id").select("lane", "part_id", "atom_id", *AXES)), "positions")
    ends = [f"{e}_{a}" for e in ("src", "dst") for a in AXES]

    def moved(edges: DataFrame, received: DataFrame, reach: int | None) -> DataFrame:
        named = lambda df, e: df.select("lane", "atom_id", *[F.col(a).alias(f"{e}_{a}") for a in AXES])
        both = edges.drop("dx", "dy", "dz", "d2", "w")
        for e in ("src", "dst"):
            both = at_source(both, named(placed, e), named(received, e), ["lane"], [f"{e}_{a}" for a in AXES], e)
        both = both.withColumns({f"d{a}": F.col(f"src_{a}") + F.col(f"i{a}") * F.lit(cell.lengths[k]).cast("long") - F.col(f"dst_{a}") for k, a in enumerate(AXES)})
        near = both.withColumn("d2", F.col("dx") * F.col("dx") + F.col("dy") * F.col("dy") + F.col("dz") * F.col("dz")).drop(*ends)
        near = near if reach is None else near.filter(F.col("d2") <= reach**2)
        return near.withColumn("w", model.edge_weight())

    received = exchange(placed, graph.outbox, lanes)
    new = replace(graph, edges=lanes.keep(moved(graph.edges, received, spec.cutoff), "edges"), trace=[], bond_trace=[])
    if graph.bonds is not None:
        new.bonds = _moved_bonds(graph, new.edges, spec)
    return new


def _moved_bonds(graph: PartitionedGraph, edges: DataFrame, spec: PotentialSpec) -> "object":
    """Bonds take their displacements from the edges that they are; border bonds receive theirs from the owners."""
    lanes, key = graph.lanes, ["src", "dst", "ix", "iy", "iz"]
    fresh = edges.filter(F.col("d2") <= spec.bond_cutoff**2).select("lane", *key, "dx", "dy", "dz", "d2", "w")
    static = [c for c in graph.bonds.owned.columns if c not in ("dx", "dy", "dz", "d2", "w")]
    owned = lanes.keep(graph.bonds.owned.select(*static).join(fresh.hint("shuffle_hash"), ["lane", *key]), "bonds")
    values = owned.select("lane", "bid", "dx", "dy", "dz", "d2", "w")
    received = exchange(values, graph.bonds.outbox, lanes, "bid")
    before = at_source(graph.bonds.before.select(*static), values, received, ["lane"], ["dx", "dy", "dz", "d2", "w"], "bid", "bid").filter("d2 IS NOT NULL")
    return graph.bonds.refreshed(owned, lanes.keep(before, "before"), lanes)


class _Run:
    def __call__(self, system: System, spec: PotentialSpec, p: int, steps: int, *, skin: int = 0, soft: float = SOFT, scratch: Scratch | None = None, sink: str | None = None, every: int = 1) -> DataFrame:
        """trajectory(step, atom_id, x, y, z, vx, vy, vz), from rest; step 0 is the start.

        The graph is built for cutoff + skin and kept until an atom may have moved half the skin; without a skin it is
        built in each step. With ``sink`` every ``every``-th step is also appended there, in folders by step. Models with
        bonds have their bonds and links renewed as well. Models in doubles move in doubles, and ``energies`` then holds
        (step, potential, kinetic) of each step.
        """
        scratch = scratch or Scratch(system.atoms.sparkSession)
        model, cell = potential(spec), system.cell
        kind, real = model.a.kind, model.real
        atoms = scratch.keep(system.atoms.select("atom_id", "species", *[F.col(a).cast(kind).alias(a) for a in AXES], *[model.a.zero().alias(f"v{a}") for a in AXES]), "start")
        out = [atoms.withColumn("step", F.lit(0))]
        graph = built_at = None
        self.energies: list[tuple] = []
        self.builds = 0

        def forces(now: DataFrame) -> tuple[DataFrame, DataFrame, float]:
            """(positions, wrapped where the graph was built for them; forces; energy)"""
            nonlocal graph, built_at
            stale = True
            if graph is not None and skin:
                old = built_at.select("atom_id", *[F.col(a).alias(f"o{a}") for a in AXES])
                gap = sum(((F.col(a) - F.col(f"o{a}")) * (F.col(a) - F.col(f"o{a}")) for a in AXES), F.lit(0))
                moved = now.join(old, "atom_id").agg(F.max(gap)).first()[0] or 0  # one number
                stale = 4 * moved > skin * skin
            if stale:
                now = scratch.keep(_wrapped(cell, now), "wrapped") if any(cell.periodic) else now
                graph, built_at = build_partitioned_graph(replace(system, atoms=now), spec, p, scratch=scratch, skin=skin), now
                self.builds += 1
            current = refreshed(graph, now, cell, spec) if skin else graph
            state = forward(current, spec)
            total = energy(state, model).first()[0] if real else None
            return now, scratch.keep(backward(current, spec), "forces"), total

        def note(step: int, rows: DataFrame, total) -> None:
            if real:
                kinetic = rows.agg(F.sum(sum((F.col(f"v{a}") * F.col(f"v{a}") for a in AXES), F.lit(0.0)))).first()[0] or 0.0
                self.energies.append((step, total, kinetic * soft / 4))  # two half steps: a mass of soft / 2

        atoms, f, total = forces(atoms)
        note(0, atoms, total)
        for step in range(1, steps + 1):
            half = _kick(atoms, f, soft, real)
            drift = half.select("atom_id", "species", *[(F.col(a) + F.col(f"v{a}")).alias(a) for a in AXES], *[f"v{a}" for a in AXES])
            # positions stay unwrapped while a list lives, so images keep their meaning
            drift, f, total = forces(scratch.keep(drift, "drift"))
            atoms = scratch.keep(_kick(drift, f, soft, real), "step")
            note(step, atoms, total)
            out.append(atoms.withColumn("step", F.lit(step)))
            if sink and step % every == 0:
                atoms.withColumn("step", F.lit(step)).write.mode("append").partitionBy("step").parquet(sink)
        whole = out[0]
        for o in out[1:]:
            whole = whole.unionByName(o)
        return whole.select("step", "atom_id", *AXES, *[f"v{a}" for a in AXES])

    @staticmethod
    def twin(steps: int, cutoff: int = 100, system: list | None = None, periodic: bool = False, layers: int = 1) -> str:
        """SQL of the same for a ring model: the open cloud, or a periodic system whose positions are wrapped."""
        made = dict(system or q.cloud())
        fixed = [(n, b) for n, b in made.items() if n != "atoms"]
        ctes = [*fixed, ("p0", made["atoms"]), ("k0", "SELECT *, 0 AS vx, 0 AS vy, 0 AS vz FROM p0")]
        names = ["atoms", "slabs", "around", "pairs", "moved", "near", "edges", "s0", "q", "pulls", "forces", "r0"]
        names += [f"{x}{k}" for k in range(1, layers + 1) for x in "smrto"]

        def force(k: int, of: str) -> list:
            rename = {n: f"{n}_{k}" for n in names}
            made = [("atoms", f"SELECT atom_id, species, x, y, z FROM {of}")] + q.edges(cutoff, periodic) + q.ring(layers) + q.ring_forces(layers)
            return [(rename[n], _swap(b, rename)) for n, b in made]

        ctes += force(0, "k0")
        at = lambda a: f"((x{a} % l{a}) + l{a}) % l{a}" if periodic else f"x{a}"
        for s in range(1, steps + 1):
            kick = lambda of, f: f"SELECT b.atom_id, species, x, y, z, " + ", ".join(f"v{a} + CAST(floor(f{a} / {float(SOFT)}) AS BIGINT) AS v{a}" for a in AXES) + f" FROM {of} b JOIN {f} USING (atom_id)"  # noqa: E731,F541
            ctes.append((f"h{s}", kick(f"k{s - 1}", f"forces_{s - 1}")))
            ctes.append((f"u{s}", f"SELECT atom_id, species, x + vx AS xx, y + vy AS xy, z + vz AS xz, vx, vy, vz FROM h{s}"))
            ctes.append((f"d{s}", f"SELECT atom_id, species, {', '.join(f'{at(a)} AS {a}' for a in AXES)}, vx, vy, vz FROM u{s}, cell"))
            ctes += force(s, f"d{s}")
            ctes.append((f"k{s}", kick(f"d{s}", f"forces_{s}")))
        return q.select(ctes, f"SELECT {steps} AS step, atom_id, x, y, z, vx, vy, vz FROM k{steps}")


def _swap(body: str, rename: dict[str, str]) -> str:
    """Table names after FROM and JOIN, and qualified columns, take the step's suffix."""
    body = re.sub(r"\b(FROM|JOIN)\s+([a-z_0-9]+)\b", lambda m: f"{m[1]} {rename.get(m[2], m[2])}", body)
    return re.sub(r"\b([st]\d)\.", lambda m: f"{rename.get(m[1], m[1])}.", body)


md_run = _Run()
