"""Pluggable potentials as column expressions.

The families are surrogates with the graph signature of each kind of model (which graphs, invariant or equivariant,
many-body, smooth); they are no pretrained models. Arithmetic is exact, modulo halograph.functions.ring.PRIME, unless the
spec asks for real numbers; then the same formulas run in doubles, with lengths in units of the cutoff.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column
from pyspark.sql import functions as F

from halograph.functions.ring import ARITHMETIC, pair_weight, smooth_weight, whole


@dataclass(frozen=True)
class PotentialSpec:
    """What a run needs to know of a model. n_parameters counts as layers * (width^2 + 16 width) in every family."""

    family: str = "ring"
    layers: int = 3
    width: int = 1
    cutoff: int = 5000
    bond_cutoff: int = 3000
    nu: int = 3
    arithmetic: str = "ring"

    def n_parameters(self) -> int:
        return self.layers * (self.width**2 + 16 * self.width)

    def matched_to(self, parameters: int) -> "PotentialSpec":
        """The same with the largest width whose parameter count does not pass the target."""
        width = 1
        while replace(self, width=width + 1).n_parameters() <= parameters:
            width += 1
        return replace(self, width=width)

    @property
    def interaction_range(self) -> int:
        return self.layers * self.cutoff


class Potential:
    """Interface of a plug-in: every method returns columns, so the optimiser sees through the model.

    A node's state is the columns in ``state``; ``message`` gives for every state sum a column over an edge (with the
    source's state under the same names) and ``update`` the new state from the old and the sums, named ``sum_<name>``.

    Conservative forces also need the adjoints. ``g_<state>`` is the energy's slope in the new state of a node and
    ``s_<sum>`` that in a message sum: ``sum_adjoints`` gives the second and ``state_adjoints`` the slope in the old state,
    both at a node; ``source_adjoints`` gives, over an edge, what the source's state receives, ``weight_adjoint`` the slope
    in the edge's weight, ``displacement_adjoint`` that in its displacement apart from the weight, and ``pull`` the force
    on the source from the two, named ``q`` and ``p<axis>``. A model without them has energies and direct forces only.
    """

    uses_bonds = False

    def __init__(self, spec: PotentialSpec):
        self.spec, self.a = spec, ARITHMETIC[spec.arithmetic]

    @property
    def real(self) -> bool:
        return self.spec.arithmetic == "real"

    @property
    def channels(self) -> list[str]:
        return [f"h{c}" for c in range(self.spec.width)]

    @property
    def state(self) -> list[str]:
        return self.channels

    def init_node(self) -> dict[str, Column]:
        first = (F.lit(1) + F.col("species")).cast(self.a.kind) / 16 if self.real else (F.lit(1) + F.col("species")).cast("long")
        return {h: self.a.mod(first * (c + 1)) for c, h in enumerate(self.channels)}

    def edge_weight(self) -> Column:
        """Weight of an edge: from its length, or as given by a graph without geometry."""
        return self._fall() if self.real else pair_weight(F.col("d2"), self.spec.cutoff)

    def _fall(self) -> Column:
        """From one at no distance to zero at the cutoff."""
        return 1 - F.col("d2") / float(self.spec.cutoff**2)

    def message(self) -> dict[str, Column]:
        return {h: F.col("w") * F.col(h) for h in self.channels}

    def update(self) -> dict[str, Column]:
        return {h: self.a.mod(F.col(h) + F.col(f"sum_{h}")) for h in self.channels}

    def readout(self) -> Column:
        return sum((F.col(h) for h in self.channels[1:]), F.col(self.channels[0]))

    def sum_adjoints(self) -> dict[str, Column]:
        raise NotImplementedError(f"{type(self).__name__} has no adjoints: conservative forces need them")

    state_adjoints = source_adjoints = weight_adjoint = pull = sum_adjoints

    def displacement_adjoint(self, axis: str) -> Column | None:
        return None


class RingPotential(Potential):
    """h' = h + sum of w h_src: linear, so its reverse pass is the exact transpose.

    In the ring, forces are in units of 32 over the squared cutoff, the constant of the weight's slope."""

    def sum_adjoints(self) -> dict[str, Column]:
        return {h: F.col(f"g_{h}") for h in self.channels}

    def state_adjoints(self) -> dict[str, Column]:
        return {h: F.col(f"g_{h}") for h in self.channels}

    def source_adjoints(self) -> dict[str, Column]:
        return {h: self.a.mod(F.col("w") * F.col(f"s_{h}")) for h in self.channels}

    def weight_adjoint(self) -> Column:
        return self.a.mod(sum((self.a.mod(F.col(h) * F.col(f"s_{h}")) for h in self.channels), self.a.zero()))

    def pull(self, axis: str) -> Column:
        d = F.col("q") * F.col(f"d{axis}")
        return d * 2 / float(self.spec.cutoff**2) if self.real else d


class ManyBodyPotential(RingPotential):
    """h' = h + A + A^2 + ... + A^nu of the message sum A: many-body terms without a bond graph."""

    def update(self) -> dict[str, Column]:
        return {h: self.a.mod(F.col(h) + self.a.powers(self.a.mod(F.col(f"sum_{h}")), self.spec.nu)) for h in self.channels}

    def sum_adjoints(self) -> dict[str, Column]:
        return {h: self.a.mod(self._slope(h) * F.col(f"g_{h}")) for h in self.channels}

    state_adjoints = RingPotential.state_adjoints

    def _slope(self, channel: str) -> Column:
        a = self.a.mod(F.col(f"sum_{channel}"))
        out = F.lit(self.spec.nu).cast(self.a.kind)
        for k in range(self.spec.nu - 1, 0, -1):
            out = self.a.mod(self.a.mul(out, a) + k)
        return out


class InvariantBondPotential(RingPotential):
    """Bonds carry a state of their own, updated over the bond graph before each update of the atoms.

    Forces of the ring are in units of one over the squared cutoff; every product of a bond angle's slope and a
    displacement is reduced first."""

    uses_bonds = True

    def _angle(self) -> Column:
        return F.col("dot") / float(self.spec.cutoff**2) if self.real else self.a.mod(F.col("dot"))

    def bond_message(self) -> Column:
        return self._angle() * F.col("b")

    def bond_update(self) -> Column:
        return self.a.mod(F.col("b") + F.col("sum_b"))

    def update(self) -> dict[str, Column]:
        return {h: self.a.mod(F.col(h) + F.col(f"sum_{h}") + F.col("sum_bond")) for h in self.channels}

    def sum_adjoints(self) -> dict[str, Column]:
        return RingPotential.sum_adjoints(self) | {"bond": self.a.mod(sum((F.col(f"g_{h}") for h in self.channels), self.a.zero()))}

    state_adjoints = RingPotential.state_adjoints

    def bond_source_adjoint(self) -> Column:
        """What the first bond of a link receives from the slope ``gb`` in the second's new state."""
        return self.a.mod(self._angle() * F.col("gb"))

    def angle_adjoint(self) -> Column:
        return self.a.mod(F.col("b") * F.col("gb"))

    def angle_pull(self, slope: Column, d: Column) -> Column:
        """Force from the slope in a link's product of displacements, of which ``d`` is the other one."""
        turned = self.a.mod(slope * d)
        return turned / float(self.spec.cutoff**2) if self.real else turned * self.spec.cutoff**2

    def pull(self, axis: str) -> Column:
        return super().pull(axis) * (1 if self.real else 32)


class LightEquivariantPotential(RingPotential):
    """A scalar and a vector in each channel; vectors turn with the system, scalars do not.

    Forces of the ring are in units of one over the squared cutoff."""

    @property
    def state(self) -> list[str]:
        return [x for c in range(self.spec.width) for x in (f"h{c}", f"vx{c}", f"vy{c}", f"vz{c}")]

    def init_node(self) -> dict[str, Column]:
        return super().init_node() | {f"v{a}{c}": self.a.zero() for c in range(self.spec.width) for a in "xyz"}

    def _d(self, axis: str) -> Column:
        return F.col(f"d{axis}") / float(self.spec.cutoff) if self.real else F.col(f"d{axis}")

    def message(self) -> dict[str, Column]:
        out = super().message()
        for c in range(self.spec.width):
            for a in "xyz":
                out[f"v{a}{c}"] = self.a.mod(self.a.mul(F.col("w"), F.col(f"h{c}")) * self._d(a)) + F.col("w") * F.col(f"v{a}{c}")
        return out

    def _turned(self, c: int) -> dict[str, Column]:
        return {a: self.a.mod(F.col(f"v{a}{c}") + F.col(f"sum_v{a}{c}")) for a in "xyz"}

    def update(self) -> dict[str, Column]:
        out = {}
        for c in range(self.spec.width):
            v = self._turned(c)
            out |= {f"v{a}{c}": v[a] for a in "xyz"}
            out[f"h{c}"] = self.a.mod(F.col(f"h{c}") + F.col(f"sum_h{c}") + self.a.mul(v["x"], v["x"]) + self.a.mul(v["y"], v["y"]) + self.a.mul(v["z"], v["z"]))
        return out

    def sum_adjoints(self) -> dict[str, Column]:
        out = {}
        for c in range(self.spec.width):
            v = self._turned(c)
            out[f"h{c}"] = F.col(f"g_h{c}")
            out |= {f"v{a}{c}": self.a.mod(F.col(f"g_v{a}{c}") + self.a.mod(v[a] * F.col(f"g_h{c}")) * 2) for a in "xyz"}
        return out

    state_adjoints = sum_adjoints

    def source_adjoints(self) -> dict[str, Column]:
        out, mod = {}, self.a.mod
        for c in range(self.spec.width):
            turned = sum((mod(mod(F.col("w") * self._d(a)) * F.col(f"s_v{a}{c}")) for a in "xyz"), mod(F.col("w") * F.col(f"s_h{c}")))
            out |= {f"h{c}": mod(turned)} | {f"v{a}{c}": mod(F.col("w") * F.col(f"s_v{a}{c}")) for a in "xyz"}
        return out

    def weight_adjoint(self) -> Column:
        total, mod = self.a.zero(), self.a.mod
        for c in range(self.spec.width):
            h = F.col(f"h{c}")
            total = total + mod(h * F.col(f"s_h{c}"))
            for a in "xyz":
                total = total + mod(mod(mod(h * self._d(a)) + F.col(f"v{a}{c}")) * F.col(f"s_v{a}{c}"))
        return mod(total)

    def displacement_adjoint(self, axis: str) -> Column:
        mod = self.a.mod
        return mod(sum((mod(mod(F.col("w") * F.col(f"h{c}")) * F.col(f"s_v{axis}{c}")) for c in range(self.spec.width)), self.a.zero()))

    def pull(self, axis: str) -> Column:
        reach = self.spec.cutoff
        if self.real:
            return super().pull(axis) - F.col(f"p{axis}") / float(reach)
        return F.col("q") * F.col(f"d{axis}") * 32 - F.col(f"p{axis}") * reach**2


class SmoothEquivariantPotential(LightEquivariantPotential):
    """As the light one, with an envelope whose value and slope vanish at the cutoff and a one-time setup.

    The setup multiplies the first features by the number of atoms of the species in the whole system. Forces of the
    ring are in units of one over 250.
    """

    def edge_weight(self) -> Column:
        return self._fall() * self._fall() if self.real else smooth_weight(F.col("d2"), self.spec.cutoff)

    def pull(self, axis: str) -> Column:
        reach = self.spec.cutoff
        if self.real:
            return F.col("q") * self._fall() * 4 * F.col(f"d{axis}") / float(reach**2) - F.col(f"p{axis}") / float(reach)
        gap = self.a.mod(whole(F.lit(reach**2).cast("long") - F.col("d2"), 1000))
        return self.a.mod(F.col("q") * gap) * F.col(f"d{axis}") - F.col(f"p{axis}") * 250


class RivalDistributedModel(RingPotential):
    """A model with distributed inference of its own: the ring update, run under spatial partitioning only."""


_FAMILIES: dict[str, type[Potential]] = {
    "ring": RingPotential, "many_body": ManyBodyPotential, "invariant_bond": InvariantBondPotential, "light": LightEquivariantPotential, "smooth": SmoothEquivariantPotential, "rival": RivalDistributedModel,
}


def register_potential(name: str, cls: type[Potential]) -> None:
    """Adds a model of one's own; nothing else of the engine changes."""
    _FAMILIES[name] = cls


def potential(spec: PotentialSpec) -> Potential:
    return _FAMILIES[spec.family](spec)


def check_adjoints(model: Potential) -> None:
    """Refuses a model whose adjoints are not its own: those of a class it derives from belong to that class's formulas."""
    order = type(model).__mro__
    at = lambda name: next(k for k, c in enumerate(order) if name in c.__dict__)
    for adjoint, formulas in (("sum_adjoints", ("update",)), ("state_adjoints", ("update",)), ("source_adjoints", ("message",)), ("weight_adjoint", ("message",)), ("pull", ("edge_weight",))):
        if order[at(adjoint)] is Potential or any(at(f) < at(adjoint) and order[at(f)] is not Potential for f in formulas):
            raise NotImplementedError(f"{type(model).__name__} changes {', '.join(formulas)} without {adjoint}: it has no conservative forces")


def families() -> tuple[str, ...]:
    return tuple(_FAMILIES)
