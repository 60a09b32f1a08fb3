"""The plate tree of a model, its messages and the order in which variables can be updated together."""

from __future__ import annotations

from dataclasses import dataclass, field

from ..lang.builder import ModelSpec, Plate, Rv, validate


@dataclass
class PlateNode:
    """An inner node: a plate (None: the top level, of size 1), its plates and its variables."""

    plate: Plate | None
    plates: list[PlateNode] = field(default_factory=list)
    rvs: list[Rv] = field(default_factory=list)


@dataclass
class NetworkTemplate:
    spec: ModelSpec
    root: PlateNode
    parents: dict[str, list[Rv]]
    children: dict[str, list[Rv]]


def build_template(spec: ModelSpec) -> NetworkTemplate:
    validate(spec)
    nodes: dict[int | None, PlateNode] = {None: PlateNode(None)}
    for p in spec.plates:
        nodes[id(p)] = PlateNode(p)
    for p in spec.plates:
        nodes[id(p.parent) if p.parent else None].plates.append(nodes[id(p)])
    parents: dict[str, list[Rv]] = {r.rid: [] for r in spec.rvs}
    children: dict[str, list[Rv]] = {r.rid: [] for r in spec.rvs}
    for r in spec.rvs:
        nodes[id(r.plate) if r.plate else None].rvs.append(r)
        if r.kind == "categorical":
            parents[r.rid] = [r.parent.prior, *r.parent.selectors]
            for p in parents[r.rid]:
                children[p.rid].append(r)
    return NetworkTemplate(spec, nodes[None], parents, children)


def message_types(t: NetworkTemplate) -> list[tuple[str, str, str]]:
    """(sender, receiver, direction) of the two messages of every dependency."""
    return [m for r in t.spec.rvs for p in t.parents[r.rid] for m in ((p.name, r.name, "parent to child"), (r.name, p.name, "child to parent"))]


def _linked(t: NetworkTemplate, a: Rv, b: Rv) -> bool:
    """Whether two variables exchange messages: parent and child, or parents of one child."""
    return b in t.parents[a.rid] or a in t.parents[b.rid] or any(b in t.parents[c.rid] for c in t.children[a.rid])


def make_schedule(t: NetworkTemplate, observed: set[str]) -> list[list[Rv]]:
    """Sub-steps of latent discrete variables without mutual messages, by greedy colouring, then the priors.

    Observed variables have no state, so the steps that would only pass their co-parents on are folded away.
    """
    steps: list[list[Rv]] = []
    for z in (r for r in t.spec.rvs if r.kind == "categorical" and r.rid not in observed):
        for step in steps:
            if not any(_linked(t, z, other) for other in step):
                step.append(z)
                break
        else:
            steps.append([z])
    return [*steps, [r for r in t.spec.rvs if r.kind == "dirichlet"]]


def sub_steps_of_all(t: NetworkTemplate) -> list[list[Rv]]:
    """The unfolded schedule over every variable: colour classes in the order of definition."""
    steps: list[list[Rv]] = []
    for r in t.spec.rvs:
        for step in steps:
            if not any(_linked(t, r, other) for other in step):
                step.append(r)
                break
        else:
            steps.append([r])
    return steps
