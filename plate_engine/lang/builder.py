"""A model as value definitions: constants, plates, Dirichlet priors, categorical variables, mixtures.

Nothing here touches Spark; binding constants and data turns a spec into a model that can be inferred.
"""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field


class ModelError(ValueError):
    """A model that can't be: an unbound or rebound name, a wrong prior, a cycle, a size that doesn't fit."""


@dataclass(frozen=True)
class Expr:
    """Deterministic arithmetic over constants, evaluated when the model is bound."""

    op: str
    args: tuple = ()

    @staticmethod
    def of(x: object) -> Expr:
        if isinstance(x, Expr):
            return x
        if isinstance(x, str):
            return Expr("name", (x,))
        if isinstance(x, bool) or not isinstance(x, int | float):
            raise ModelError(f"{x!r} is no constant of type long or double")
        return Expr("value", (x,))

    def __add__(self, o: object) -> Expr:
        return Expr("+", (self, Expr.of(o)))

    def __sub__(self, o: object) -> Expr:
        return Expr("-", (self, Expr.of(o)))

    def __mul__(self, o: object) -> Expr:
        return Expr("*", (self, Expr.of(o)))

    def __truediv__(self, o: object) -> Expr:
        return Expr("/", (self, Expr.of(o)))

    def __neg__(self) -> Expr:
        return Expr("neg", (self,))

    def __pos__(self) -> Expr:
        return self

    def names(self) -> set[str]:
        return {self.args[0]} if self.op == "name" else set().union(*(a.names() for a in self.args if isinstance(a, Expr)), set())

    def value(self, env: dict[str, float]) -> float:
        if self.op == "value":
            return self.args[0]
        if self.op == "name":
            if self.args[0] not in env:
                raise ModelError(f"constant {self.args[0]!r} isn't bound")
            return env[self.args[0]]
        got = [a.value(env) for a in self.args]
        if self.op == "neg":
            return -got[0]
        if self.op == "/" and got[1] == 0:
            raise ModelError("division by zero in a constant")
        return {"+": lambda a, b: a + b, "-": lambda a, b: a - b, "*": lambda a, b: a * b, "/": lambda a, b: a / b}[self.op](*got)


@dataclass(eq=False)
class Plate:
    """Repetition.  ``size`` is None where data will tell; a parent makes it nested and possibly ragged."""

    name: str
    size: Expr | None = None
    parent: Plate | None = None

    def chain(self) -> list[Plate]:
        """Outermost plate first, this one last."""
        return [*(self.parent.chain() if self.parent else []), self]


@dataclass(eq=False)
class Indexed:
    """A member of a plated Dirichlet picked by discrete variables, outer level first."""

    prior: Rv
    selectors: tuple[Rv, ...]


@dataclass(eq=False)
class Rv:
    rid: str
    kind: str
    plate: Plate | None
    names: set[str] = field(default_factory=set)
    concentration: Expr | None = None
    dimension: Expr | None = None
    parent: Indexed | None = None
    beta: bool = False

    @property
    def name(self) -> str:
        return min(self.names, default=self.rid)

    def at(self, *selectors: Rv) -> Indexed:
        return Indexed(self, selectors)

    def chain(self) -> list[Plate]:
        return self.plate.chain() if self.plate else []


class ModelSpec:
    """Single-assignment definitions of one model; each call defines one value."""

    def __init__(self, name: str, params: dict[str, type] | None = None):
        self.name = name
        self.params = dict(params or {})
        if bad := [p for p, t in self.params.items() if t not in (int, float)]:
            raise ModelError(f"parameters {bad} are neither long nor double")
        self.plates: list[Plate] = []
        self.rvs: list[Rv] = []
        self.statements = 0
        self._scopes: list[dict[str, object]] = [{p: Expr.of(p) for p in self.params}]

    def _define(self, name: str | None, value: object) -> None:
        self.statements += 1
        if name is None:
            return
        if any(name in s for s in self._scopes):
            raise ModelError(f"{name!r} is already defined")
        self._scopes[-1][name] = value

    def __getitem__(self, name: str) -> object:
        for scope in reversed(self._scopes):
            if name in scope:
                return scope[name]
        raise ModelError(f"{name!r} isn't defined")

    @contextmanager
    def scope(self) -> Iterator[None]:
        """Names defined inside are unknown outside; the variables themselves stay part of the model."""
        self._scopes.append({})
        try:
            yield
        finally:
            self._scopes.pop()

    def alias(self, name: str, value: Rv | Plate) -> Rv | Plate:
        self._define(name, value)
        if isinstance(value, Rv):
            value.names.add(name)
        return value

    def plate(self, name: str, size: object = None, lo: object = 0, inclusive: bool = False, parent: Plate | None = None) -> Plate:
        extent = None if size is None else Expr.of(size) - Expr.of(lo) + Expr.of(int(inclusive))
        made = Plate(name, extent, parent)
        self._define(name, made)
        self.plates.append(made)
        return made

    def _rv(self, name: str | None, **fields) -> Rv:
        made = Rv(f"r{len(self.rvs) + 1}", names={name} if name else set(), **fields)
        self._define(name, made)
        self.rvs.append(made)
        return made

    def dirichlet(self, name: str | None, concentration: object, dimension: object, plate: Plate | None = None) -> Rv:
        return self._rv(name, kind="dirichlet", plate=plate, concentration=Expr.of(concentration), dimension=Expr.of(dimension))

    def beta(self, name: str | None, concentration: object, plate: Plate | None = None) -> Rv:
        return self._rv(name, kind="dirichlet", plate=plate, concentration=Expr.of(concentration), dimension=Expr.of(2), beta=True)

    def categorical(self, name: str | None, probability: Rv | Indexed, plate: Plate | None = None) -> Rv:
        parent = probability if isinstance(probability, Indexed) else Indexed(probability, ())
        return self._rv(name, kind="categorical", plate=plate, parent=parent)

    def bind(self, spark, **constants):
        from ..network.instantiate import BoundModel

        return BoundModel(self, spark, constants)


def model_loc(spec: ModelSpec) -> int:
    """Statements of the model."""
    return spec.statements


def levels(rv: Rv) -> tuple[list[Plate], list[Plate]]:
    """Plates of a categorical's prior that it shares, and those its selectors pick a member of."""
    own = set(map(id, rv.chain()))
    chain = rv.parent.prior.chain()
    return [p for p in chain if id(p) in own], [p for p in chain if id(p) not in own]


def validate(spec: ModelSpec, constants: dict[str, float] | None = None) -> None:
    known = {id(r): i for i, r in enumerate(spec.rvs)}
    plates = set(map(id, spec.plates))
    for p in spec.plates:
        seen, q = set(), p
        while q is not None:
            if id(q) in seen:
                raise ModelError(f"plate {p.name!r} contains itself")
            seen.add(id(q))
            q = q.parent
    for i, rv in enumerate(spec.rvs):
        if rv.plate is not None and id(rv.plate) not in plates:
            raise ModelError(f"{rv.name!r} is in a plate of another model")
        exprs = [e for e in (rv.concentration, rv.dimension) if e is not None]
        if unknown := set().union(*(e.names() for e in exprs), set()) - set(spec.params):
            raise ModelError(f"{rv.name!r} uses undeclared constants {sorted(unknown)}")
        if constants is not None and rv.kind == "dirichlet":
            if rv.concentration.value(constants) <= 0 or rv.dimension.value(constants) < 1:
                raise ModelError(f"{rv.name!r} needs a positive concentration and a dimension of at least 1")
        if rv.kind != "categorical":
            continue
        prior, selectors = rv.parent.prior, rv.parent.selectors
        if prior.kind != "dirichlet":
            raise ModelError(f"{rv.name!r} has the prior {prior.name!r}, which isn't conjugate to it")
        for other in (prior, *selectors):
            if known.get(id(other), len(spec.rvs)) >= i:
                raise ModelError(f"{rv.name!r} depends on {other.name!r}, which isn't defined before it")
        _, picked = levels(rv)
        if len(picked) != len(selectors):
            raise ModelError(f"{rv.name!r} needs {len(picked)} selectors for {prior.name!r}, it has {len(selectors)}")
        own = set(map(id, rv.chain()))
        for plate, selector in zip(picked, selectors, strict=True):
            if selector.kind != "categorical":
                raise ModelError(f"selector {selector.name!r} isn't discrete")
            if any(id(q) not in own for q in selector.chain()):
                raise ModelError(f"selector {selector.name!r} isn't repeated with {rv.name!r}")
            if constants is not None and plate.size is not None:
                a, b = selector.parent.prior.dimension.value(constants), plate.size.value(constants)
                if a != b:
                    raise ModelError(f"{selector.name!r} has {a} values, plate {plate.name!r} has {b} members")
