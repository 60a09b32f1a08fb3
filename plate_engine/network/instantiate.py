"""Binding: constants, observations and plate sizes turn a spec into a model that can be inferred."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..lang.builder import ModelError, ModelSpec, Plate, Rv, validate
from ..runtime.timing import Stopwatch
from .template import build_template, make_schedule

WHOLE = ("tinyint", "smallint", "int", "bigint")


#: From so many components on the block layout is chosen.
BLOCK_TOPICS = 16


class Handle:
    """What a user does with one variable: ``model["x"].observe(...)``, ``model["phi"].posterior()``."""

    def __init__(self, model: BoundModel, rv: Rv):
        self.model, self.rv = model, rv

    def observe(self, df: DataFrame, value: str, keys: dict[str, str] | None = None, weight: str | None = None) -> None:
        self.model.observe(self.rv.plate.name, df, {self.rv.name: value}, keys, weight)

    def posterior(self, dense: bool = False) -> DataFrame:
        return self.model.posterior(self.rv.name, dense)

    def mean(self) -> DataFrame:
        return self.posterior().drop("gamma") if self.rv.kind == "dirichlet" else self.posterior()

    def mode(self) -> DataFrame:
        """The likeliest outcome of every instance, the lowest of equals."""
        found = self.posterior()
        value, by = ("mean", "j") if self.rv.kind == "dirichlet" else ("r", "state")
        keys = [c for c in found.columns if c not in ("j", "state", "gamma", "mean", "r", "n")]
        best = F.max(F.struct(F.col(value), (-F.col(by)).alias("k")))
        return found.groupBy(*keys).agg((-best["k"]).alias("mode"))


class BoundModel:
    def __init__(self, spec: ModelSpec, spark: SparkSession, constants: dict[str, float]):
        self.clock = Stopwatch()
        with self.clock.stage("network construction"):
            missing = set(spec.params) - set(constants)
            if missing or set(constants) - set(spec.params):
                raise ModelError(f"constants missing {sorted(missing)} or unknown {sorted(set(constants) - set(spec.params))}")
            for name, kind in spec.params.items():
                if isinstance(constants[name], bool) or not isinstance(constants[name], int if kind is int else int | float):
                    raise ModelError(f"constant {name!r} must be {'long' if kind is int else 'double'}")
            self.spec, self.spark, self.env = spec, spark, dict(constants)
            validate(spec, self.env)
            self.template = build_template(spec)
        self.bases: dict[str, DataFrame] = {}
        self.packed: dict[str, DataFrame] = {}
        self.own_key: dict[str, bool] = {}
        self.values: dict[str, list[str]] = {}
        self.sizes: dict[str, int] = {p.name: int(p.size.value(self.env)) for p in spec.plates if p.size is not None}
        self.partial: set[str] = set()
        self.engine = None

    def rv(self, name: str) -> Rv:
        for r in self.spec.rvs:
            if name in r.names or name == r.rid:
                return r
        raise ModelError(f"the model has no variable {name!r}")

    def plate(self, name: str) -> Plate:
        for p in self.spec.plates:
            if p.name == name:
                return p
        raise ModelError(f"the model has no plate {name!r}")

    def __getitem__(self, name: str) -> Handle:
        return Handle(self, self.rv(name))

    def observe(self, plate: str, df: DataFrame, values: dict[str, str], keys: dict[str, str] | None = None, weight: str | None = None, partial: bool = False) -> None:
        """Attach outcomes of the variables of one plate.

        ``keys`` names the columns of the plate's ancestors, and of the plate itself where its members differ by
        more than their outcomes; else equal outcomes are one member with a weight (they share their posterior).
        Rows without an outcome say nothing and are left out, unless ``partial``: then they are latent.
        """
        p, keys = self.plate(plate), dict(keys or {})
        outer = [q.name for q in p.chain()[:-1]]
        if lost := [q for q in outer if q not in keys]:
            raise ModelError(f"plate {plate!r} needs key columns for {lost}")
        kinds = dict(df.dtypes)
        for c in values.values():
            if kinds[c] not in WHOLE:
                raise ModelError(f"outcomes must be whole numbers, {c!r} is {kinds[c]}")
        for v in values:
            if self.rv(v).plate is not p:
                raise ModelError(f"{v!r} isn't in plate {plate!r}")
        own = plate in keys
        n = F.coalesce(F.col(weight).cast("double"), F.lit(0.0)) if weight else F.lit(1.0)
        columns = [F.col(keys[q]).alias(q) for q in [*outer, *([plate] if own else [])]] + [F.col(c).cast("long").alias(v) for v, c in values.items()]
        rows = df.select(*columns, n.alias("n")).filter("n > 0").dropna(subset=[*outer, *([] if partial else values)])
        if partial:
            self.partial |= set(values)
        self.own_key[plate], self.values[plate] = own, list(values)
        names = [c for c in rows.columns if c != "n"]
        self.bases[plate] = rows.groupBy(*names).agg(F.sum("n").alias("n"))

    def observe_packed(self, value: str, blocks: DataFrame) -> None:
        """Attach the outcomes of a variable as blocks of whole documents (``plans.blocks.pack_texts``), which a topic
        model runs on as they are; for any other use they are unpacked."""
        from ..plans.blocks import unpacked

        p = self.rv(value).plate
        self.own_key[p.name], self.values[p.name], self.packed[p.name] = False, [value], blocks
        self.bases[p.name] = unpacked(blocks, [*[q.name for q in p.chain()[:-1]], value])

    def set_size(self, plate: str, n: int) -> None:
        self.sizes[self.plate(plate).name] = int(n)

    def infer_plate_sizes(self) -> dict[str, int]:
        """Flattened sizes of the observed plates and the plates around them."""
        for name, base in self.bases.items():
            self.sizes[name] = int(base.agg(F.sum("n")).first()[0] or 0)
            for q in self.plate(name).chain()[:-1]:
                if q.name not in self.sizes:
                    self.sizes[q.name] = base.select(*[x.name for x in q.chain()]).distinct().count()
        return self.sizes

    def plate_sizes(self, plate: str) -> DataFrame:
        """Number of members of a nested plate within each member of its parent."""
        p = self.plate(plate)
        return self.bases[plate].groupBy(*[q.name for q in p.chain()[:-1]]).agg(F.sum("n").alias("size"))

    def check_ready(self) -> None:
        if not self.bases:
            raise ModelError("nothing is observed")
        covered = {q.name for name in self.bases for q in self.plate(name).chain()}
        for r in self.spec.rvs:
            if r.kind == "categorical" and r.plate is not None and r.plate.name not in covered:
                raise ModelError(f"the size of plate {r.plate.name!r} of {r.name!r} is unknown: observe it or a plate inside it")

    def observed(self) -> set[str]:
        return {self.rv(v).rid for vs in self.values.values() for v in vs if v not in self.partial}

    def schedule(self) -> list[list[Rv]]:
        return make_schedule(self.template, self.observed())

    def infer(self, steps: int, callback: Callable | None = None, checkpoint_every: int = 1, init: Callable[[list[str]], tuple[Column, Column]] | None = None, cache: bool = True, layout: str = "auto") -> BoundModel:
        """Run the rounds.  ``layout``: ``long`` (any model), ``block`` (topic models whose components fit on a worker), or
        ``auto``: the block layout for such models with ``BLOCK_TOPICS`` components or more, where it is the faster one,
        and for all whose outcomes came packed: responsibilities as rows take many times the disk."""
        from ..plans.blocks import BlockEngine, BurstyEngine, fits, roles
        from ..vmp.engine import LongEngine

        self.check_ready()
        found = roles(self) if layout != "long" and init is None else None
        if found:
            size, topics = (int(g.dimension.value(self.env)) for g in (found.phi, found.theta))
            if layout == "auto" and not ((topics >= BLOCK_TOPICS or self.packed) and (found.bursty or fits(size, topics))):
                found = None
        elif layout == "block":
            raise ModelError("the block layout runs topic models only, from their standard start")
        self.engine = (BurstyEngine if found.bursty else BlockEngine)(self, found) if found else LongEngine(self, init, checkpoint_every, cache)
        self.engine.run(steps, callback)
        return self

    def posterior(self, name: str, dense: bool = False) -> DataFrame:
        if self.engine is None:
            raise ModelError("infer() comes first")
        return self.engine.posterior(self.rv(name), dense)

    def lower_bound(self) -> float:
        return self.engine.lower_bound()

    def history(self) -> DataFrame:
        return self.spark.createDataFrame(self.engine.history, "iter int, elbo double, seconds double")

    def timings(self) -> DataFrame:
        return self.clock.table(self.spark)
