"""Variational message passing compiled from the template, in the long layout.

Tables: a prior ``g`` has (plate keys, j, gamma), rows only for outcomes that data touched, all others stay at the
prior; a discrete variable has (instance columns, state, r).  For every dependency the two messages are
one join and one aggregate over plate keys, so a changed model needs no derivation of its own:

* prior to variable: the expected log-probability ``digamma(gamma_j) - digamma(sum)``;
* variable to prior: its responsibility, times those of its selectors, times its weight;
* child to selector: the expected log-probability of the child's outcome under each component.

Nothing is collected but the bound's scalars.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.special import digamma, log_gamma
from ..lang.builder import ModelError, Rv, levels
from ..runtime.loop import View, checkpointed

#: Components of at most so many numbers are replicated to all tasks, larger ones are joined by shuffle.
BROADCAST_CELLS = 4_000_000


def hashed_start(columns: list[str]) -> tuple[Column, Column]:
    """The two whole numbers whose hash breaks the symmetry of the components."""
    return F.col(columns[0]) if columns else F.lit(0), F.col(columns[1]) if len(columns) > 1 else F.lit(0)


class LongEngine:
    def __init__(self, model, init: Callable | None = None, checkpoint_every: int = 1, cache: bool = True):
        self.model, self.spec, self.spark = model, model.spec, model.spark
        self.init = init or hashed_start
        self.checkpoint_every, self.cache = checkpoint_every, cache
        with model.clock.stage("code generation"):
            self.schedule = model.schedule()
        self.latent = [z for step in self.schedule[:-1] for z in step]
        self.priors = self.schedule[-1]
        self.fixed = model.observed()
        self.base = {}
        with model.clock.stage("graph construction"):
            for name, rows in model.bases.items():
                self.base[name] = rows.persist()
                rows.count()
        self.gamma: dict[str, DataFrame] = {}
        self.r: dict[str, DataFrame] = {}
        self.history: list[tuple[int, float, float]] = []
        self.bound: DataFrame | None = None
        self._expected: dict[str, DataFrame] = {}

    # Columns and rows of plates.

    def keys(self, g: Rv) -> list[str]:
        return [p.name for p in g.chain()]

    def instance_columns(self, z: Rv) -> list[str]:
        if z.plate is None:
            return []
        name, outer = z.plate.name, [p.name for p in z.plate.chain()[:-1]]
        if name not in self.base:
            return [*outer, name]
        values = [v for v in self.model.values[name] if v not in self.model.partial]
        return [*outer, name] if self.model.own_key[name] else [*outer, *values]

    def instances(self, z: Rv) -> DataFrame:
        """Rows of a variable's plate with weights; of a plate without data, those that plates inside it name."""
        if z.plate is None:
            return self.spark.range(1).select(F.lit(1.0).alias("n"))
        if z.plate.name in self.base:
            return self.base[z.plate.name]
        columns = [p.name for p in z.plate.chain()]
        inside = [self.base[n].select(*columns) for n in self.base if any(p is z.plate for p in self.model.plate(n).chain())]
        return reduce(DataFrame.union, inside).distinct().withColumn("n", F.lit(1.0))

    def constants(self, g: Rv) -> tuple[float, int]:
        return float(g.concentration.value(self.model.env)), int(g.dimension.value(self.model.env))

    def expected(self, g: Rv) -> DataFrame:
        """(keys, j, el) of a prior for the outcomes it has rows for."""
        if g.rid not in self._expected:
            prior, dim = self.constants(g)
            keys = self.keys(g)
            totals = self.gamma[g.rid].groupBy(*keys).agg((F.sum("gamma") + (dim - F.count("*")) * prior).alias("total"))
            joined = self.gamma[g.rid].join(totals, keys) if keys else self.gamma[g.rid].crossJoin(F.broadcast(totals))
            self._expected[g.rid] = joined.select(*keys, "j", (digamma(F.col("gamma")) - digamma(F.col("total"))).alias("el"))
        return self._expected[g.rid]

    def _joined(self, rows: DataFrame, right: DataFrame, on: list[str], small: bool = False) -> DataFrame:
        right = F.broadcast(right) if small else right
        return rows.join(right, on) if on else rows.crossJoin(right)

    def _small(self, g: Rv) -> bool:
        """Whether a prior's table has a bounded size: no plate whose size the data decides."""
        _, dim = self.constants(g)
        cells = dim
        for p in g.chain():
            if p.size is None:
                return False
            cells *= int(p.size.value(self.model.env))
        return cells <= BROADCAST_CELLS

    def _picked(self, rows: DataFrame, c: Rv, skip: Rv | None = None) -> DataFrame:
        """Level columns of the components that c's selectors pick, and ``w``, the product of their probabilities."""
        _, picked = levels(c)
        rows = rows.withColumn("w", F.lit(1.0))
        for level, s in zip(picked, c.parent.selectors, strict=True):
            if s is skip:
                continue
            if s.rid in self.fixed:
                if s.name not in rows.columns:
                    rows = rows.join(self.base[s.plate.name].select(*self.instance_columns(s), s.name), self.instance_columns(s))
                rows = rows.withColumn(level.name, F.col(s.name))
            else:
                got = self.r[s.rid].select(*self.instance_columns(s), F.col("state").alias(level.name), F.col("r").alias("w_s"))
                rows = self._joined(rows, got, self.instance_columns(s)).withColumn("w", F.col("w") * F.col("w_s")).drop("w_s")
        return rows

    # The two kinds of update.

    def scores(self, z: Rv) -> DataFrame:
        """(instance columns, state, s): what the parent and the children say."""
        own = self.instance_columns(z)
        shared, picked = levels(z)
        rows = self._picked(self.instances(z).select(*own), z)
        g = z.parent.prior
        on = [p.name for p in [*shared, *picked]]
        terms = [self._joined(rows, self.expected(g), on, self._small(g)).select(*own, F.col("j").alias("state"), (F.col("w") * F.col("el")).alias("s"))]
        for c in self.model.template.children[z.rid]:
            if z not in c.parent.selectors:
                continue
            shared, picked = levels(c)
            level = next(p.name for p, s in zip(picked, c.parent.selectors, strict=True) if s is z)
            rows = self._picked(self.instances(c), c, skip=z)
            on = [p.name for p in [*shared, *picked] if p.name != level]
            h = c.parent.prior
            if c.rid in self.fixed:
                rows, el = rows.withColumn("j", F.col(c.name)), self.expected(h)
            else:
                rows = rows.join(self.r[c.rid].select(*self.instance_columns(c), F.col("state").alias("j"), F.col("r").alias("w_c")), self.instance_columns(c))
                rows, el = rows.withColumn("w", F.col("w") * F.col("w_c")), self.expected(h)
            times = F.lit(1.0) if c.plate is z.plate else F.col("n")
            joined = self._joined(rows, el, [*on, "j"], self._small(h))
            terms.append(joined.select(*own, F.col(level).cast("long").alias("state"), (times * F.col("w") * F.col("el")).alias("s")))
        return reduce(DataFrame.union, terms).groupBy(*own, "state").agg(F.sum("s").alias("s"))

    def update_latent(self, z: Rv) -> DataFrame:
        own = self.instance_columns(z)
        over = Window.partitionBy(*own) if own else Window.partitionBy(F.lit(0))
        s = self.scores(z).withColumn("top", F.max("s").over(over)).withColumn("e", F.exp(F.col("s") - F.col("top"))).withColumn("z", F.sum("e").over(over))
        found = s.select(*own, "state", (F.col("e") / F.col("z")).alias("r"), (F.col("top") + F.log("z")).alias("lse"))
        return self._given(z, found)

    def _given(self, z: Rv, found: DataFrame) -> DataFrame:
        """Weights, and for a partly observed variable the outcomes that are known."""
        own = self.instance_columns(z)
        rows = self.instances(z)
        found = rows.select(*own, *([z.name] if z.name in self.model.partial else []), "n").join(found, own) if own else found.crossJoin(rows)
        if z.name in self.model.partial:
            known = F.when(F.col(z.name).isNull(), F.col("r")).otherwise((F.col("state") == F.col(z.name)).cast("double"))
            found = found.withColumn("r", known).drop(z.name)
        return found

    def start_latent(self, z: Rv) -> DataFrame:
        own = self.instance_columns(z)
        a, b = self.init(own)
        _, dim = self.constants(z.parent.prior)
        rows = self.instances(z).select(*own).crossJoin(F.broadcast(self.spark.range(dim).withColumnRenamed("id", "state")))
        u = (1 + F.pmod(31 * a + 17 * b + 7 * F.col("state"), F.lit(13))).cast("double")
        over = Window.partitionBy(*own) if own else Window.partitionBy(F.lit(0))
        return self._given(z, rows.withColumn("u", u).select(*own, "state", (F.col("u") / F.sum("u").over(over)).alias("r"), F.lit(0.0).alias("lse")))

    def update_prior(self, g: Rv) -> DataFrame:
        prior, _ = self.constants(g)
        keys = self.keys(g)
        sums = []
        for c in self.model.template.children[g.rid]:
            if c.parent.prior is not g:
                continue
            rows = self._picked(self.instances(c), c)
            if c.rid in self.fixed:
                rows = rows.withColumn("j", F.col(c.name))
            else:
                got = self.r[c.rid].select(*self.instance_columns(c), F.col("state").alias("j"), F.col("r").alias("w_c"))
                rows = self._joined(rows, got, self.instance_columns(c)).withColumn("w", F.col("w") * F.col("w_c"))
            sums.append(rows.select(*[F.col(k).cast("long").alias(k) for k in keys], F.col("j").cast("long").alias("j"), (F.col("n") * F.col("w")).alias("m")))
        if not sums:
            raise ModelError(f"{g.name!r} has no variable that depends on it")
        return reduce(DataFrame.union, sums).groupBy(*keys, "j").agg((prior + F.sum("m")).alias("gamma"))

    # Rounds.

    def _kept(self, df: DataFrame, round_: int, state: bool) -> DataFrame:
        """State that the next round builds on is checkpointed: each table is read more than once, so a plan over
        several rounds would grow as a tree.  What one round uses up is only cached for it."""
        if state and self.checkpoint_every and round_ % self.checkpoint_every == 0:
            return checkpointed(df)
        if not self.cache:
            return df
        df = df.persist()
        df.count()
        return df

    def _replace(self, table: dict[str, DataFrame], key: str, new: DataFrame) -> None:
        old = table.get(key)
        table[key] = new
        if old is not None and self.cache:
            old.unpersist()

    def run(self, steps: int, callback: Callable | None) -> None:
        with self.model.clock.stage("inference"):
            began = time.perf_counter()
            for z in self.latent:
                self.r[z.rid] = self._kept(self.start_latent(z), 0, not self.single_layer())
            self._update_priors(0)
            if callback and callback(View(self.model, 0)) is False:
                return
            for t in range(1, steps + 1):
                for step in self.schedule[:-1]:
                    for z, new in [(z, self._kept(self.update_latent(z), t, not self.single_layer())) for z in step]:
                        self._replace(self.r, z.rid, new)
                self.bound = self._bound()
                if callback:  # before the priors that entered it are replaced
                    self.bound = self.spark.createDataFrame([tuple(self.bound.first())], "elbo double")
                self._update_priors(t)
                self.history.append((t, self.lower_bound() if callback else float("nan"), time.perf_counter() - began))
                if callback and callback(View(self.model, t)) is False:
                    return

    def _update_priors(self, t: int) -> None:
        news = [(g, self._kept(self.update_prior(g), t, True)) for g in self.priors]
        for g, new in news:
            self.gamma[g.rid] = new
        self._expected = {}

    # The bound.

    def kl(self, g: Rv) -> DataFrame:
        """KL divergence of every posterior of g from its prior; outcomes at the prior add nothing."""
        prior, dim = self.constants(g)
        keys = self.keys(g)
        t = self.gamma[g.rid].join(self.expected(g), [*keys, "j"])
        per = t.groupBy(*keys).agg(
            (F.sum("gamma") + (dim - F.count("*")) * prior).alias("total"),
            F.sum(log_gamma(F.lit(prior)) - log_gamma(F.col("gamma")) + (F.col("gamma") - prior) * F.col("el")).alias("rest"),
        )
        return per.select(*keys, (log_gamma(F.col("total")) - log_gamma(F.lit(prior * dim)) + F.col("rest")).alias("kl"))

    def single_layer(self) -> bool:
        return len(self.latent) == 1 and not any(z.name in self.model.partial for z in self.latent)

    def _bound(self) -> DataFrame:
        return self.fused_bound() if self.single_layer() else self.elbo_terms().agg(F.sum("value").alias("elbo"))

    def fused_bound(self) -> DataFrame:
        """One row: sum of log-normalisers of the latest scores less the divergences of the priors that made them."""
        z = self.latent[0]
        own = self.instance_columns(z)
        logs = self.r[z.rid].groupBy(*own, "n").agg(F.first("lse").alias("lse")).agg(F.coalesce(F.sum(F.col("n") * F.col("lse")), F.lit(0.0)).alias("v"))
        parts = [logs, *[self.kl(g).agg((-F.coalesce(F.sum("kl"), F.lit(0.0))).alias("v")) for g in self.priors]]
        return reduce(DataFrame.union, parts).agg(F.sum("v").alias("elbo"))

    def elbo_terms(self) -> DataFrame:
        """``rv, term, value``: expected log-probabilities, entropies and prior divergences, added up anew."""
        parts = []
        for c in (r for r in self.spec.rvs if r.kind == "categorical"):
            shared, picked = levels(c)
            h = c.parent.prior
            rows = self._picked(self.instances(c), c)
            if c.rid in self.fixed:
                rows = rows.withColumn("j", F.col(c.name))
            else:
                got = self.r[c.rid].select(*self.instance_columns(c), F.col("state").alias("j"), F.col("r").alias("w_c"))
                rows = self._joined(rows, got, self.instance_columns(c)).withColumn("w", F.col("w") * F.col("w_c"))
            el = self._joined(rows, self.expected(h), [*[p.name for p in [*shared, *picked]], "j"], self._small(h))
            parts.append(el.agg(F.coalesce(F.sum(F.col("n") * F.col("w") * F.col("el")), F.lit(0.0)).alias("value")).select(F.lit(c.name).alias("rv"), F.lit("expected log-probability").alias("term"), "value"))
            if c.rid not in self.fixed:
                entropy = F.sum(F.when(F.col("r") > 0, -F.col("n") * F.col("r") * F.log("r")).otherwise(0.0))
                parts.append(self.r[c.rid].agg(F.coalesce(entropy, F.lit(0.0)).alias("value")).select(F.lit(c.name).alias("rv"), F.lit("entropy").alias("term"), "value"))
        for g in self.priors:
            parts.append(self.kl(g).agg((-F.coalesce(F.sum("kl"), F.lit(0.0))).alias("value")).select(F.lit(g.name).alias("rv"), F.lit("minus divergence").alias("term"), "value"))
        return reduce(DataFrame.union, parts)

    def lower_bound(self) -> float:
        if self.bound is None:
            return float("-inf")
        return float(self.bound.first()["elbo"])

    # Results.

    def posterior(self, v: Rv, dense: bool = False) -> DataFrame:
        if v.kind == "categorical":
            return self.r[v.rid].drop("lse") if v.rid in self.r else self.instances(v)
        prior, dim = self.constants(v)
        keys = self.keys(v)
        got = self.gamma[v.rid]
        if dense:
            groups = got.select(*keys).distinct() if keys else self.spark.range(1).select()
            index = groups.crossJoin(F.broadcast(self.spark.range(dim).withColumnRenamed("id", "j")))
            got = index.join(got, [*keys, "j"], "left").select(*keys, "j", F.coalesce("gamma", F.lit(prior)).alias("gamma"))
            total = F.sum("gamma")
        else:
            total = F.sum("gamma") + (dim - F.count("*")) * prior
        totals = got.groupBy(*keys).agg(total.alias("total"))
        joined = got.join(totals, keys) if keys else got.crossJoin(F.broadcast(totals))
        return joined.select(*keys, "j", "gamma", (F.col("gamma") / F.col("total")).alias("mean"))
