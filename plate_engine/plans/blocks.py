"""The block layout: document ranges as numpy blocks, for many topics.

The corpus is packed once into blocks of whole documents (the tailored placement: a document's variables never
leave their block).  A round is one pass over the blocks with the components' expected logs replicated, if their
size allows; every block returns its new document state and its sums for the outcomes it holds, cut by ranges of
outcomes.  One shuffle brings a range together, where its parts are added up one by one.  Responsibilities live for a slice of a
block only.  Models without a shared component run all rounds inside the block, with no shuffle at all.

What a round makes is written as a table in the shared folder and read by the next, which cuts the lineage; the
table before the last is deleted.  A block's words travel with its document state, so no round joins or shuffles the
corpus.  ``BlockEngine`` and ``BurstyEngine`` run a bound model of these shapes (see ``roles``).
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.special import digamma_np, log_gamma_np
from ..lang.builder import ModelError, Rv
from ..runtime.loop import Scratch, View
from ..runtime.timing import Stopwatch
from ..sources.text import flat_words, word_units

#: Replicated components may take so many bytes; beyond, use the long layout (its join is by outcome).
BROADCAST_BYTES = 1 << 30
SLICE = 1 << 15
#: Rows of a block that texts are packed into; a longer document is a block by itself.
BLOCK_ROWS = 1 << 18
#: A task adds its blocks' sums up itself if the components have at most so many cells.
TASK_CELLS = 8_000_000
#: Vocabularies of at most so many words are held by every task that packs texts.
HELD_WORDS = 1_000_000
PACKED = "block long, d binary, s binary, w binary, n binary"


def fits(v: int, k: int) -> bool:
    return v * k * 8 <= BROADCAST_BYTES


def _pack(*arrays: np.ndarray) -> list[bytes]:
    """Length and compressed bytes of each array, since the JVM holds many rows at once."""
    return [len(raw := np.ascontiguousarray(a).tobytes()).to_bytes(8, "little") + pa.compress(raw, "zstd", asbytes=True) for a in arrays]


def _array(data: bytes, kind: type) -> np.ndarray:
    return np.frombuffer(pa.decompress(data[8:], int.from_bytes(data[:8], "little"), "zstd"), kind)


def pack_corpus(tokens: DataFrame, blocks: int, sentences: bool = False) -> DataFrame:
    """``block, d, s, w, n`` (binary arrays): whole documents per block, rows sorted by document (and sentence).

    ``tokens`` has d, w, n (and s).  Documents are dealt by hash, so equal load is a matter of many documents.
    """
    columns = ["d", "s", "w", "n"] if sentences else ["d", "w", "n"]
    rows = tokens.select(*[F.col(c).cast("long").alias(c) for c in columns], F.pmod(F.xxhash64("d"), F.lit(blocks)).alias("block"))

    def pack(key: tuple, table: pa.Table) -> pa.Table:
        got = {c: table.column(c).to_numpy() for c in columns}
        s = got.get("s", np.arange(table.num_rows))
        order = np.lexsort((got["w"], s, got["d"])) if sentences else np.lexsort((got["w"], got["d"]))
        data = _pack(got["d"][order], s[order] if sentences else np.zeros(0, np.int64), got["w"][order].astype(np.int32), got["n"][order].astype(np.float32))
        return pa.table({"block": [key[0].as_py()], "d": [data[0]], "s": [data[1]], "w": [data[2]], "n": [data[3]]})

    return rows.groupBy("block").applyInArrow(pack, PACKED)


def pack_texts(docs: DataFrame, key: str, vocab: DataFrame, sentences: bool = False) -> DataFrame:
    """The same blocks straight from texts and a vocabulary (w, word) of at most ``HELD_WORDS``, without a shuffle of words.

    Every task counts whole documents, so only rows that share an id meet in a shuffle (see ``word_units``).
    """
    got = vocab.select("w", "word").toArrow()  # bounded above
    size = got.num_rows
    words = got.column("word").combine_chunks() if size else pa.array([], pa.string())
    held = docs.sparkSession.sparkContext.broadcast((words.cast(pa.string()), got.column("w").to_numpy()))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        word_list, number = held.value
        made, part = 0, TaskContext.get().partitionId()
        for batch in batches:
            doc, s, coded = flat_words(batch)
            ids, rank = np.unique(batch.column(0).to_numpy(), return_inverse=True)
            at = pc.fill_null(pc.index_in(coded.dictionary, value_set=word_list), -1).to_numpy()
            w = np.where(at >= 0, number[at], -1)[coded.indices.to_numpy()] if size else np.full(len(doc), -1)
            known = w >= 0
            doc, s, w = rank[doc[known]], s[known], w[known]
            span = int(s.max()) + 1 if len(s) else 1
            cell, n = np.unique((doc * span + s) * size + w, return_counts=True)
            unit, w = cell // max(size, 1), cell % max(size, 1)
            doc, s = unit // span, unit % span
            ends = np.append(np.flatnonzero(doc[1:] != doc[:-1]) + 1, len(doc)) if len(doc) else doc
            a = 0
            while a < len(doc):
                b = int(ends[max(np.searchsorted(ends, a + BLOCK_ROWS, side="right") - 1, np.searchsorted(ends, a, side="right"))])
                data = _pack(ids[doc[a:b]].astype(np.int64), s[a:b] if sentences else np.zeros(0, np.int64), w[a:b].astype(np.int32), n[a:b].astype(np.float32))
                yield pa.RecordBatch.from_pydict({"block": [(part << 32) + made], **{c: [x] for c, x in zip("dswn", data, strict=True)}})
                made, a = made + 1, b

    return word_units(docs.filter(F.col(key).isNotNull()), key, sentences=sentences).mapInArrow(pack, PACKED)


def unpacked(blocks: DataFrame, names: list[str]) -> DataFrame:
    """The rows of blocks: ``names`` (document, the sentence if they are three, outcome) and ``n``."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            got = [_array(row["d"], np.int64), *([_array(row["s"], np.int64)] if len(names) > 2 else []), _array(row["w"], np.int32).astype(np.int64), _array(row["n"], np.float32).astype(np.float64)]
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in got], [*names, "n"])

    return blocks.mapInArrow(rows, ", ".join(f"{c} long" for c in names) + ", n double")


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    """Row by row, since each is large."""
    for batch in batches:
        for i in range(batch.num_rows):
            yield {c: batch.column(c)[i].as_py() for c in batch.schema.names}


@dataclass
class _Corpus:
    docs: np.ndarray
    doc: np.ndarray
    unit: np.ndarray
    unit_doc: np.ndarray
    unit_first: np.ndarray
    w: np.ndarray
    n: np.ndarray
    place: np.ndarray

    @classmethod
    def of(cls, row: dict) -> _Corpus:
        d = _array(row["d"], np.int64)
        s = _array(row["s"], np.int64)
        docs, doc = np.unique(d, return_inverse=True)
        new = np.ones(len(d), bool)
        place = np.zeros(len(d), np.int64)
        if len(s):
            new[1:] = (d[1:] != d[:-1]) | (s[1:] != s[:-1])
            place = s
        first = np.flatnonzero(new)
        return cls(docs, doc, np.cumsum(new) - 1, doc[first], first, _array(row["w"], np.int32).astype(np.int64), _array(row["n"], np.float32).astype(np.float64), place[first] if len(s) else _array(row["w"], np.int32).astype(np.int64))


def _start(c: _Corpus, a: int, b: int, k: int) -> np.ndarray:
    u = 1.0 + (31 * c.docs[c.unit_doc[a:b], None] + 17 * c.place[a:b, None] + 7 * np.arange(k)) % 13
    return u / u.sum(1, keepdims=True)


def _softmax(s: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    top = s.max(axis=1, keepdims=True)
    e = np.exp(s - top)
    z = e.sum(axis=1, keepdims=True)
    return e / z, (top + np.log(z))[:, 0]


def _expected(gamma: np.ndarray) -> np.ndarray:
    return digamma_np(gamma) - digamma_np(gamma.sum(axis=1))[:, None]


def _kl_rows(gamma: np.ndarray, prior: float) -> float:
    k = gamma.shape[1]
    total = gamma.sum(axis=1)
    lg = lambda x: float(log_gamma_np(np.array([x]))[0])
    return float((log_gamma_np(total) - lg(prior * k) + k * lg(prior) - log_gamma_np(gamma).sum(1) + ((gamma - prior) * _expected(gamma)).sum(1)).sum())


class BlockTopics:
    """LDA and, with sentences, the model of one topic a sentence."""

    def __init__(self, tokens: DataFrame, k: int, v: int, alpha: float, beta: float, blocks: int, sentences: bool = False, clock: Stopwatch | None = None, packed: DataFrame | None = None):
        if not fits(v, k):
            raise ValueError(f"{v} x {k} components don't fit in {BROADCAST_BYTES} bytes; use the long layout")
        self.spark, self.k, self.v, self.alpha, self.beta = tokens.sparkSession, k, v, alpha, beta
        self.sentences, self.folder = sentences, Scratch(tokens.sparkSession)
        self.clock = clock or Stopwatch()
        self.ranges = max(1, min(64, v * k // 200_000))
        with self.clock.stage("graph construction"):
            self.corpus = self.folder.table(packed if packed is not None else pack_corpus(tokens, blocks, sentences), "corpus")
        self.phi = np.zeros((v, k))
        self.theta: DataFrame | None = None
        self.history: list[tuple[int, float, float]] = []

    def _round(self, held, first: bool):
        k, v, alpha, ranges, sentences = self.k, self.v, self.alpha, self.ranges, self.sentences
        step = -(-v // ranges)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            added = np.zeros((v, k)) if v * k <= TASK_CELLS else None
            met = np.zeros(v, bool)
            for row in _rows(batches):
                c = _Corpus.of(row)
                theta = np.full((len(c.docs), k), alpha)
                e_theta = None if first else _expected(np.frombuffer(row["theta"], np.float64).reshape(-1, k))
                e_phi = None if first else held.value
                held_words, word_at = np.unique(c.w, return_inverse=True)
                sums, logs = np.zeros((len(held_words), k)), 0.0
                units = len(c.unit_doc)
                edges = np.append(c.unit_first, len(c.w))
                for a in range(0, units, SLICE):
                    b = min(units, a + SLICE)
                    lo, hi = edges[a], edges[b]
                    if first:
                        r = _start(c, a, b, k)
                    else:
                        s = e_theta[c.unit_doc[a:b]]
                        if sentences:
                            s = s + np.add.reduceat(c.n[lo:hi, None] * e_phi[c.w[lo:hi]], c.unit_first[a:b] - lo, axis=0)
                        else:
                            s = s + e_phi[c.w[lo:hi]]
                        r, lse = _softmax(s)
                        logs += float(lse.sum() if sentences else (c.n[lo:hi] * lse).sum())
                    m = r if sentences else c.n[lo:hi, None] * r
                    own = c.unit_doc[a:b]
                    starts = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]]))
                    theta[own[starts]] += np.add.reduceat(m, starts, axis=0)
                    token = c.n[lo:hi, None] * r[c.unit[lo:hi] - a] if sentences else m
                    order = np.argsort(word_at[lo:hi], kind="stable")
                    w = word_at[lo:hi][order]
                    starts = np.flatnonzero(np.concatenate([[True], w[1:] != w[:-1]]))
                    sums[w[starts]] += np.add.reduceat(token[order], starts, axis=0)
                minus = 0.0 if first else _kl_rows(np.frombuffer(row["theta"], np.float64).reshape(-1, k), alpha)
                yield one("theta", row["block"], theta.tobytes(), logs - minus, row)
                if added is None:
                    yield from parts(held_words, sums)
                else:
                    added[held_words] += sums
                    met[held_words] = True
            if met.any():
                held_words = np.flatnonzero(met)
                yield from parts(held_words, added[held_words])

        def parts(words: np.ndarray, sums: np.ndarray) -> Iterator[pa.RecordBatch]:
            cuts = np.searchsorted(words, np.arange(ranges + 1) * step)
            for p, (lo, hi) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
                if hi > lo:
                    yield one("phi", p, (words[lo:hi] - p * step).astype("<i8").tobytes() + sums[lo:hi].tobytes(), 0.0, {})

        def one(kind: str, at: int, data: bytes, value: float, row: dict) -> pa.RecordBatch:
            binary = {c: pa.array([row.get(c)], pa.binary()) for c in "dswn"}
            return pa.RecordBatch.from_pydict({"kind": pa.array([kind]), "at": pa.array([at], pa.int64()), "data": pa.array([data], pa.binary()), "value": pa.array([value], pa.float64()), **binary})

        return run

    def _pass(self, t: int) -> float:
        first, k = t == 0, self.k
        step = -(-self.v // self.ranges)
        held = None if first else self.spark.sparkContext.broadcast(_expected(self.phi.T).T.copy())
        rows = self.corpus if first else self.theta
        out = self.folder.table(rows.mapInArrow(self._round(held, first), "kind string, at long, data binary, value double, d binary, s binary, w binary, n binary"), "round")
        bound = out.filter("kind = 'theta'").agg(F.sum("value")).first()[0] or 0.0

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            """The parts of a range, which follow one another, added up."""
            at, total = None, np.zeros((step, k))
            for batch in batches:
                for p, data in zip(batch.column("at").to_pylist(), batch.column("data"), strict=True):
                    if p != at and at is not None:
                        yield pa.RecordBatch.from_pydict({"at": [at], "data": [total.tobytes()]})
                        total[:] = 0.0
                    at = p
                    raw = data.as_buffer()
                    n = raw.size // (8 + 8 * k)
                    total[np.frombuffer(raw, "<i8", n)] += np.frombuffer(raw, "<f8", n * k, 8 * n).reshape(n, k)
            if at is not None:
                yield pa.RecordBatch.from_pydict({"at": [at], "data": [total.tobytes()]})

        parts = out.filter("kind = 'phi'").select("at", "data").repartition("at").sortWithinPartitions("at")
        sums = parts.mapInArrow(add, "at long, data binary").toArrow()  # V x K numbers, bounded above
        minus = 0.0 if first else _kl_phi(self.phi, self.beta)
        self.phi = np.full((self.ranges * step, k), self.beta)
        for p, data in zip(sums.column("at").to_pylist(), sums.column("data").to_pylist(), strict=True):
            self.phi[p * step : (p + 1) * step] += np.frombuffer(data, "<f8").reshape(step, k)
        self.phi = self.phi[: self.v]
        self.theta = out.filter("kind = 'theta'").select(F.col("at").alias("block"), F.col("data").alias("theta"), "d", "s", "w", "n")
        self.folder.forget("round", keep=1)
        self.folder.forget("corpus")  # the round's table has it
        if held is not None:
            held.destroy()
        return bound - minus

    def infer(self, steps: int, callback: Callable | None = None) -> BlockTopics:
        """``steps`` rounds after the start; ``callback`` gets the history and ends the rounds by False."""
        with self.clock.stage("inference"):
            began = time.perf_counter()
            self._pass(0)
            if callback and callback(self.history) is False:
                return self
            for t in range(1, steps + 1):
                bound = self._pass(t)
                self.history.append((t, bound, time.perf_counter() - began))
                if callback and callback(self.history) is False:
                    break
        return self

    def topics(self, dense: bool = True) -> DataFrame:
        """``topics, j, gamma`` of the components; unless ``dense``, of the outcomes that data touched."""
        held = np.arange(self.v) if dense else np.flatnonzero((self.phi > self.beta).any(axis=1))
        rows = pa.table({"topics": np.tile(np.arange(self.k), len(held)), "j": np.repeat(held, self.k), "gamma": self.phi[held].ravel()})
        return self.spark.createDataFrame(rows).withColumn("total", F.element_at(F.array(*[F.lit(float(x)) for x in self.phi.sum(axis=0)]), F.col("topics").cast("int") + 1))

    def proportions(self) -> DataFrame:
        """``docs, j, gamma`` of the documents."""
        k = self.k

        def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for row in _rows(batches):
                docs = np.unique(_array(row["d"], np.int64))
                gamma = np.frombuffer(row["theta"], np.float64)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(docs, k)), pa.array(np.tile(np.arange(k), len(docs))), pa.array(gamma)], ["docs", "j", "gamma"])

        return self.theta.select("d", "theta").mapInArrow(listed, "docs long, j long, gamma double")


@dataclass
class Roles:
    """The variables of a topic model: components, proportions of the documents, topics, outcomes."""

    phi: Rv
    theta: Rv
    z: Rv
    x: Rv
    #: Every document has components of its own.
    bursty: bool = False


def roles(model) -> Roles | None:
    """The roles if ``model`` is of the shape this layout runs: one shared prior with a plate of known size, one
    prior a document, a topic per outcome or per group of outcomes, and an observed outcome that the topic picks;
    or the same with a topic per outcome and components of every document's own."""
    rvs = model.spec.rvs
    priors, discrete = [r for r in rvs if r.kind != "categorical"], [r for r in rvs if r.kind == "categorical"]
    if len(priors) != 2 or len(discrete) != 2 or len(model.bases) != 1:
        return None
    x = next((r for r in discrete if r.parent.selectors), None)
    z = next((r for r in discrete if not r.parent.selectors), None)
    if x is None or z is None or list(x.parent.selectors) != [z] or model.observed() != {x.rid}:
        return None
    phi, theta = x.parent.prior, z.parent.prior
    if phi is theta or phi.plate is None or theta.plate is None or phi.plate.size is None or len(theta.chain()) != 1 or theta.plate.size is not None:
        return None
    bursty = len(phi.chain()) == 2 and phi.chain()[0] is theta.plate
    if len(phi.chain()) != 1 and not bursty:
        return None
    inside = [p.name for p in x.plate.chain()]
    same = z.plate is x.plate and inside == [theta.plate.name, x.plate.name] and not model.own_key[x.plate.name]
    grouped = inside == [theta.plate.name, z.plate.name, x.plate.name] and not model.own_key[x.plate.name]
    return Roles(phi, theta, z, x, bursty) if same or (grouped and not bursty) else None


def _bound_rows(model, found: Roles) -> tuple[DataFrame, list[str]]:
    """The observed rows as d, (s,) w, n and the columns before n."""
    plate = found.x.plate
    names = [found.theta.plate.name, *([found.z.plate.name] if found.z.plate is not plate else []), found.x.name]
    short = ["d", "s", "w"] if len(names) > 2 else ["d", "w"]
    return model.bases[plate.name].select(*[F.col(c).cast("long").alias(a) for c, a in zip(names, short, strict=True)], "n"), short


def _constants(model, found: Roles) -> tuple[float, int, float, int]:
    of = lambda g: (float(g.concentration.value(model.env)), int(g.dimension.value(model.env)))
    return *of(found.phi), *of(found.theta)


def _blocks(model) -> int:
    return max(model.spark.sparkContext.defaultParallelism, int(model.spark.conf.get("spark.sql.shuffle.partitions")))


class BlockEngine:
    """A bound model of that shape in the block layout, behind the interface of the long one."""

    def __init__(self, model, found: Roles, blocks: int | None = None):
        self.model, self.roles = model, found
        self.beta, v, self.alpha, k = _constants(model, found)
        rows, columns = _bound_rows(model, found)
        packed = model.packed.get(found.x.plate.name)
        self.topics = BlockTopics(rows, k, v, self.alpha, self.beta, blocks or _blocks(model), sentences=len(columns) > 2, clock=model.clock, packed=packed)

    @property
    def history(self) -> list[tuple[int, float, float]]:
        return self.topics.history

    def run(self, steps: int, callback: Callable | None = None) -> None:
        self.topics.infer(steps, (lambda past: callback(View(self.model, past[-1][0] if past else 0))) if callback else None)

    def lower_bound(self) -> float:
        return self.history[-1][1] if self.history else float("-inf")

    def posterior(self, v: Rv, dense: bool = False) -> DataFrame:
        if v is self.roles.phi:
            got, key = self.topics.topics(dense), v.plate.name
            got = got.withColumnRenamed("topics", key)
        elif v is self.roles.theta:
            # Every document of the corpus has data, so it has a row for every topic.
            got, key = self.topics.proportions(), v.plate.name
            got = got.withColumnRenamed("docs", key)
            got = got.join(got.groupBy(key).agg(F.sum("gamma").alias("total")), key)
        else:
            raise ModelError("the block layout keeps no posterior of single outcomes; infer with layout='long'")
        return got.select(key, "j", "gamma", (F.col("gamma") / F.col("total")).alias("mean"))


class BurstyEngine:
    """A bound model without a shared component: blocks run all rounds, so only bounds and results leave them."""

    def __init__(self, model, found: Roles, blocks: int | None = None):
        self.model, self.roles = model, found
        self.beta, self.v, self.alpha, self.k = _constants(model, found)
        packed = model.packed.get(found.x.plate.name)
        with model.clock.stage("graph construction"):
            self.folder = Scratch(model.spark)
            self.corpus = self.folder.table(packed if packed is not None else pack_corpus(_bound_rows(model, found)[0], blocks or _blocks(model)), "corpus")
        self.rounds, self.history, self.done = 0, [], None

    def run(self, steps: int, callback: Callable | None = None) -> None:
        """All rounds at once; if the callback ends them earlier, the last one's state is made again (rounds are exact repeats)."""
        with self.model.clock.stage("inference"):
            began = time.perf_counter()
            self._upto(steps)
            seconds = time.perf_counter() - began
            bounds = self.done.select(F.posexplode("bounds").alias("t", "v")).groupBy("t").agg(F.sum("v").alias("v")).collect()
            bounds = [r["v"] for r in sorted(bounds, key=lambda r: r["t"])] or [0.0] * steps
            if callback and callback(View(self.model, 0)) is False:
                return self._upto(0)
            for t, bound in enumerate(bounds, 1):
                self.history.append((t, bound, seconds * t / steps))
                if callback and callback(View(self.model, t)) is False:
                    return self._upto(t)

    def _upto(self, rounds: int) -> None:
        if self.done is None or rounds != self.rounds:
            self.rounds = rounds
            self.done = self.folder.table(bursty_blocks(self.corpus, self.k, self.v, self.alpha, self.beta, rounds), "bursty")
            self.folder.forget("bursty", keep=1)

    def lower_bound(self) -> float:
        return self.history[-1][1] if self.history else float("-inf")

    def posterior(self, v: Rv, dense: bool = False) -> DataFrame:
        doc, k = self.roles.theta.plate.name, self.k
        if v is self.roles.theta:

            def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for row in _rows(batches):
                    docs, gamma = np.frombuffer(row["d"], np.int64), np.frombuffer(row["theta"], np.float64)
                    total = gamma.reshape(-1, k).sum(axis=1)
                    yield pa.RecordBatch.from_arrays([pa.array(np.repeat(docs, k)), pa.array(np.tile(np.arange(k), len(docs))), pa.array(gamma), pa.array(gamma / np.repeat(total, k))], [doc, "j", "gamma", "mean"])

            return self.done.select("d", "theta").mapInArrow(listed, f"{doc} long, j long, gamma double, mean double")
        if v is not self.roles.phi or dense:
            raise ModelError("the block layout keeps neither posteriors of single outcomes nor dense components of every document; infer with layout='long'")
        topic = v.plate.name

        def held(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for row in _rows(batches):
                w, phi, mass = row["w"], np.frombuffer(row["phi"], np.float64), np.frombuffer(row["mass"], np.float64)
                w, docs = np.frombuffer(w, np.int64), np.frombuffer(row["doc"], np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(docs, k)), pa.array(np.tile(np.arange(k), len(w))), pa.array(np.repeat(w, k)), pa.array(phi), pa.array(phi / mass)], [doc, topic, "j", "gamma", "mean"])

        again = bursty_blocks(self.corpus, self.k, self.v, self.alpha, self.beta, self.rounds, components=True)
        return again.mapInArrow(held, f"{doc} long, {topic} long, j long, gamma double, mean double")


def _kl_phi(phi: np.ndarray, beta: float) -> float:
    return _kl_rows(phi.T, beta)


def local_bursty(tokens: DataFrame, k: int, v: int, alpha: float, beta: float, rounds: int, blocks: int) -> DataFrame:
    """The bursty topic model: all rounds inside a block.  ``block, docs, bounds``: each round's bound as an array.

    Words that a document lacks stay at the prior for every topic, so only (word in document, topic) is held.
    """
    return bursty_blocks(pack_corpus(tokens, blocks), k, v, alpha, beta, rounds)


def bursty_blocks(corpus: DataFrame, k: int, v: int, alpha: float, beta: float, rounds: int, components: bool = False) -> DataFrame:
    """The rounds of packed blocks: ``block, docs, bounds, theta, d``, or with ``components`` ``doc, w, phi, mass`` a word."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            c = _Corpus.of(row)
            starts = np.flatnonzero(np.concatenate([[True], c.doc[1:] != c.doc[:-1]])) if len(c.doc) else np.zeros(0, np.int64)
            r, bounds = _start(c, 0, len(c.w), k), []
            lg = lambda x: float(log_gamma_np(np.array([x]))[0])
            for t in range(rounds + 1):
                if t:
                    s = _expected(theta)[c.doc] + digamma_np(phi) - digamma_np(mass)[c.doc]
                    r, lse = _softmax(s)
                    e = digamma_np(phi) - digamma_np(mass)[c.doc]
                    minus = _kl_rows(theta, alpha) + float((log_gamma_np(mass) - lg(v * beta)).sum()) + float((lg(beta) - log_gamma_np(phi) + (phi - beta) * e).sum())
                    bounds.append(float((c.n * lse).sum()) - minus)
                m = c.n[:, None] * r
                sums = np.add.reduceat(m, starts, axis=0)
                theta, phi, mass = alpha + sums, beta + m, v * beta + sums
            if components:
                yield pa.RecordBatch.from_pydict({"doc": [c.docs[c.doc].tobytes()], "w": [c.w.tobytes()], "phi": [phi.tobytes()], "mass": [mass[c.doc].tobytes()]})
                continue
            yield pa.RecordBatch.from_pydict({"block": [row["block"]], "docs": [len(c.docs)], "bounds": [bounds], "theta": [theta.tobytes()], "d": [c.docs.tobytes()]})

    return corpus.mapInArrow(run, "doc binary, w binary, phi binary, mass binary" if components else "block long, docs long, bounds array<double>, theta binary, d binary")
