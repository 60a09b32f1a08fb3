"""Near-duplicate classes by BagMinHash signatures and exact multiset verification.

A text is the multiset of its runs of five words (a shorter text: its words as one run).  A run of count w
owns the weight interval [0, w), cut into the dyadic pieces [0,1), [1,2), [2,4), [4,8), ...  On every piece a Poisson
process of its own (seeded by run and piece) throws points at rate 1 per unit of weight; a point has a time, a
signature component, and a place found by halving the piece, one random bit a halving, until the half it lies
in is wholly below or above w.  Points below w count, and each component keeps its earliest point.  So a smaller count
sees a part of the same points, and two texts agree in a component with probability equal to their
weighted Jaccard similarity.  Points are made up to a time by which all components are surely taken; the
few texts where one stays open go on in later time slices.

Exact copies (equal run multisets) form classes first, one text stands for each.  Signatures are cut into bands; texts
that share a band are candidates.  In every band one text leads: the one that shares most bands with other texts,
which in a family of edited copies is the one nearest to all.  Every member is compared with its bands' leaders
by the exact multiset similarity, and links connect classes.  Bands whose members then belong to several classes are
gone through again, with two leaders drawn by hash, each compared with the members of other classes.  What is still
open then is done whole: in every band with several classes, all texts outside its largest class are compared with all
members of other classes.  So every two texts that share a band and could be ``SIMILARITY`` near are in one class or were
compared, and only a pair that shares no band can be missed.  No pairs are made for this: bands of one largest class are a
group, each of its texts is sent to the group once, and there an inverted index of the runs of those outside the class
gives the exact overlap of each with every text of the group.  Groups over ``HELD`` and ``STREAM`` are dealt in blocks.

Hot keys: bands, leaders, classes and digests that hold many rows are joined by broadcast of at most
``HOT_SHARE`` rows (see ``hot_join``), and the texts compared with one leader are dealt in chunks of ``CHUNK``.

Defined cases: a null text counts as empty; texts without a word form one class of their own; repeated rows are
copies; rows without an id are left out, of rows that share an id the text of the lowest hash counts; columns
other than the id and the text are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_bytes, hot_join, ragged, stored, text_array

SHINGLE = 5
SIMILARITY = 0.8
BANDS, ROWS = 32, 4
COMPONENTS = BANDS * ROWS
#: Texts that are compared with one leader in one group.
CHUNK = 256
#: Runs of texts outside the largest class that a task holds, and of texts that it compares with them, about.
HELD, STREAM = 1 << 17, 1 << 19
#: A text counts for so many runs more, so a task holds at most HELD / LEAST texts.
LEAST = 32
#: Common runs, and pairs of texts, that are counted at a time.
MATCHES = 1 << 19
#: Times that open bands, those that hold several classes, are gone through with leaders before all that is left is compared.
TURNS = 2
BATCH_BYTES = 2 << 20
#: Pieces whose points are made at a time.
MOST_PIECES = 1 << 17
U = np.uint64


def mixed(x: np.ndarray) -> np.ndarray:
    """The finaliser of a published 64-bit generator."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def word_hashes(table: pa.Array) -> np.ndarray:
    import xxhash

    return np.array([xxhash.xxh64_intdigest(w) for w in table.cast(pa.binary()).to_pylist()], np.uint64)


def runs(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Text number, hash and count of every distinct run of five words, by text and hash."""
    pieces = pc.ascii_split_whitespace(pc.utf8_lower(texts))
    filled = pc.binary_length(pieces.values).to_numpy() > 0
    edges = np.concatenate([[0], np.cumsum(filled)])[pieces.offsets.to_numpy()]
    coded = pieces.values.filter(pa.array(filled)).dictionary_encode()
    if not len(coded):
        return np.zeros(0, np.int64), np.zeros(0, U), np.zeros(0, np.int64)
    word = word_hashes(coded.dictionary)[coded.indices.to_numpy()]
    n = np.diff(edges)
    width = np.minimum(n, SHINGLE)
    many = np.where(n > 0, n - width + 1, 0)
    doc = np.repeat(np.arange(len(n)), many)
    start = ragged(edges[:-1], many)
    value = np.full(len(doc), U(0x9E3779B97F4A7C15))
    for k in range(SHINGLE):
        inside = k < width[doc]
        value[inside] = mixed(value[inside] * U(3) + word[start[inside] + k])
    order = np.lexsort((value, doc))
    doc, value = doc[order], value[order]
    first = np.flatnonzero(np.concatenate([[True], (doc[1:] != doc[:-1]) | (value[1:] != value[:-1])]))
    return doc[first], value[first], np.diff(np.append(first, len(doc)))


def _unit(x: np.ndarray) -> np.ndarray:
    return ((x >> U(11)).astype(np.float64) + 0.5) * 2.0**-53


def _below(low: np.ndarray, span: np.ndarray, limit: np.ndarray, bits: np.ndarray) -> np.ndarray:
    """Whether points of the pieces [low, low + span) lie below ``limit``, by halving; each bit names a half."""
    inside = low + span <= limit
    open_ = np.flatnonzero(~inside & (low < limit))
    low, span = low[open_].copy(), span[open_].copy()
    level = 63
    while len(open_):
        span /= 2
        low += span * ((bits[open_] >> U(level)) & U(1)).astype(np.float64)
        below = low + span <= limit[open_]
        inside[open_[below]] = True
        left = ~below & (low < limit[open_])
        open_, low, span, level = open_[left], low[left], span[left], level - 1
    return inside


def signatures(doc: np.ndarray, value: np.ndarray, count: np.ndarray, n_docs: int, m: int = COMPONENTS) -> np.ndarray:
    """BagMinHash signatures (n_docs x m hashes of the winning points); texts without runs get zeros."""
    pieces = np.where(count > 1, np.ceil(np.log2(np.maximum(count, 1))).astype(np.int64) + 1, 1)
    at = np.repeat(np.arange(len(doc)), pieces)
    level = ragged(np.zeros(len(doc), np.int64), pieces)
    low = np.where(level == 0, 0, 2.0 ** (level - 1))
    span = np.where(level == 0, 1.0, low)
    owner, limit = doc[at], count[at].astype(np.float64)
    seed = mixed(value[at] + level.astype(U) * U(0x9E3779B97F4A7C15))
    weight = np.bincount(doc, count, n_docs)
    # The mean gap of a component's points is m / weight; after this many, one of m stays open rarely.
    horizon = np.where(weight > 0, m * (np.log(m) + 3) / np.maximum(weight, 1), 0)
    best = np.full(n_docs * m, np.inf)
    sign = np.zeros(n_docs * m, U)
    active = np.arange(len(at))
    while len(active):
        for start in range(0, len(active), MOST_PIECES):
            live = active[start : start + MOST_PIECES]
            made, time = np.zeros(len(live), np.int64), np.zeros(len(live))
            while len(live):
                # Some points of every piece at once, many where few pieces are left.
                turn = np.arange(1, max(1, min(64, MOST_PIECES // (4 * len(live)))) + 1)
                point = mixed(seed[live][:, None] + (made[:, None] + turn).astype(U) * U(0x632BE59BD9B4E019))
                t = time[:, None] + np.cumsum(-np.log(_unit(mixed(point ^ U(4)))), axis=1) / span[live][:, None]
                row, column = np.nonzero(t < horizon[owner[live]][:, None])
                whose, point, early = live[row], point[row, column], t[row, column]
                inside = _below(low[whose], span[whose], limit[whose], mixed(point ^ U(3)))
                cell = owner[whose] * m + (mixed(point ^ U(2)) % U(m)).astype(np.int64)
                inside &= early < best[cell]
                cell, early, point = cell[inside], early[inside], point[inside]
                order = np.lexsort((point, early, cell))
                cell, early, point = cell[order], early[order], point[order]
                lead = np.flatnonzero(np.concatenate([[True], cell[1:] != cell[:-1]])) if len(cell) else cell
                best[cell[lead]], sign[cell[lead]] = early[lead], point[lead]
                on = t[:, -1] < horizon[owner[live]]
                live, made, time = live[on], made[on] + len(turn), t[on, -1]
        unsettled = np.isinf(best).reshape(n_docs, m).any(axis=1) & (weight > 0)
        active = active[unsettled[owner[active]]]
        horizon = horizon * 2
    return sign.reshape(n_docs, m)


def band_keys(sign: np.ndarray) -> np.ndarray:
    keys = np.zeros((len(sign), BANDS), U)
    for r in range(ROWS):
        keys = mixed(keys * U(3) + sign[:, r::ROWS][:, :BANDS] + U(r + 1))
    return mixed(keys + np.arange(BANDS, dtype=U))


def similarity(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Exact multiset Jaccard similarity of two sorted (hash, count) lists."""
    total = int(a[1].sum() + b[1].sum())
    if not total:
        return 1.0
    _, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    both = int(np.minimum(a[1][i], b[1][j]).sum())
    return both / (total - both)


def _digested(rows: DataFrame) -> DataFrame:
    """``k, same, bands, size`` of rows (k, t): id, digest of the run multiset, band keys, number of runs."""

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in by_bytes(batches, "t", BATCH_BYTES):
            n = table.num_rows
            doc, value, count = runs(text_array(table.column("t")))
            keys = band_keys(signatures(doc, value, count, n))
            size = np.bincount(doc, count, n).astype(np.int64)
            one, two = np.zeros(n, U), np.zeros(n, U)
            with np.errstate(over="ignore"):
                np.add.at(one, doc, mixed(value + count.astype(U) * U(0x9E3779B97F4A7C15)))
                np.add.at(two, doc, mixed(mixed(value ^ U(0x5851F42D4C957F2D)) + count.astype(U)))
            same = np.ascontiguousarray(np.stack([one, two], axis=1)).view(np.uint8).reshape(n, 16)
            flat = pa.array(keys.view(np.int64).ravel())
            bands = pa.ListArray.from_arrays(pa.array(np.arange(0, n * BANDS + 1, BANDS, dtype=np.int32)), flat)
            yield pa.RecordBatch.from_arrays([table.column("k").combine_chunks(), pa.array([x.tobytes() for x in same], pa.binary()), bands, pa.array(size)], ["k", "same", "bands", "size"])

    return rows.mapInArrow(digest, f"k {rows.schema['k'].dataType.simpleString()}, same binary, bands array<long>, size long")


def _verified(texts: DataFrame, pairs: DataFrame, least: float) -> DataFrame:
    """``a, b, near`` for every (leader a, member b, chunk) of ``pairs``: whether the texts are ``least`` similar, exactly.

    A leader's text goes before each chunk of its members and is parsed once a chunk.
    """
    kind = pairs.schema["a"].dataType.simpleString()
    heads = pairs.select("a", "chunk", F.lit(0).alias("side"), F.col("a").alias("k")).distinct()
    wanted = heads.union(pairs.select("a", "chunk", F.lit(1), "b"))
    stream = wanted.join(texts.hint("merge"), "k").withColumnRenamed("k", "b").repartition("a", "chunk").sortWithinPartitions("a", "chunk", "side")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lead = (np.zeros(0, U), np.zeros(0, np.int64))
        for table in by_bytes(batches, "t", BATCH_BYTES):
            doc, value, count = runs(text_array(table.column("t")))
            cuts = np.searchsorted(doc, np.arange(table.num_rows + 1))
            side = table.column("side").to_numpy()
            near = np.zeros(table.num_rows, bool)
            for i, member in enumerate(side):
                own = value[cuts[i] : cuts[i + 1]], count[cuts[i] : cuts[i + 1]]
                if member:
                    near[i] = similarity(lead, own) >= least
                else:
                    lead = own
            found = table.append_column("near", pa.array(near)).select(["a", "b", "near"]).filter(pa.array(side == 1))
            yield from found.combine_chunks().to_batches()

    return stream.mapInArrow(compare, f"a {kind}, b {kind}, near boolean")


class _Held:
    """Texts outside a group's largest class, by run."""

    def __init__(self) -> None:
        self.ids, self.roots, self.parts, self.sorted = [], [], [], False

    def add(self, doc: np.ndarray, value: np.ndarray, count: np.ndarray, ids: list, roots: list) -> None:
        self.parts.append((doc + len(self.ids), value, count))
        self.ids += ids
        self.roots += roots

    def _sort(self) -> None:
        owner, value, count = (np.concatenate(x) for x in zip(*self.parts, strict=True))
        order = np.argsort(value, kind="stable")
        self.owner, self.count = owner[order], count[order]
        self.run, first = np.unique(value[order], return_index=True)
        self.starts = np.append(first, len(order))
        self.size = np.bincount(owner, count, len(self.ids)).astype(np.int64)
        self.code = {r: i for i, r in enumerate(dict.fromkeys(self.roots))}
        self.root = np.array([self.code[r] for r in self.roots])
        self.parts, self.sorted, self.linked = [], True, set()

    def near(self, doc: np.ndarray, value: np.ndarray, count: np.ndarray, ids: list, roots: list, least: float, most: int) -> Iterator[tuple]:
        """Ids of a held text and one of ``ids`` that are ``least`` similar: one link of each held text with each other class at least."""
        if not self.sorted:
            self._sort()
        n, n_held = len(ids), len(self.ids)
        size = np.bincount(doc, count, n).astype(np.int64)
        own = np.array([self.code.setdefault(r, len(self.code)) for r in roots])
        at = np.minimum(np.searchsorted(self.run, value), len(self.run) - 1)
        hit = self.run[at] == value
        doc, at, count = doc[hit], at[hit], count[hit]
        many = self.starts[at + 1] - self.starts[at]
        cuts = np.searchsorted(doc, np.arange(n + 1))
        reach = np.concatenate([[0], np.cumsum(many)])[cuts]
        start = 0
        while start < n:
            stop = int(np.searchsorted(reach, reach[start] + most, side="right")) - 1
            stop = min(n, max(start + 1, min(stop, start + most // n_held)))
            part = slice(cuts[start], cuts[stop])
            place = ragged(self.starts[at[part]], many[part])
            both = np.minimum(np.repeat(count[part], many[part]), self.count[place])
            pair = np.repeat((doc[part] - start) * n_held, many[part]) + self.owner[place]
            both = np.bincount(pair, both, (stop - start) * n_held)
            pair = np.flatnonzero(both)
            row, held = pair // n_held + start, pair % n_held
            near = (both[pair] / (size[row] + self.size[held] - both[pair]) >= least) & (own[row] != self.root[held])
            row, held = row[near], held[near]
            _, first = np.unique(held * len(self.code) + own[row], return_index=True)
            for r, h in zip(row[first].tolist(), held[first].tolist(), strict=True):
                if (h, roots[r]) not in self.linked:
                    self.linked.add((h, roots[r]))
                    yield self.ids[h], ids[r]
            start = stop


def _blocks(members: DataFrame, least: float) -> DataFrame:
    """``g, p, q, side, k, root``: of each group and block (p, q) the texts outside the largest class g (side 0) and those to compare with them (1).

    ``members``: id, size, root and band of every text and band.  A group is all open bands of one largest class.
    """
    sized = members.groupBy("band", "root").agg(F.count("*").alias("held"))
    main = sized.groupBy("band").agg(F.max(F.struct("held", "root"))["root"].alias("g"), F.sum("held").alias("n"), F.count("*").alias("roots"))
    main = stored(main.filter("roots > 1").select("band", "n", "g"), "main-classes")
    texts = stored(hot_join(members, main, "band").select("g", "id", "size", "root").distinct(), "open-texts")
    outside = F.when(F.col("root") != F.col("g"), F.col("size"))
    groups = texts.groupBy("g").agg(F.count("*").alias("n"), F.min(outside).alias("lo"), F.max(outside).alias("hi"), F.sum(outside + LEAST).alias("o"), F.sum(F.col("size") + LEAST).alias("m"))
    groups = stored(groups.select("g", "n", "lo", "hi", F.ceil(F.col("o") / HELD).cast("int").alias("ps"), F.ceil(F.col("m") / STREAM).cast("int").alias("qs")), "open-groups")
    # A text whose size no text outside comes near to has no link.
    texts = hot_join(texts, groups, "g").filter((F.col("size") >= F.col("lo") * least) & (F.col("size") * least <= F.col("hi")))
    own = {x: F.pmod(F.xxhash64("id", F.lit(x)), F.col(x)).cast("int") for x in ("ps", "qs")}
    every = {x: F.sequence(F.lit(0), F.col(x) - 1) for x in ("ps", "qs")}
    dealt = F.array(F.struct(F.lit(0).alias("side"), F.array(own["ps"]).alias("p"), every["qs"].alias("q")), F.struct(F.lit(1).alias("side"), every["ps"].alias("p"), F.array(own["qs"]).alias("q")))
    sides = texts.select("g", "root", F.col("id").alias("k"), F.explode(F.filter(dealt, lambda x: (x["side"] == 1) | (F.col("root") != F.col("g")))).alias("d"))
    sides = sides.select("g", "root", "k", "d.side", F.explode("d.p").alias("p"), F.col("d.q").alias("q"))
    return sides.select("g", "p", F.explode("q").alias("q"), "side", "k", "root")


def _compared(texts: DataFrame, blocks: DataFrame, least: float) -> DataFrame:
    """``a, b``: links between different classes of all texts that ``blocks`` brings together, enough to connect the classes."""
    kind, most = texts.schema["k"].dataType.simpleString(), MATCHES
    stream = blocks.join(texts.hint("merge"), "k").repartition("g", "p", "q").sortWithinPartitions("g", "p", "q", "side")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, held = None, _Held()
        for table in by_bytes(batches, "t", BATCH_BYTES):
            doc, value, count = runs(text_array(table.column("t")))
            ids, roots, side = (table.column(c).to_pylist() for c in ("k", "root", "side"))
            key = list(zip(*(table.column(c).to_pylist() for c in ("g", "p", "q")), strict=True))
            found, start = [], 0
            while start < len(ids):
                stop = start + 1
                while stop < len(ids) and side[stop] == side[start] and key[stop] == key[start]:
                    stop += 1
                if key[start] != last:
                    last, held = key[start], _Held()
                a, b = np.searchsorted(doc, [start, stop])
                some = doc[a:b] - start, value[a:b], count[a:b], ids[start:stop], roots[start:stop]
                if not side[start]:
                    held.add(*some)
                elif held.ids:
                    found += held.near(*some, least, most)
                start = stop
            yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in found], table.schema.field("k").type) for i in (0, 1)], ["a", "b"])

    return stream.mapInArrow(compare, f"a {kind}, b {kind}")


def components(links: DataFrame, what: str = "components") -> DataFrame:
    """``id, root``: the lowest id of each connected component of ``links`` (a, b), for ids that have a link.

    Every round hooks the larger neighbours of an id to its smallest, then the smaller ones, until nothing moves;
    the rounds grow with the logarithm of a component's size and each is a table in the shared folder.
    """
    edges = stored(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v").distinct(), what)
    summary = (F.count("*"), F.bit_xor(F.xxhash64("u", "v")))
    mark = edges.agg(*summary).first()
    while mark[0]:
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v"))
        edges = stored(small.filter("u <> v").distinct(), what)
        before, mark = mark, edges.agg(*summary).first()
        if before == mark:
            break
    return edges.select(F.col("u").alias("id"), F.col("v").alias("root")).union(edges.select(F.col("v").alias("id"), F.col("v").alias("root")).distinct())


def classes(links: DataFrame) -> DataFrame:
    """``id, root``: the lowest id of the class, for every text in ``links`` (leader a, member b).

    Members of one leader may be a third of all texts, so the components are those of the leaders alone: two
    are joined if they have a member in common or one is the other's member.  A member has few leaders.
    """
    sets = stored(links.groupBy("b").agg(F.min("a").alias("low"), F.collect_set("a").alias("leaders")), "members-leaders")
    leaders = stored(links.groupBy("a").agg(F.min("b").alias("least")), "linked-leaders")
    chains = sets.join(leaders.select(F.col("a").alias("b")), "b", "left_semi").select(F.col("b").alias("a"), F.col("low").alias("b"))
    shared = sets.filter(F.size("leaders") > 1).select(F.explode("leaders").alias("a"), F.col("low").alias("b"))
    roots = components(chains.union(shared), "leader-links")
    named = leaders.join(roots.withColumnRenamed("id", "a"), "a", "left").select("a", F.coalesce("root", "a").alias("root"), F.least("a", "least").alias("least"))
    lowest = named.groupBy("root").agg(F.min("least").alias("class"))
    named = stored(named.join(lowest, "root").select("a", "class"), "leader-classes")
    # Both sides are read from tables, so adaptive execution can split a leader's many members.
    members = sets.select(F.col("b").alias("id"), F.col("low").alias("a")).join(named, "a").select("id", F.col("class").alias("root"))
    alone = named.join(sets.select(F.col("b").alias("a")), "a", "left_anti").select(F.col("a").alias("id"), F.col("class").alias("root"))
    return stored(members.union(alone), "roots")


def _one_text_an_id(docs: DataFrame, key: str, text: str) -> DataFrame:
    rows = docs.select(F.col(key).alias("k"), F.coalesce(F.col(text), F.lit("")).alias("t")).filter("k is not null")
    repeated = rows.groupBy("k").agg(F.count("*").alias("n")).filter("n > 1").select("k")
    if not repeated.take(1):
        return rows
    lowest = rows.join(repeated, "k", "left_semi").groupBy("k").agg(F.min(F.struct(F.xxhash64("t").alias("h"), "t")).alias("l"))
    return stored(rows.join(repeated, "k", "left_anti").union(lowest.select("k", "l.t")), "one-text-an-id")


def _leaders(turn: int) -> list:
    """The leaders of a band: the text of most companions at first, later the ends of a random order."""
    if not turn:
        return [F.max(F.struct(F.col("c").alias("rank"), "id", "size", "root"))]
    ranked = F.struct(F.xxhash64("id", "band", F.lit(turn)).alias("rank"), "id", "size", "root")
    return [F.min(ranked), F.max(ranked)]


def near_classes(docs: DataFrame, key: str = "doc_id", text: str = "text", least: float = SIMILARITY) -> DataFrame:
    """``key, class_id, copy_of``: the lowest id of the near-duplicate class and of the exact copies, a row an id."""
    rows = _one_text_an_id(docs, key, text)
    digests = stored(_digested(rows), "bag-signatures")
    kind = digests.schema["k"].dataType.simpleString()
    copies = stored(digests.groupBy("same").agg(F.min("k").alias("id"), F.count("*").alias("n")), "copies")
    reps = digests.join(copies.select(F.col("id").alias("k")), "k", "left_semi").filter("size > 0")
    flat = reps.select(F.col("k").alias("id"), "size", F.explode("bands").alias("band"))
    # A band of one text can't link; those of several are a small part of the corpus.
    crowded = stored(flat.groupBy("band").agg(F.count("*").alias("n")).filter("n > 1").withColumn("held", F.col("n")), "crowded-bands")
    # A row a text, with its bands and how many texts it meets there.
    bands = hot_join(flat, crowded, "band").groupBy("id", "size").agg(F.sum("held").alias("c"), F.collect_list("band").alias("bands"))
    bands = stored(bands, "bands")
    # Dealt by id at every size: a broadcast list of candidates would grow with the corpus.
    texts = stored(rows.join(bands.select(F.col("id").alias("k")).hint("merge"), "k", "left_semi"), "candidate-texts")
    roots = links = None
    for turn in range(TURNS + 1):
        members = bands.join(roots, "id", "left").withColumn("root", F.coalesce("root", "id")) if roots else bands.withColumn("root", F.col("id"))
        members = (stored(members, "members") if roots else members).select("id", "size", "c", "root", F.explode("bands").alias("band"))
        if turn == TURNS:
            near = _compared(texts, stored(_blocks(members, least), "blocks"), least)
        else:
            groups = members.groupBy("band").agg(F.count("*").alias("n"), F.min("root").alias("lo"), F.max("root").alias("hi"), F.array(*_leaders(turn)).alias("leads"))
            groups = stored(groups.filter("lo <> hi").select("band", "n", F.ceil(F.col("n") / CHUNK).alias("chunks"), "leads"), "open-bands")
            led = hot_join(members, groups, "band").select("id", "size", "root", "chunks", F.explode("leads").alias("l"))
            fit = F.least("l.size", "size") >= F.greatest("l.size", "size") * least
            pairs = led.filter(fit & (F.col("l.root") != F.col("root"))).groupBy(F.col("l.id").alias("a"), F.col("id").alias("b")).agg(F.max("chunks").alias("chunks"))
            pairs = stored(pairs.select("a", "b", F.hash("chunks", F.pmod(F.xxhash64("b"), F.col("chunks"))).alias("chunk")), "pairs")
            near = _verified(texts, pairs, least).filter("near").select("a", "b")
        near = stored(near, "links")
        if near.take(1):
            links = links.union(near) if links else near
            roots = classes(links)
    if not roots:
        roots = docs.sparkSession.createDataFrame([], f"id {kind}, root {kind}")
    named = stored(copies.join(roots, "id", "left").select("same", "id", "n", F.coalesce("root", "id").alias("root")), "classes")
    return hot_join(digests.select("k", "same"), named, "same").select(F.col("k").alias(key), F.col("root").alias("class_id"), F.col("id").alias("copy_of"))


def keep_one(docs: DataFrame, key: str = "doc_id", text: str = "text", least: float = SIMILARITY) -> DataFrame:
    """The rows of ``docs`` whose id is the lowest of its class, one row an id; rows without an id stay."""
    drop = near_classes(docs, key, text, least).filter(F.col(key) != F.col("class_id")).select(key)
    kept = docs.join(drop, key, "left_anti").select(docs.columns)
    repeated = docs.filter(F.col(key).isNotNull()).groupBy(key).agg(F.count("*").alias("n")).filter("n > 1").select(key)
    if not repeated.take(1):
        return kept
    whole = F.struct(*[F.col(f"`{c}`") for c in docs.columns])
    again = kept.join(repeated, key, "left_semi").select(docs.columns).withColumn("__h", F.xxhash64(text)).groupBy(key).agg(F.min_by(whole, F.col("__h")).alias("row")).select("row.*")
    return kept.join(repeated, key, "left_anti").select(docs.columns).union(again)
