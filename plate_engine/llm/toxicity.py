"""Toxicity by the nearest labelled examples: exact TF-IDF cosine over a block-max inverted index.

Learning (on labelled rows only): words are lower-cased runs of characters outside white space and ASCII
punctuation; a word gives the terms of itself and of its stems of four and five characters, since inflecting
languages rarely repeat a whole word.  Every term of a labelled text has a weight, whatever its label, language
or count: TF-IDF, with document frequencies over *all* documents, times 1 + |z|, z being the signed root of the
chi-square statistic of the term with the label over all training texts.  So a short abusive passage is not drowned
by thousands of neutral words, which keep their TF-IDF weight.  A term that no labelled text holds can match none and is not
weighed.  At most ``TOXIC`` toxic and ``OTHER`` other labelled documents are learnt from, those of the lowest id hashes;
their distinct texts form the index: postings of every term, and for the ``FREQUENT`` terms of the most postings a matrix of
weights by example and one of the largest weight of each block of 64 neighbouring example numbers.

Scoring: a text's vector is matched against the index and its ``k`` nearest examples are found
exactly.  Some texts are searched together: first the postings of their rarer terms are summed.  Then the blocks' largest weights
bound what the frequent terms can add to the examples of a block; an example that can't reach the k-th score any more is out,
and once few are left, that ends the search.  For the other texts a matrix product adds the frequent terms to all examples, in
single precision; an example that is below the k-th score by more than the product's greatest error is out.  Those left get
their cosines in double precision, so neither step changes a neighbour.  Equal scores go to the lower example number.  The labels vote with weight 1 / (distance + eps); the vote,
binned and made monotone by pooling on leave-one-out votes of the examples, is the score.  In the pooling an example counts
for all labelled rows of its label, so the share of toxic ones is that of the labels and not of the sample.  A text without a term of the
examples has no neighbours and gets the rate of such examples.

Defined cases: a null text counts as empty (no neighbours); ties as above; repeated rows are scored each;
one text with both labels counts as toxic; with no labelled rows every score is 0; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import by_bytes, distinct_texts, ragged, text_array

BLOCK = 64
EPS = 0.05
STEMS = (4, 5)
#: For sums of single-precision weights in another order.
SLACK = 1e-9
BINS = 20
BATCH_BYTES = 2 << 20
#: Words whose terms are counted at a time; a worker holds some 150 bytes a word then.
PAIRED = 1 << 16
#: Labelled rows to learn from, at most, of each label.
TOXIC, OTHER = 1000, 2000
#: Terms of the most postings, whose weights are a matrix; texts searched together, and their postings of other terms.
FREQUENT = 1024
TOGETHER, POSTINGS = 64, 1 << 18
#: Up to 1 / ENOUGH of the examples are completed one by one rather than all by the product.
ENOUGH = 32
#: ASCII white space, control characters and punctuation become spaces, capitals lower case.
FOLD = bytes(32 if b < 48 or 58 <= b < 65 or 91 <= b < 97 or 123 <= b < 128 else b + 32 if 65 <= b < 91 else b for b in range(256))


def folded_words(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, pa.Array]:
    """Document number and word number of every word, and the distinct words of the batch."""
    offsets = np.frombuffer(texts.buffers()[1], np.int32)[texts.offset : texts.offset + len(texts) + 1] if len(texts) else np.zeros(1, np.int32)
    data = texts.buffers()[2]
    body = data.to_pybytes()[offsets[0] : offsets[-1]].translate(FOLD) if data is not None else b""
    flat = pa.Array.from_buffers(pa.string(), len(texts), [None, pa.py_buffer((offsets - offsets[0]).astype(np.int32)), pa.py_buffer(body)])
    pieces = pc.split_pattern(flat, " ")
    doc = np.repeat(np.arange(len(texts)), np.diff(pieces.offsets.to_numpy()))
    values = pieces.values
    filled = pc.binary_length(values).to_numpy() > 0
    coded = values.filter(pa.array(filled)).dictionary_encode()
    return doc[filled], coded.indices.to_numpy().astype(np.int64), coded.dictionary


def terms_of(word: str) -> list[str]:
    return ["=" + word] + ["^" + word[:k] for k in STEMS if len(word) > k]


@dataclass
class Terms:
    """Numbered terms, in their order: whole words, then stems."""

    whole: pa.Array
    stem: pa.Array

    @classmethod
    def of(cls, terms: pa.Array) -> Terms:
        stem = pc.starts_with(terms, "^")
        bare = pc.utf8_slice_codeunits(terms, 1)
        return cls(bare.filter(pc.invert(stem)), bare.filter(stem))

    def __len__(self) -> int:
        return len(self.whole) + len(self.stem)

    def __iter__(self) -> Iterator[str]:
        yield from ("=" + w for w in self.whole.to_pylist())
        yield from ("^" + w for w in self.stem.to_pylist())

    def __getitem__(self, term: str) -> int:
        """The number of a term, -1 if it is none of these."""
        own, first = (self.stem, len(self.whole)) if term[0] == "^" else (self.whole, 0)
        at = own.index(term[1:]).as_py()
        return at if at < 0 else first + at

    def held(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The numbers of the terms of every word that are among these, word by word, and how many they are."""
        number = np.full((len(words), 1 + len(STEMS)), -1, np.int64)
        number[:, 0] = pc.fill_null(pc.index_in(words, self.whole), -1).to_numpy()
        length = pc.utf8_length(words).to_numpy()
        cut = pa.concat_arrays([pc.utf8_slice_codeunits(words, 0, k) for k in STEMS])
        stems = pc.fill_null(pc.index_in(cut, self.stem), -1).to_numpy().reshape(len(STEMS), -1).T
        number[:, 1:] = np.where((stems >= 0) & (length[:, None] > np.array(STEMS)), stems + len(self.whole), -1)
        return number[number >= 0], (number >= 0).sum(axis=1)


def term_counts(texts: pa.Array, number: Terms | dict[str, int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (text, term) pairs and their counts, by text.  Only the terms of ``number`` count; to a dict new ones are added."""
    doc, word, table = folded_words(texts)
    if isinstance(number, Terms):
        found, sizes = number.held(table)
    else:
        terms = [[number.setdefault(t, len(number)) for t in terms_of(w)] for w in table.to_pylist()]
        found, sizes = np.array([t for some in terms for t in some], np.int64), np.array([len(some) for some in terms], np.int64)
    starts, n = np.cumsum(sizes) - sizes, max(1, len(number))
    # By some whole texts at a time, since the pairs of all take much more memory than the texts.
    cuts = np.append(np.searchsorted(doc, doc[np.arange(0, len(doc), PAIRED)]), len(doc))
    parts = []
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        some, own = word[a:b], sizes[word[a:b]]
        pair, count = np.unique(np.repeat(doc[a:b], own) * n + found[ragged(starts[some], own)], return_counts=True)
        parts.append(((pair // n).astype(np.int32), (pair % n).astype(np.int32), count.astype(np.int32)))
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True)) if parts else (np.zeros(0, np.int32),) * 3


def _grouped(key: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The order that sorts ``key`` (kept stable) and where each of the n keys starts in it."""
    return np.argsort(key, kind="stable"), np.concatenate([[0], np.cumsum(np.bincount(key, minlength=n))]).astype(np.int64)


@dataclass
class BlockMaxIndex:
    """L2-normalised examples by term, in single precision, with the largest weight of every block."""

    starts: np.ndarray
    example: np.ndarray
    weight: np.ndarray
    n_examples: int

    @classmethod
    def build(cls, word: np.ndarray, example: np.ndarray, weight: np.ndarray, n_words: int, n_examples: int) -> BlockMaxIndex:
        order, starts = _grouped(word, n_words)
        return cls(starts, example[order].astype(np.int32), weight[order].astype(np.float32), n_examples)

    @cached_property
    def frequent(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
        """Place of every frequent term (-1: rare), their weights by example, the largest of each block, the largest norm."""
        sizes = np.diff(self.starts)
        terms = np.argsort(-sizes, kind="stable")[:FREQUENT]
        place = np.full(len(sizes), -1, np.int32)
        place[terms] = np.arange(len(terms))
        weight = np.zeros((len(terms), -(-self.n_examples // BLOCK) * BLOCK), np.float32)
        at = ragged(self.starts[terms], sizes[terms])
        weight[np.repeat(np.arange(len(terms)), sizes[terms]), self.example[at]] = self.weight[at]
        block_max = weight.reshape(len(terms), -(-self.n_examples // BLOCK), BLOCK).max(axis=2)
        norm = np.sqrt(np.einsum("ij,ij->j", weight, weight).max(initial=0.0))
        return place, weight[:, : self.n_examples], block_max, float(norm)

    def nearest(self, words: np.ndarray, weights: np.ndarray, k: int, skip: int = -1) -> tuple[np.ndarray, np.ndarray]:
        """The k examples of largest cosine (all positive), by (cosine desc, number), without ``skip``."""
        return self.nearest_each([(words, weights)], k, [skip])[0]

    def nearest_each(self, queries: list[tuple[np.ndarray, np.ndarray]], k: int, skip: list[int] | None = None) -> list[tuple[np.ndarray, np.ndarray]]:
        """``nearest`` of every (words, weights) of ``queries``."""
        place, weight, _, _ = self.frequent
        sizes, found, start = np.diff(self.starts), [], 0
        work = [int(sizes[w[place[w] < 0]].sum()) for w, _ in queries]
        while start < len(queries):
            stop, held = start + 1, work[start]
            while stop < len(queries) and stop - start < TOGETHER and held + work[stop] <= POSTINGS:
                held, stop = held + work[stop], stop + 1
            for i, score, open_ in zip(range(start, stop), *self._open(queries[start:stop], k), strict=True):
                words, weights = queries[i]
                who = np.flatnonzero(open_)
                who = who[who != skip[i]] if skip else who
                at = place[words]
                # Added term by term, so a cosine does not depend on what else is open.
                cosine = score[who] + (weights[at >= 0, None] * weight[np.ix_(at[at >= 0], who)]).sum(axis=0)
                who, cosine = who[cosine > 0], np.round(cosine[cosine > 0], 12)
                best = np.lexsort((who, -cosine))[:k]
                found.append((who[best], np.minimum(cosine[best], 1.0)))
            start = stop
        return found

    def _open(self, queries: list[tuple[np.ndarray, np.ndarray]], k: int) -> tuple[np.ndarray, np.ndarray]:
        """Of every query (a row), what its rare terms give to the examples, and which of them may be among its k + 1 nearest."""
        place, weight, block_max, norm = self.frequent
        n, rows = self.n_examples, len(queries)
        row = np.repeat(np.arange(rows), [len(w) for w, _ in queries])
        word, value = (np.concatenate(x) for x in zip(*queries, strict=True))
        rare = place[word] < 0
        terms = word[rare]
        sizes = self.starts[terms + 1] - self.starts[terms]
        at = ragged(self.starts[terms], sizes)
        score = np.bincount(np.repeat(row[rare] * n, sizes) + self.example[at], np.repeat(value[rare], sizes) * self.weight[at], rows * n).reshape(rows, n)
        query = np.zeros((rows, len(weight)), np.float32)
        query[row[~rare], place[word[~rare]]] = value[~rare]
        # Single-precision sums of so many products are off by this at most.
        slack = SLACK + (len(weight) + 4) * 2.0**-23 * norm * np.sqrt(np.einsum("ij,ij->i", query, query, dtype=np.float64))[:, None]
        least = max(0, n - k - 1)
        floor = (lambda s: np.partition(s, least, axis=1)[:, [least]] if n > k + 1 else np.zeros((len(s), 1)))
        open_ = score + np.repeat(query @ block_max, BLOCK, axis=1)[:, :n] >= floor(score) - slack
        more = np.flatnonzero(open_.sum(axis=1) * ENOUGH > n)
        whole = score[more] + query[more] @ weight
        open_[more] = (whole >= floor(whole) - slack[more]) & (whole > 0)
        return score, open_


@dataclass
class Sent:
    """A model for the workers: its large parts are broadcast once, for learning and scoring alike."""

    words: Broadcast
    scale: Broadcast
    parts: Broadcast | None
    k: int
    edges: np.ndarray
    level: np.ndarray
    bare: float

    def model(self) -> NeighbourModel:
        index, label, example_hash = self.parts.value if self.parts else (None, None, None)
        return NeighbourModel(self.words.value, self.scale.value, index, label, example_hash, self.k, self.edges, self.level, self.bare)


@dataclass
class NeighbourModel:
    words: Terms
    scale: np.ndarray
    index: BlockMaxIndex
    label: np.ndarray
    example_hash: np.ndarray
    k: int
    edges: np.ndarray
    level: np.ndarray
    bare: float
    sent: Sent | None = None

    def vectors(self, texts: pa.Array) -> list[tuple[np.ndarray, np.ndarray]]:
        """Words and L2-normalised TF-IDF weights of every text."""
        doc, word, n = term_counts(texts, self.words)
        weight = (1 + np.log(n)) * self.scale[word]
        norm = np.sqrt(np.bincount(doc, weight**2, len(texts)))
        weight = weight / np.maximum(norm[doc], 1e-300)
        cuts = np.searchsorted(doc, np.arange(len(texts) + 1))
        return [(word[a:b], weight[a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]

    def votes(self, texts: pa.Array, skip: list[int] | None = None) -> Iterator[tuple[float, np.ndarray, np.ndarray]]:
        """The vote of every text's nearest examples (-1: it has none), their numbers and cosines."""
        for near, cosine in self.index.nearest_each(self.vectors(texts), self.k, skip):
            pull = 1.0 / (1.0 - cosine + EPS)
            yield float((pull * self.label[near]).sum() / pull.sum()) if len(near) else -1.0, near, cosine

    def calibrated(self, vote: float) -> float:
        return self.bare if vote < 0 else float(self.level[min(len(self.level) - 1, int(np.searchsorted(self.edges, vote, side="right")))])


def _pooled(rates: list[float], sizes: list[float]) -> np.ndarray:
    """Pool adjacent violators: the closest rising sequence."""
    stack: list[list[float]] = []
    for rate, size in zip(rates, sizes, strict=True):
        stack.append([rate, size, 1])
        while len(stack) > 1 and stack[-2][0] >= stack[-1][0]:
            r, s, c = stack.pop()
            stack[-1] = [(stack[-1][0] * stack[-1][1] + r * s) / (stack[-1][1] + s), stack[-1][1] + s, stack[-1][2] + c]
    return np.array([r for r, _, c in stack for _ in range(int(c))])


def examples(docs: DataFrame, marks: DataFrame, where: Column | None = None, toxic: int = TOXIC, other: int = OTHER, label: str = "toxic") -> tuple[DataFrame, dict[int, float]]:
    """Distinct texts (h, t, y) of at most ``toxic`` and ``other`` labelled documents, the lowest id hashes of each label,
    and for how many labelled documents one of each label stands."""
    marks = marks.filter(F.col(label).isNotNull() & F.col("doc_id").isNotNull())
    marks = marks.filter(where) if where is not None else marks
    marks = marks.groupBy("doc_id").agg(F.max((F.col(label) > 0).cast("int")).alias("y"))
    total = {r["y"]: r["n"] for r in marks.groupBy("y").agg(F.count("*").alias("n")).collect()}  # two rows
    most = {0: other, 1: toxic}
    parts = [marks.filter(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(n) for y, n in most.items()]
    return distinct_texts(docs, parts[0].union(parts[1])), {y: max(1.0, total.get(y, 0) / n) for y, n in most.items()}


def fit(texts: DataFrame, docs: DataFrame | None = None, k: int = 15, text: str = "text", stands: dict[int, float] | None = None) -> NeighbourModel | None:
    """Learn from rows (h, t, y) of distinct texts; document frequencies are those of ``docs``, else of ``texts``.

    ``stands``: for how many labelled documents a text of each label counts.  The driver gets the terms and a sparse
    vector a text; the number of texts is bounded by ``examples``.
    """

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in by_bytes(batches, "t", BATCH_BYTES):
            number: dict[str, int] = {}
            doc, term, _ = term_counts(text_array(table.column("t")), number)
            both, toxic = np.bincount(term, minlength=len(number)), np.bincount(term, table.column("y").to_numpy()[doc], len(number))
            yield pa.RecordBatch.from_pydict({"w": pa.array(list(number), pa.string()), "n": pa.array(both, pa.int64()), "t": pa.array(toxic.astype(np.int64))})

    n = texts.agg(F.count("*").alias("n"), F.coalesce(F.sum("y"), F.lit(0)).alias("t")).first()
    if not n["n"]:
        return None
    total, toxic = float(n["n"]), float(n["t"])
    by_word = texts.select("t", "y").mapInArrow(spread, "w string, n long, t long").groupBy("w").agg(F.sum("n").alias("n"), F.sum("t").alias("t")).toArrow().sort_by("w")
    words = Terms.of(by_word.column("w").combine_chunks())  # "=" sorts before "^"
    m, a = by_word.column("n").to_numpy().astype(float), by_word.column("t").to_numpy().astype(float)
    expected = m * toxic / total
    z = (a - expected) / np.sqrt(np.maximum(expected * (1 - toxic / total) * (1 - m / total), 1e-9))
    del by_word
    sc = texts.sparkSession.sparkContext
    held = sc.broadcast(words)

    def frequency(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number, rows, df = held.value, 0, np.zeros(len(held.value), np.int64)
        for table in by_bytes(batches, "t", BATCH_BYTES):
            _, term, _ = term_counts(text_array(table.column("t")), number)
            rows += table.num_rows
            df += np.bincount(term, minlength=len(df))
        at = np.flatnonzero(df)
        # The number of documents goes under term -1.
        yield pa.RecordBatch.from_pydict({"i": pa.array(np.append(at, -1), pa.int64()), "n": pa.array(np.append(df[at], rows), pa.int64())})

    if docs is not None:
        counted = docs.select(F.col(text).alias("t")).mapInArrow(frequency, "i long, n long").groupBy("i").agg(F.sum("n").alias("n")).toArrow()
        i, f = counted.column("i").to_numpy(), counted.column("n").to_numpy()
        total = float(f[i < 0].sum())
        m = np.zeros(len(words))
        m[i[i >= 0]] = f[i >= 0]
    scale = np.log1p(total / np.maximum(m, 1)) * (1 + np.abs(z))
    sent = Sent(held, sc.broadcast(scale), None, k, np.zeros(0), np.zeros(1), 0.0)

    def vectorise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in by_bytes(batches, "t", BATCH_BYTES):
            got = sent.model().vectors(text_array(table.column("t")))
            yield pa.RecordBatch.from_pydict({"h": table.column("h").combine_chunks(), "y": table.column("y").combine_chunks(), "w": pa.array([x.astype(np.int32) for x, _ in got], pa.list_(pa.int32())), "v": pa.array([x.astype(np.float32) for _, x in got], pa.list_(pa.float32()))})

    found = texts.mapInArrow(vectorise, "h long, y int, w array<int>, v array<float>").toArrow()
    # Toxic examples are neighbours, so the blocks' largest weights tell them from the others.
    order = np.lexsort((found.column("h").to_numpy(), -found.column("y").to_numpy()))
    label, example_hash = found.column("y").to_numpy().astype(np.int64)[order], found.column("h").to_numpy()[order]
    place = np.empty(len(order), np.int32)
    place[order] = np.arange(len(order))
    example = np.repeat(place, pc.list_value_length(found.column("w")).to_numpy())
    flat_w, flat_v = (pc.list_flatten(found.column(c)).to_numpy() for c in ("w", "v"))
    del found
    index = BlockMaxIndex.build(flat_w, example, flat_v, len(words), len(label))
    del flat_w, flat_v, example
    sent = replace(sent, parts=sc.broadcast((index, label, example_hash)))

    def left_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = sent.model()
        by_hash = np.argsort(own.example_hash)
        for table in by_bytes(batches, "t", BATCH_BYTES):
            at = by_hash[np.searchsorted(own.example_hash, table.column("h").to_numpy(), sorter=by_hash)]
            votes = [vote for vote, _, _ in own.votes(text_array(table.column("t")), skip=at.tolist())]
            yield pa.RecordBatch.from_pydict({"i": pa.array(at, pa.int64()), "vote": pa.array(votes, pa.float64())})

    # Each search is long, so the texts are dealt to all cores.
    spread_out = texts.select("h", "t").repartition(4 * sc.defaultParallelism, "h")
    votes = spread_out.mapInArrow(left_out, "i long, vote double").toArrow().sort_by("i").column("vote").to_numpy()
    count = np.where(label > 0, (stands or {}).get(1, 1.0), (stands or {}).get(0, 1.0))
    alone = votes < 0
    bare = float((label * count)[alone].sum() / max(1.0, count[alone].sum()))
    edges = np.linspace(0, 1, BINS + 1)[1:-1]
    bins = np.searchsorted(edges, votes[~alone], side="right")
    size = np.bincount(bins, count[~alone], BINS)
    hit = np.bincount(bins, (label * count)[~alone], BINS)
    # An empty bin stands for its middle, with little weight.
    level = _pooled(list((hit + 0.5 * (np.arange(BINS) + 0.5) / BINS) / (size + 0.5)), list(size + 0.5))
    return NeighbourModel(words, scale, index, label, example_hash, k, edges, level, bare, replace(sent, edges=edges, level=level, bare=bare))


def scored(docs: DataFrame, model: NeighbourModel | None, threshold: float = 0.7, evidence: int = 3, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key, score, predicted, evidence``: evidence is the nearest examples' text hashes, labels and cosines."""
    kind = docs.schema[key].dataType.simpleString()
    sent = model.sent if model else None
    entry = pa.struct([("example", pa.int64()), ("toxic", pa.int32()), ("cosine", pa.float64())])

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.model() if sent else None
        for table in by_bytes(batches, "t", BATCH_BYTES):
            scores, shown = [], []
            for vote, near, cosine in m.votes(text_array(table.column("t"))) if m else [(-1.0, [], [])] * table.num_rows:
                scores.append(m.calibrated(vote) if m else 0.0)
                shown.append([{"example": int(m.example_hash[e]), "toxic": int(m.label[e]), "cosine": float(c)} for e, c in zip(near[:evidence], cosine[:evidence], strict=True)])
            s = np.array(scores)
            yield pa.RecordBatch.from_arrays([table.column("k").combine_chunks(), pa.array(s, pa.float64()), pa.array((s >= threshold).astype(np.int32)), pa.array(shown, pa.list_(entry))], [key, "score", "predicted", "evidence"])

    return docs.select(F.col(key).alias("k"), F.col(text).alias("t")).mapInArrow(score, f"`{key}` {kind}, score double, predicted int, evidence array<struct<example:long,toxic:int,cosine:double>>")


def learnt(docs: DataFrame, marks: DataFrame, train: Column | None = None, toxic: int = TOXIC, other: int = OTHER) -> NeighbourModel | None:
    """The model of at most ``toxic`` and ``other`` labelled documents that meet ``train``."""
    texts, stands = examples(docs, marks, train, toxic, other)
    return fit(texts, docs, stands=stands)


def toxicity(docs: DataFrame, marks: DataFrame, train: Column | None = None, **options) -> DataFrame:
    """Scores of every row of ``docs``, learnt from labelled documents that meet ``train``."""
    return scored(docs, learnt(docs, marks, train), **options)


def keep_clean(docs: DataFrame, marks: DataFrame, threshold: float = 0.7, text: str = "text") -> DataFrame:
    """The rows of ``docs`` that score below ``threshold``, with its columns."""
    model = learnt(docs, marks)
    sent = model.sent if model else None
    place = docs.columns.index(text)

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.model() if sent else None
        for batch in batches:
            # By place, since other columns may have any name.
            for table in by_bytes(iter([batch.rename_columns([f"c{i}" for i in range(batch.num_columns)])]), f"c{place}", BATCH_BYTES):
                low = [m.calibrated(vote) < threshold for vote, _, _ in m.votes(text_array(table.column(place)))] if m else [True] * table.num_rows
                yield from table.rename_columns(batch.schema.names).filter(pa.array(low, pa.bool_())).to_batches()

    return docs.mapInArrow(keep, docs.schema)
