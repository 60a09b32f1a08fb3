"""Katz backoff language model over words, bigram to unigram to unknown word.

Counts are Good-Turing discounted (counts up to 5, from the counts of counts of each order).  The mass that a
history's seen successors give up goes to the unseen ones in proportion to their unigram probability, with the exact
weight ``(1 - sum of discounted bigrams) / (1 - sum of the unigrams of seen successors)``, so each
history's probabilities sum to 1.  At the unigram level the mass given up is the probability of one unknown word.
A history unknown to training, or a text's unknown word, is scored by the level below, recursively.

Everything that grows with the corpus travels as packed arrays, one row a block of texts and slice of
the vocabulary (or bucket of bigrams), and is kept in tables partitioned by kind:

1. blocks: texts become word numbers of the block; its distinct words go to their slice with counts;
2. a slice adds them up, numbers the words that training holds and answers every block;
3. a block sends its distinct bigrams to the bucket of their history, those of hot histories (over 1/2000
   of the tokens) to the bucket of both words, so no task gets a whole hot history;
4. a bucket adds them up and answers with counts; with the global counts of counts known it
   answers with backoff weights; sums of hot histories, at most 2000, are completed on the driver;
5. a block scores its texts from the answers.

Defined cases: a null text counts as empty and is scored as its end token; repeated rows are trained on and
scored each; without training rows all counts are 0 and every token is the unknown word of probability 1;
other columns are ignored.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import by_bytes, ragged, stored, text_array

DISCOUNTED = 5
#: Histories of over 1/HOT_SHARE of the tokens, and HOT_LEAST, are spread over buckets.
HOT_SHARE, HOT_LEAST = 2000, 1000
BATCH_BYTES = 6 << 20
#: Text for which one more slice is made, so that what one task holds doesn't grow with the corpus.
SLICE_BYTES = 32 << 20
END = np.uint64(0)
UNKNOWN, START = -2, -1
ROW = "kind string, block long, part long, payload binary"


def pack(*arrays: np.ndarray) -> bytes:
    """Whole-number or float arrays, whole ones at the least width, their first bytes together, then their second
    ones and so on, compressed."""
    out = []
    for a in arrays:
        if a.dtype.kind in "iu" and a.dtype != np.uint64 and len(a):
            a = a.astype(np.result_type(np.min_scalar_type(a.min()), np.min_scalar_type(a.max())))
        planes = np.ascontiguousarray(a).view(np.uint8).reshape(len(a), a.dtype.itemsize).T
        out.append(struct.pack("<4sQ", a.dtype.str.encode().ljust(4), len(a)) + planes.tobytes())
    return zstandard.ZstdCompressor(level=1).compress(b"".join(out))


def unpack(payload: bytes) -> list[np.ndarray]:
    data, at, out = zstandard.ZstdDecompressor().decompress(payload), 0, []
    while at < len(data):
        kind, n = struct.unpack_from("<4sQ", data, at)
        dtype = np.dtype(kind.decode().strip())
        planes = np.frombuffer(data, np.uint8, n * dtype.itemsize, at + 12).reshape(dtype.itemsize, n)
        a = np.ascontiguousarray(planes.T).view(dtype).ravel()
        at += 12 + planes.nbytes
        out.append(a if a.dtype.kind == "f" or a.dtype == np.uint64 else a.astype(np.int64))
    return out


def _rows(rows: list[tuple]) -> pa.Table:
    kind, block, part, payload = zip(*rows, strict=True) if rows else ((), (), (), ())
    return pa.table([pa.array(kind, pa.string()), pa.array(block, pa.int64()), pa.array(part, pa.int64()), pa.array(payload, pa.binary())], ["kind", "block", "part", "payload"])


@dataclass
class Discounts:
    """Good-Turing discounts of one order from its counts of counts (index 0 unused)."""

    factor: np.ndarray
    empty: bool

    @classmethod
    def of(cls, n: np.ndarray) -> Discounts:
        n = n.astype(float)
        factor = np.ones(DISCOUNTED + 2)
        r = np.arange(1, DISCOUNTED + 1)
        if n[1] > 0:
            common = (DISCOUNTED + 1) * n[DISCOUNTED + 1] / n[1]
            with np.errstate(divide="ignore", invalid="ignore"):
                factor[1 : DISCOUNTED + 1] = ((r + 1) * n[r + 1] / (r * n[r]) - common) / (1 - common)
        seen = n[r] > 0
        good = factor[r][seen]
        if not (np.isfinite(good).all() and (good > 0).all() and (good < 1).all()):
            factor[r] = (r - 0.5) / r  # too few counts for the estimate: half a count is given up
        return cls(factor, not seen.any())

    def discounted(self, count: np.ndarray) -> np.ndarray:
        return count * self.factor[np.minimum(count, DISCOUNTED + 1)]


@dataclass
class Unigrams:
    total: int
    distinct: int
    discounts: Discounts
    unknown: float

    @classmethod
    def of(cls, total: int, distinct: int, n: np.ndarray, kept: float) -> Unigrams:
        """kept: the sum of all discounted counts."""
        discounts = Discounts.of(n)
        return cls(total, distinct, discounts, (total - kept) / total if total and kept < total else (1.0 if not total else 1.0 / (total + 1)))

    def probability(self, count: np.ndarray) -> np.ndarray:
        if not self.total:
            return np.ones(len(count))
        p = self.discounts.discounted(count) / self.total
        if self.discounts.empty:
            p = p * self.total / (self.total + 1)
        return np.where(count > 0, p, self.unknown)


def _word_key(table: pa.Array) -> np.ndarray:
    import xxhash

    got = np.array([xxhash.xxh64_intdigest(w) for w in table.cast(pa.binary()).to_pylist()], np.uint64)
    got[got == END] = 1
    return got


def _blocks(slices: int):
    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = TaskContext.get().partitionId() << 32
        for seq, table in enumerate(by_bytes(batches, "t", BATCH_BYTES)):
            texts = pc.ascii_lower(text_array(table.column("t")))
            pieces = pc.ascii_split_whitespace(texts)
            filled = pc.binary_length(pieces.values).to_numpy() > 0
            edges = np.concatenate([[0], np.cumsum(filled)])[pieces.offsets.to_numpy()]
            coded = pieces.values.filter(pa.array(filled)).dictionary_encode()
            n = np.diff(edges) + 1
            tokens = np.zeros(int(n.sum()), np.int64)  # word 0 is the end
            tokens[ragged(np.cumsum(n) - n, n - 1)] = coded.indices.to_numpy() + 1
            key = np.concatenate([[END], _word_key(coded.dictionary)]).astype(np.uint64)
            train = table.column("train").to_numpy().astype(np.int64)
            count = np.bincount(tokens, np.repeat(train, n), len(key)).astype(np.int64)
            part = (key % np.uint64(slices)).astype(np.int64)
            block = first + seq
            ids = pa.record_batch([table.column("k").combine_chunks()], ["k"])
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, ids.schema) as out:
                out.write_batch(ids)
            named = sink.getvalue().to_pybytes()
            rows = [("block", block, -1, struct.pack("<Q", len(named)) + named + pack(train, n, tokens, part))]
            for s in np.unique(part):
                own = part == s
                rows.append(("words", block, int(s), pack(key[own], count[own])))
            yield from _rows(rows).to_batches()

    return cut


def _histogram(count: np.ndarray) -> np.ndarray:
    return np.bincount(np.minimum(count[count > 0], DISCOUNTED + 2), minlength=DISCOUNTED + 3)


def _number_words(slices: int):
    def number(key: tuple, table: pa.Table) -> pa.Table:
        part = key[0].as_py()
        got = [unpack(x) for x in table.column("payload").to_pylist()]
        words, inverse = np.unique(np.concatenate([g[0] for g in got]), return_inverse=True)
        count = np.bincount(inverse, np.concatenate([g[1] for g in got])).astype(np.int64)
        known = count > 0
        ids = np.where(known, (np.cumsum(known) - 1) * slices + part, UNKNOWN)
        rows = [("table", -1, part, pack(words[known], count[known])), ("stats", -1, part, pack(_histogram(count), np.array([count.sum(), known.sum()])))]
        at = 0
        for block, g in zip(table.column("block").to_pylist(), got, strict=True):
            own = inverse[at : at + len(g[0])]
            at += len(g[0])
            rows.append(("ids", block, part, pack(ids[own], count[own])))
        return _rows(rows)

    return number


def _answers(table: pa.Table, kind: str) -> dict[int, list[np.ndarray]]:
    own = table.filter(pc.equal(table.column("kind"), kind))
    return {p: unpack(x) for p, x in zip(own.column("part").to_pylist(), own.column("payload").to_pylist(), strict=True)}


@dataclass
class _Block:
    """A block with the ids and counts of its words, and its distinct known bigrams by bucket."""

    docs: pa.ChunkedArray
    n: np.ndarray
    tokens: np.ndarray
    word_id: np.ndarray
    word_count: np.ndarray
    bucket: np.ndarray
    first: np.ndarray
    second: np.ndarray
    trained: np.ndarray
    of_token: np.ndarray
    part: np.ndarray

    @classmethod
    def of(cls, payload: bytes, ids: dict[int, list[np.ndarray]], slices: int, hot: int) -> _Block:
        (named,) = struct.unpack_from("<Q", payload)
        docs = pa.ipc.open_stream(payload[8 : 8 + named]).read_all().column("k")
        train, n, tokens, part = unpack(payload[8 + named :])
        word_id, word_count = np.full(len(part) + 1, START), np.zeros(len(part) + 1, np.int64)
        for s, (own, count) in ids.items():
            at = np.flatnonzero(part == s)
            word_id[at], word_count[at] = own, count
        before = np.concatenate([[0], tokens[:-1]])
        before[np.cumsum(n) - n] = len(part)
        pair = before * (len(part) + 1) + tokens
        known = (word_id[before] != UNKNOWN) & (word_id[tokens] != UNKNOWN)
        code, inverse = np.unique(pair[known], return_inverse=True)
        of_token = np.full(len(tokens), -1)
        of_token[known] = inverse
        first, second = code // (len(part) + 1), code % (len(part) + 1)
        trained = np.bincount(inverse, np.repeat(train, n)[known], len(code)).astype(np.int64)
        del pair, inverse, before, known
        spread = (word_id[first] == START) | (word_count[first] > hot)
        bucket = np.where(spread, (word_id[first] * 7919 + word_id[second] * 104729) % slices, word_id[first] % slices)
        return cls(docs, n, tokens, word_id, word_count, bucket, first, second, trained, of_token, part)


def _send_pairs(slices: int, hot: int):
    def send(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        b = _Block.of(left.column("payload")[0].as_py(), _answers(right, "ids"), slices, hot)
        rows = []
        for s in np.unique(b.bucket):
            own = b.bucket == s
            rows.append(("pairs", key[0].as_py(), int(s), pack(b.word_id[b.first[own]], b.word_id[b.second[own]], b.trained[own], b.word_count[b.second[own]], b.word_count[b.first[own]])))
        return _rows(rows)

    return send


def _count_pairs(key: tuple, table: pa.Table) -> pa.Table:
    part = key[0].as_py()
    got = [unpack(x) for x in table.column("payload").to_pylist()]
    first, second, trained, count2, count1 = (np.concatenate([g[k] for g in got]) for k in range(5))
    order = np.lexsort((second, first))
    a, b = first[order], second[order]
    lead = np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])])
    group = np.cumsum(lead) - 1
    count = np.bincount(group, trained[order]).astype(np.int64)
    total = np.empty(len(first), np.int64)
    total[order] = count[group]
    at = np.flatnonzero(lead)
    seen = count > 0
    rows = [("table", -1, part, pack(a[at][seen], b[at][seen], count[seen], count2[order][at][seen], count1[order][at][seen])), ("stats", -1, part, pack(_histogram(count)))]
    start = 0
    for block, g in zip(table.column("block").to_pylist(), got, strict=True):
        rows.append(("counts", block, part, pack(total[start : start + len(g[0])])))
        start += len(g[0])
    return _rows(rows)


def backoff_weight(history_count: np.ndarray, kept: np.ndarray, lower: np.ndarray) -> np.ndarray:
    """(mass left by discounted successors) / (unigram mass of unseen words)."""
    return (1 - kept / history_count) / np.maximum(1 - lower, 1e-300)


def log_weight(total: np.ndarray, kept: np.ndarray, lower: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """log10 backoff weights, and 1 for histories whose successors are all too frequent to give anything up:
    these count as seen once more than they were, and their successors share less than 1."""
    whole = kept >= total * (1 - 1e-12)
    return np.log10(backoff_weight(total, np.where(whole, total * total / (total + 1), kept), lower)), whole.astype(np.int64)


def _history_sums(table: list[np.ndarray], bigrams: Discounts, unigrams: Unigrams) -> tuple[np.ndarray, ...]:
    first, _, count, count2, count1 = table
    history, at, group = np.unique(first, return_index=True, return_inverse=True)
    return history, count1[at], np.bincount(group, count), np.bincount(group, bigrams.discounted(count)), np.bincount(group, unigrams.probability(count2))


def _weigh(hot: int, unigrams: Unigrams, bigrams: Discounts):
    def weigh(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        rows = []
        history, weight, whole = np.zeros(0, np.int64), np.zeros(0), np.zeros(0, np.int64)
        for payload in left.column("payload").to_pylist():
            history, c1, total, kept, lower = _history_sums(unpack(payload), bigrams, unigrams)
            own = (history != START) & (c1 <= hot)
            history = history[own]
            weight, whole = log_weight(total[own], kept[own], lower[own])
        for block, payload in zip(right.column("block").to_pylist(), right.column("payload").to_pylist(), strict=True):
            ids = unpack(payload)[0]
            answer, flag = np.zeros(len(ids)), np.zeros(len(ids), np.int64)
            if len(history):
                at = np.minimum(np.searchsorted(history, ids), len(history) - 1)
                hit = history[at] == ids
                answer[hit], flag[hit] = weight[at[hit]], whole[at[hit]]
            rows.append(("weights", block, key[0].as_py(), pack(answer, flag)))
        return _rows(rows)

    return weigh


def _hot_sums(hot: int, unigrams: Unigrams, bigrams: Discounts):
    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for payload in batch.column("payload").to_pylist():
                history, c1, total, kept, lower = _history_sums(unpack(payload), bigrams, unigrams)
                own = (history == START) | (c1 > hot)
                yield pa.RecordBatch.from_arrays([pa.array(x[own]) for x in (history, total, kept, lower)], ["history", "total", "kept", "lower"])

    return sums


def _score(slices: int, hot: int, unigrams: Unigrams, bigrams: Discounts, hot_weight: dict[int, tuple[float, int]], starts: int):
    def score(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        b = _Block.of(left.column("payload")[0].as_py(), _answers(right, "ids"), slices, hot)
        weight, generous = np.zeros(len(b.word_id)), np.zeros(len(b.word_id), np.int64)
        for s, (own, whole) in _answers(right, "weights").items():
            at = np.flatnonzero(b.part == s)
            weight[at], generous[at] = own, whole
        for i in np.flatnonzero((b.word_count > hot) | (b.word_id == START)):
            weight[i], generous[i] = hot_weight.get(int(b.word_id[i]), (0.0, 0))
        counts = np.zeros(len(b.first), np.int64)
        for s, (own,) in _answers(right, "counts").items():
            counts[b.bucket == s] = own
        lower = np.log10(unigrams.probability(b.word_count))
        history = np.where(b.word_id[b.first] == START, starts, b.word_count[b.first])
        kept = bigrams.discounted(counts).astype(float)
        with np.errstate(divide="ignore"):
            seen = np.log10(kept / np.maximum(history + generous[b.first], 1))
        before = np.concatenate([[0], b.tokens[:-1]])
        before[np.cumsum(b.n) - b.n] = len(b.part)
        value = weight[before] + lower[b.tokens]
        has = b.of_token >= 0
        pair = b.of_token[has]
        value[has] = np.where(counts[pair] > 0, seen[pair], value[has])
        ends = np.cumsum(b.n)
        totals = lambda x: np.add.reduceat(x, ends - b.n)
        c = b.word_count[b.tokens]
        base = np.log10((c + 1) / (unigrams.total + unigrams.distinct + 1))
        return pa.table({"doc_id": b.docs, "n_tokens": pa.array(b.n), "n_known": pa.array(totals((c > 0).astype(np.int64))), "base_score": pa.array(totals(base)), "score": pa.array(totals(value))})

    return score


def katz_scores(docs: DataFrame, train: Column, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, n_tokens, n_known, train_tokens, base_score, score`` of every row, from the rows that meet ``train``."""
    spark = docs.sparkSession
    volume = docs.agg(F.coalesce(F.sum(F.octet_length(F.col(text))), F.lit(0)).alias("bytes")).first()["bytes"]
    slices = max(16, 2 * int(spark.conf.get("spark.sql.shuffle.partitions")), -(-volume // SLICE_BYTES))
    rows = docs.select(F.col(key).alias("k"), F.col(text).alias("t"), F.coalesce(train, F.lit(False)).cast("int").alias("train"))
    cut = stored(rows.mapInArrow(_blocks(slices), ROW), "lm-blocks", ["kind"])
    blocks = cut.filter("kind = 'block'")
    words = stored(cut.filter("kind = 'words'").groupBy("part").applyInArrow(_number_words(slices), ROW), "lm-words", ["kind"])
    stats = [unpack(r["payload"]) for r in words.filter("kind = 'stats'").select("payload").collect()]  # a row a slice
    n1 = sum((s[0] for s in stats), np.zeros(DISCOUNTED + 3, np.int64))
    total, distinct = (int(sum(s[1][k] for s in stats)) for k in range(2))
    discounts = Discounts.of(n1)
    small = np.arange(1, DISCOUNTED + 1)
    given_up = float((n1[small] * (small - discounts.discounted(small))).sum())
    unigrams = Unigrams.of(total, distinct, n1, total - given_up)
    hot = max(HOT_LEAST, total // HOT_SHARE)
    ids = words.filter("kind = 'ids'")
    by_block = lambda x, y: x.groupBy("block").cogroup(y.groupBy("block"))
    pairs = by_block(blocks, ids).applyInArrow(_send_pairs(slices, hot), ROW)
    counted = stored(pairs.groupBy("part").applyInArrow(_count_pairs, ROW), "lm-bigrams", ["kind"])
    stats = [unpack(r["payload"]) for r in counted.filter("kind = 'stats'").select("payload").collect()]
    bigrams = Discounts.of(sum((s[0] for s in stats), np.zeros(DISCOUNTED + 3, np.int64)))
    tables = counted.filter("kind = 'table'")
    sums = tables.select("payload").mapInArrow(_hot_sums(hot, unigrams, bigrams), "history long, total double, kept double, lower double").groupBy("history").agg(*[F.sum(c).alias(c) for c in ("total", "kept", "lower")]).collect()
    hot_weight = {r["history"]: tuple(x.item() for x in log_weight(*[np.float64(r[c]) for c in ("total", "kept", "lower")])) for r in sums}
    starts = next((int(r["total"]) for r in sums if r["history"] == START), 0)
    weights = tables.groupBy("part").cogroup(ids.groupBy("part")).applyInArrow(_weigh(hot, unigrams, bigrams), ROW)
    answers = ids.select("kind", "block", "part", "payload").unionByName(counted.filter("kind = 'counts'")).unionByName(weights)
    scored = by_block(blocks, answers).applyInArrow(_score(slices, hot, unigrams, bigrams, hot_weight, starts), f"doc_id {docs.schema[key].dataType.simpleString()}, n_tokens long, n_known long, base_score double, score double")
    return scored.select(F.col("doc_id").alias(key), "n_tokens", "n_known", F.lit(total).cast("long").alias("train_tokens"), "base_score", "score")
