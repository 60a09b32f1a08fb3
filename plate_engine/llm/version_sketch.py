"""Document fingerprints: invertible Bloom lookup sketches of paragraph digests; DataFrame functions only.

Paragraphs are content-defined: one ends after a word where a hash of it and the word before is a multiple of
``SCALE``, so they are some ``SCALE`` words long in every text, their number grows with the text, and an edit changes only
those it touches.

A sketch has three thirds of cells; a digest falls in one cell of each.  A cell holds the number, the xor of
digests and the xor of their check hashes; empty cells are not kept.  The fingerprint is the sketch of ``SMALLEST``
cells a third.  Subtracting two sketches leaves the digests of one text alone; peeling
takes a cell with one digest, moves the digest to the result and takes it out of its other cells, until
all cells are empty.  If some can't be emptied, both sketches are built again with ``GROWTH`` times the cells, as often as it
takes (``ATTEMPTS`` sizes hold more digests than a text can have); texts whose numbers of digests differ by more than the
first sketch holds start at the size for that.  With a, b digests and d different ones the likeness
is the shared over all: (a + b - d) / (a + b + d), and 1 for two texts without words.

Defined cases: a null text counts as empty; rows of one id are ordered by their text's hash, and rows that
repeat id and text are one document of that order, each returned; null ids come first; a table of one document has
that document as its own next; a paragraph that repeats in a text counts once; other columns are ignored.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import stored
from .quality_rules import WORD_GAP, _let

#: Cells in a third of a fingerprint, how much larger the next try's sketch is (cells not in use take no room), and tries.
SMALLEST, GROWTH, ATTEMPTS = 64, 16, 8
SCALE = 32
PEEL_ROUNDS = 40
CELL = "struct<p:bigint,n:int,x:bigint,c:bigint>"


def word_hashes(text: Column) -> Column:
    return F.transform(F.array_remove(F.split(text, WORD_GAP), ""), lambda w: F.xxhash64(w))


def paragraphs(words: Column, scale: int = SCALE) -> Column:
    """Distinct digests of the paragraphs of an array of word hashes."""

    def cut(w: Column) -> Column:
        def ends_here(i: Column) -> Column:
            pair = F.xxhash64(F.get(w, i - 1), F.get(w, i - 2))
            return (F.pmod(pair, F.lit(scale)) == 0) | (i == F.size(w))

        def digests(ends: Column) -> Column:
            def digest(e: Column, k: Column) -> Column:
                start = F.when(k == 0, 0).otherwise(F.get(ends, k - 1))
                return F.xxhash64(F.slice(w, start + 1, e - start))

            return F.array_distinct(F.transform(ends, digest))

        ends = F.filter(F.sequence(F.lit(1), F.size(w)), ends_here)
        return F.when(F.size(w) > 0, _let(ends, digests)).otherwise(F.array().cast("array<bigint>"))

    # Bound once: an expression inside a lambda is evaluated for every element.
    return _let(words, cut)


def _check(digest: Column) -> Column:
    return F.xxhash64(digest, F.lit("check"))


def _cell(p: Column, n: Column, x: Column, c: Column) -> Column:
    return F.struct(p.cast("long").alias("p"), n.cast("int").alias("n"), x.cast("long").alias("x"), c.cast("long").alias("c"))


def _entries(digest: Column, n: Column, check: Column, cells: Column) -> Column:
    """The three cells that a digest falls in."""
    return F.array(*[_cell(F.lit(t) * cells + F.pmod(F.xxhash64(digest, F.lit(t)), cells), n, digest, check) for t in range(3)])


def _folded(entries: Column) -> Column:
    """Entries of one cell added up, in the order of the cells; cells that come out empty go."""
    zero = F.struct(F.lit(0).alias("n"), F.lit(0).cast("long").alias("x"), F.lit(0).cast("long").alias("c"))

    def added(own: Column) -> Column:
        total = F.aggregate(own, zero, lambda z, e: F.struct((z["n"] + e["n"]).alias("n"), z["x"].bitwiseXOR(e["x"]).alias("x"), z["c"].bitwiseXOR(e["c"]).alias("c")))
        return _let(total, lambda z: _cell(F.get(own, F.lit(0))["p"], z["n"], z["x"], z["c"]))

    def runs(ordered: Column) -> Column:
        def cells(starts: Column) -> Column:
            def cell(at: Column, k: Column) -> Column:
                after = F.coalesce(F.get(starts, k + 1), F.size(ordered))
                return F.when(after == at + 1, F.get(ordered, at)).otherwise(_let(F.slice(ordered, at + 1, after - at), added))

            return F.filter(F.transform(starts, cell), lambda z: (z["n"] != 0) | (z["x"] != 0) | (z["c"] != 0))

        places = F.sequence(F.lit(0), F.size(ordered) - 1)
        begins = F.filter(places, lambda i: (i == 0) | (F.get(ordered, i)["p"] != F.get(ordered, i - 1)["p"]))
        return F.when(F.size(ordered) > 0, _let(begins, cells)).otherwise(F.array().cast(f"array<{CELL}>"))

    return _let(F.sort_array(entries), runs)


def sketch(digests: Column, cells: Column) -> Column:
    """The cells in use (p, n, x, c) of ``3 * cells``, of an array of distinct digests."""
    return _folded(F.flatten(F.transform(digests, lambda d: _entries(d, F.lit(1), _check(d), cells))))


def subtracted(a: Column, b: Column) -> Column:
    return _folded(F.concat(a, F.transform(b, lambda z: _cell(z["p"], -z["n"], z["x"], z["c"]))))


def peeled(difference: Column, cells: Column) -> Column:
    """struct(left, found): what is left of the cells, and the recovered (side n: 1 or -1, digest x)."""
    start = F.struct(difference.alias("left"), F.array().cast("array<struct<n:int,x:bigint>>").alias("found"), F.lit(False).alias("done"))

    def step(acc: Column, _round: Column) -> Column:
        pure = F.filter(acc["left"], lambda z: (F.abs(z["n"]) == 1) & (_check(z["x"]) == z["c"]))

        def take_out(single: Column) -> Column:
            gone = F.flatten(F.transform(single, lambda z: _entries(z["x"], -z["n"], _check(z["x"]), cells)))
            return F.when(F.size(single) == 0, F.struct(acc["left"].alias("left"), acc["found"].alias("found"), F.lit(True).alias("done"))).otherwise(
                F.struct(_folded(F.concat(acc["left"], gone)).alias("left"), F.concat(acc["found"], single).alias("found"), F.lit(False).alias("done"))
            )

        singles = F.array_distinct(F.transform(pure, lambda z: F.struct(z["n"].alias("n"), z["x"].alias("x"))))
        return F.when(acc["done"], acc).otherwise(_let(singles, take_out))

    return F.aggregate(F.sequence(F.lit(1), F.lit(PEEL_ROUNDS)), start, step)


def recovered(a: Column, b: Column) -> Column:
    """The digests (n, x) that the sets a and b don't share, by sketches of the size that suffices."""

    def attempt(acc: Column, _try: Column) -> Column:
        cells = acc["cells"]

        def judged(p: Column) -> Column:
            return F.when(F.size(p["left"]) == 0, F.struct(cells.alias("cells"), p["found"].alias("found"), F.lit(True).alias("done"))).otherwise(
                F.struct((cells * GROWTH).alias("cells"), acc["found"].alias("found"), F.lit(False).alias("done"))
            )

        return F.when(acc["done"], acc).otherwise(_let(peeled(subtracted(sketch(a, cells), sketch(b, cells)), cells), judged))

    # A sketch of m cells a third can give back fewer than 3 m digests.
    growths = F.greatest(F.lit(0.0), F.ceil(F.log2(F.greatest(F.abs(F.size(a) - F.size(b)), F.lit(1)) / (3 * SMALLEST)) / math.log2(GROWTH)))
    first = (SMALLEST * F.pow(F.lit(float(GROWTH)), growths)).cast("long")
    start = F.struct(first.alias("cells"), F.array().cast("array<struct<n:int,x:bigint>>").alias("found"), F.lit(False).alias("done"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(ATTEMPTS)), start, attempt, lambda acc: acc["found"])


def likeness(a: Column, b: Column) -> Column:
    total = F.size(a) + F.size(b)

    def share(x: Column) -> Column:
        return F.when(total == 0, 1.0).otherwise((total - F.size(x)) / (total + F.size(x)))

    return _let(recovered(a, b), share)


def serialised(digests: Column) -> Column:
    """The fingerprint as text: scale, cells, number of digests, then cell, number, digest and check of every cell in use."""
    cells = F.transform(sketch(digests, F.lit(SMALLEST).cast("long")), lambda z: F.concat_ws(":", z["p"], z["n"], F.hex(z["x"]), F.hex(z["c"])))
    return F.concat(F.lit(f"{SCALE}/{3 * SMALLEST}/"), F.size(digests).cast("string"), F.lit("/"), F.array_join(cells, ","))


def _followers(docs: DataFrame, key: str) -> DataFrame:
    """``key, h, next_key, next_h, n, times`` in ascending order of key and text hash; the last is followed by the first.

    The order is by range partitions; only ids move, each partition's ends are joined by a table of one row
    a partition.
    """
    ids = docs.select(F.col(key).alias("k"), "h", F.length("t").alias("n")).groupBy("k", "h", "n").agg(F.count("*").alias("times")).repartitionByRange("k", "h")
    ids = stored(ids.withColumn("p", F.spark_partition_id()), "ids")
    ends = ids.groupBy("p").agg(F.min(F.struct("k", "h")).alias("first"))
    over = Window.orderBy("p")
    heads = ends.select("p", F.coalesce(F.lead("first").over(over), F.first("first").over(over)).alias("after"))
    inside = ids.withColumn("next", F.lead(F.struct("k", "h")).over(Window.partitionBy("p").orderBy("k", "h")))
    found = inside.join(F.broadcast(heads), "p").withColumn("next", F.coalesce("next", "after"))
    return stored(found.select("k", "h", "n", "times", F.col("next.k").alias("next_k"), F.col("next.h").alias("next_h")), "followers")


def versions(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Every document with its sketch, that of its edited text, and their likenesses."""
    rows = docs.select(F.col(key).alias("k"), F.coalesce(F.col(text), F.lit("")).alias("t")).withColumn("h", F.xxhash64("t"))
    order = _followers(rows, "k")
    same = lambda a, b: reduce(lambda x, y: x & y, [F.col(p).eqNullSafe(F.col(q)) for p, q in zip(a, b, strict=True)])
    # To the document before it, each one sends its first half-length of text and its paragraphs.
    sends = order.select(F.col("k").alias("before_k"), F.col("h").alias("before_h"), F.col("n").alias("before_n"), F.col("next_k").alias("k0"), F.col("next_h").alias("h0"))
    sent = rows.join(sends, same(["k", "h"], ["k0", "h0"])).select("before_k", "before_h", F.substring("t", F.lit(1), F.floor(F.col("before_n") / 2).cast("int")).alias("head"), paragraphs(word_hashes(F.col("t"))).alias("next"))
    if order.filter("times > 1").take(1):
        sent = sent.dropDuplicates(["before_k", "before_h"])
    both = rows.join(sent, same(["k", "h"], ["before_k", "before_h"]))
    n = F.length("t")
    edited = F.concat(F.substring("t", F.lit(1), n - F.floor(n / 2).cast("int")), F.col("head"))
    both = both.select("k", "t", "next", n.alias("n"), edited.alias("e"))
    both = both.select("k", "n", "next", F.sha2(F.col("e").cast("binary"), 256).alias("sha"), paragraphs(word_hashes(F.col("t"))).alias("a"), paragraphs(word_hashes(F.col("e"))).alias("b"))
    return both.select(
        F.col("k").alias(key),
        F.col("n").cast("long").alias("n_chars"),
        F.col("sha").alias("edited_sha256"),
        serialised(F.col("a")).alias("fingerprint"),
        serialised(F.col("b")).alias("edited_fingerprint"),
        likeness(F.col("a"), F.col("b")).alias("near_edited"),
        likeness(F.col("a"), F.col("next")).alias("near_next"),
    )
