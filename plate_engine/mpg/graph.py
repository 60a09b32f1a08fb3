"""The message-passing graph, its ids, its partitionings and their measures."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..runtime.loop import checkpointed
from ..sources.text import dense_index

PRIME = 2147483647
STRATEGIES = ("1d", "2d", "rvc", "crvc", "tailored", "root_range")


@dataclass(frozen=True)
class Interval:
    """Consecutive ids of one variable's instances."""

    rv: str
    lo: int
    size: int

    @property
    def hi(self) -> int:
        return self.lo + self.size - 1


def assign_ids(sizes: dict[str, int]) -> dict[str, Interval]:
    """Adjacent intervals in the given order; variables of one plate should follow each other."""
    out, lo = {}, 0
    for rv, n in sizes.items():
        out[rv] = Interval(rv, lo, n)
        lo += n
    return out


def id_to_rv(df: DataFrame, column: str, ids: dict[str, Interval]) -> DataFrame:
    case = F.lit(None).cast("string")
    for i in ids.values():
        case = F.when(F.col(column).between(i.lo, i.hi), i.rv).otherwise(case)
    return df.withColumn("rv", case)


def sibling_id(column: Column, source: Interval, target: Interval) -> Column:
    """The id of the member of the same plate: an offset, no join."""
    return column + (target.lo - source.lo)


def mix(v: Column) -> Column:
    """A hash without overflow, the same in any engine with 64-bit numbers."""
    p = F.lit(PRIME)
    v = F.pmod(F.pmod(v, p) * 48271 + 12345, p)
    v = F.pmod(v * v + v, p)
    v = F.pmod(v * 40692 + 7, p)
    return F.pmod(v * v + 3 * v, p)


def mix_sql(v: str) -> str:
    v = f"((({v}) % {PRIME} * 48271 + 12345) % {PRIME})"
    v = f"(({v} * {v} + {v}) % {PRIME})"
    v = f"(({v} * 40692 + 7) % {PRIME})"
    return f"(({v} * {v} + 3 * {v}) % {PRIME})"


@dataclass
class MessageGraph:
    """Topic-model shape: x and z per observation, theta per group, phi per component."""

    tokens: DataFrame
    ids: dict[str, Interval]
    components: int

    @classmethod
    def of(cls, observations: DataFrame, group: str, order: list[str], components: int) -> MessageGraph:
        groups = dense_index(observations.select(group).distinct(), [group], "g")
        tokens = dense_index(observations.select(group, *[c for c in order if c != group]), order, "i").join(groups, group).select("i", "g")
        n, d = tokens.count(), groups.count()
        return cls(tokens, assign_ids({"x": n, "z": n, "theta": d, "phi": components}), components)

    def vertices(self) -> DataFrame:
        spark = self.tokens.sparkSession
        parts = [self.tokens.select((F.col("i") + self.ids[rv].lo).alias("vid"), F.lit(rv).alias("rv"), F.col("i").alias("idx")) for rv in ("x", "z")]
        parts.append(self.tokens.select("g").distinct().select((F.col("g") + self.ids["theta"].lo).alias("vid"), F.lit("theta").alias("rv"), F.col("g").alias("idx")))
        parts.append(spark.range(self.components).select((F.col("id") + self.ids["phi"].lo).alias("vid"), F.lit("phi").alias("rv"), F.col("id").alias("idx")))
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out

    def edges(self) -> DataFrame:
        """``src, dst, etype, root``: parent to child; root is the group's number.  N(K + 2) rows, for analysis only."""
        x, z = F.col("i") + self.ids["x"].lo, F.col("i") + self.ids["z"].lo
        links = [F.struct((F.col("g") + self.ids["theta"].lo).alias("src"), z.alias("dst"), F.lit("theta-z").alias("etype")), F.struct(z.alias("src"), x.alias("dst"), F.lit("z-x").alias("etype"))]
        links += [F.struct(F.lit(self.ids["phi"].lo + k).cast("long").alias("src"), x.alias("dst"), F.lit("phi-x").alias("etype")) for k in range(self.components)]
        return self.tokens.select(F.explode(F.array(*links)).alias("e"), F.col("g").alias("root")).select("e.*", "root")


def orient_edges(edges: DataFrame, partitions: int, cluster_by: str = "dst") -> DataFrame:
    """Edges placed and sorted by the end that receives, so that messages of one kind are a run of rows."""
    return edges.repartition(partitions, cluster_by).sortWithinPartitions(cluster_by)


def partition_ids(edges: DataFrame, ids: dict[str, Interval], strategy: str, m: int) -> DataFrame:
    """``edges`` with the partition ``pid`` of each, as plain column arithmetic."""
    src, dst = F.col("src"), F.col("dst")
    if strategy == "1d":
        pid = F.pmod(mix(src), F.lit(m))
    elif strategy == "2d":
        side = math.isqrt(m)
        pid = F.pmod(mix(src), F.lit(side)) * side + F.pmod(mix(dst), F.lit(side))
    elif strategy in ("rvc", "crvc"):
        a, b = (src, dst) if strategy == "rvc" else (F.least(src, dst), F.greatest(src, dst))
        pid = F.pmod(mix(mix(a) + mix(b + 1000003)), F.lit(m))
    elif strategy == "tailored":
        pid = _tailored(edges, ids, m)
    elif strategy == "root_range":
        pid = F.floor(F.col("root") * m / ids["theta"].size).cast("long")
    else:
        raise ValueError(f"{strategy!r} isn't one of {STRATEGIES}")
    return edges.withColumn("pid", pid.cast("long"))


def _tailored(edges: DataFrame, ids: dict[str, Interval], m: int) -> Column:
    """The end whose variable has more vertices decides: its interval is cut into m equal ranges."""

    def looked_up(c: Column, f) -> Column:
        case = F.lit(None).cast("long")
        for i in ids.values():
            case = F.when(c.between(i.lo, i.hi), F.lit(f(i)).cast("long")).otherwise(case)
        return case

    src, dst = F.col("src"), F.col("dst")
    larger = looked_up(src, lambda i: i.size) > looked_up(dst, lambda i: i.size)
    end = F.when(larger, src).otherwise(dst)
    lo = F.when(larger, looked_up(src, lambda i: i.lo)).otherwise(looked_up(dst, lambda i: i.lo))
    size = F.when(larger, looked_up(src, lambda i: i.size)).otherwise(looked_up(dst, lambda i: i.size))
    return F.expr("0") + F.floor((end - lo) * m / size)


def placed(edges: DataFrame, m: int) -> DataFrame:
    """Edges physically in the partition that ``pid`` names."""
    return edges.repartitionById(m, F.col("pid").cast("int"))


def replicas(edges: DataFrame) -> DataFrame:
    """``vid, n``: in how many partitions a vertex is needed."""
    both = edges.select(F.explode(F.array("src", "dst")).alias("vid"), "pid").distinct()
    return both.groupBy("vid").agg(F.count("*").alias("n"))


def partition_loads(edges: DataFrame) -> DataFrame:
    """``pid, n``: vertices of each partition."""
    both = edges.select("pid", F.explode(F.array("src", "dst")).alias("vid")).distinct()
    return both.groupBy("pid").agg(F.count("*").alias("n"))


def expected_replicas(strategy: str, m: int, k: int) -> float:
    if strategy in ("tailored", "root_range"):
        return 1.0
    side = math.isqrt(m) if strategy == "2d" else m
    return side * (1 - (1 - 1 / side) ** (k + 1))


def expected_replicas_column(strategy: Column, m: Column, k: Column) -> Column:
    """``expected_replicas`` of columns."""
    side = F.when(strategy == "2d", F.floor(F.sqrt(m))).otherwise(m).cast("double")
    return F.when(strategy.isin("tailored", "root_range"), F.lit(1.0)).otherwise(side * (1 - F.pow(1 - 1 / side, k + 1)))


def largest_partition_column(strategy: Column, n: Column, m: Column, k: Column) -> Column:
    """``largest_partition_bound`` of columns."""
    side = F.floor(F.sqrt(m)).cast("double")
    spread = lambda parts: 1 - F.pow(1 - 1 / parts, k + 1)
    found = F.when(strategy == "1d", n.cast("double")).when(strategy == "2d", n / side * spread(side)).when(strategy.isin("rvc", "crvc"), n * spread(m.cast("double")))
    return found.otherwise((3 * F.ceil(n / m) + k).cast("double"))


def largest_partition_bound(strategy: str, n: int, m: int, k: int) -> float:
    if strategy == "1d":
        return float(n)
    if strategy == "2d":
        side = math.isqrt(m)
        return n / side * (1 - (1 - 1 / side) ** (k + 1))
    if strategy in ("rvc", "crvc"):
        return n * (1 - (1 - 1 / m) ** (k + 1))
    return float(3 * -(-n // m) + k)


#: Classes of replicas and of the largest partition for K = O(1) and K = O(M).
ASYMPTOTIC = [
    ("1d", "O(1)", "O(K)", "O(N)"), ("2d", "O(1)", "O(K)", "O(K N / M)"), ("rvc", "O(1)", "O(K)", "O(K N / M)"), ("crvc", "O(1)", "O(K)", "O(K N / M)"), ("tailored", "O(1)", "1", "3 N / M + K"),
    ("1d", "O(M)", "O(M)", "O(N)"), ("2d", "O(M)", "O(sqrt(M))", "O(sqrt(M) N / M)"), ("rvc", "O(M)", "O(M)", "O(N)"), ("crvc", "O(M)", "O(M)", "O(N)"), ("tailored", "O(M)", "1", "3 N / M + K"),
]


def asymptotic_table(observations: DataFrame, group: str, key: str, partitions: tuple[int, ...], few: int) -> DataFrame:
    """The classes with the expected replicas and the bound of the largest partition for the observations of a table.

    K = O(1) is taken as ``few`` components and K = O(M) as one a partition.
    """
    spark = observations.sparkSession
    rows = [(*r, m, few if r[1] == "O(1)" else m) for r in ASYMPTOTIC for m in partitions]
    classes = spark.createDataFrame(rows, "strategy string, k string, replicas string, largest string, m int, components int")
    size = observations.filter(F.col(group).isNotNull() & F.col(key).isNotNull()).agg(F.count("*").alias("n"))
    s, m, k = F.col("strategy"), F.col("m"), F.col("components")
    found = F.broadcast(classes).crossJoin(size)
    return found.select("strategy", "k", "replicas", "largest", "m", "n", F.round(expected_replicas_column(s, m, k), 6).alias("expected"), F.round(largest_partition_column(s, F.col("n"), m, k), 3).alias("bound"))


def starved_messages(graph: MessageGraph, changed: str = "phi") -> DataFrame:
    """Messages that a round lacks where only vertices that changed last may send: ``needed, sent, starved`` by kind.

    A component's update pulls from x and, through x, from z; if only ``changed`` sends, z's part never arrives.
    """
    both = graph.edges().select("etype", F.explode(F.array(F.struct(F.col("src").alias("a"), F.col("dst").alias("b")), F.struct(F.col("dst").alias("a"), F.col("src").alias("b")))).alias("e")).select("etype", "e.a", "e.b")
    i = graph.ids[changed]
    return both.groupBy("etype").agg(F.count("*").alias("needed"), F.count_if(F.col("a").between(i.lo, i.hi)).alias("sent")).withColumn("starved", F.col("needed") - F.col("sent"))


def pregel_round(edges: DataFrame, active: DataFrame) -> DataFrame:
    """``vid, needed, received, ready`` of every vertex, after a round in which only ``active`` (vid) vertices send.

    Messages go along an edge both ways.  A vertex can update, and so be active in the next round, only with all its messages.
    """
    both = edges.select(F.col("src").alias("a"), F.col("dst").alias("vid")).union(edges.select(F.col("dst").alias("a"), F.col("src").alias("vid")))
    sent = both.join(active.select(F.col("vid").alias("a"), F.lit(1).alias("sends")), "a", "left")
    return sent.groupBy("vid").agg(F.count("*").alias("needed"), F.count("sends").alias("received")).withColumn("ready", F.col("needed") == F.col("received"))


def pregel_run(graph: MessageGraph, first: str = "phi", rounds: int = 3) -> list[dict[str, int]]:
    """Rounds from the vertices of ``first``: how many ``sent``, got a message (``reached``) and could update (``ready``).

    Ends when nothing may send; each round's active vertices are a checkpoint, so plans don't grow.
    """
    i = graph.ids[first]
    edges, active, found = graph.edges(), graph.vertices().filter(F.col("vid").between(i.lo, i.hi)).select("vid"), []
    for _ in range(rounds):
        state = pregel_round(edges, active)
        row = state.agg(F.count_if(F.col("received") > 0).alias("reached"), F.count_if("ready").alias("ready")).first()
        found.append({"sent": active.count(), "reached": row["reached"], "ready": row["ready"]})
        if not row["ready"]:
            break
        active = checkpointed(state.filter("ready").select("vid"))
    return found
