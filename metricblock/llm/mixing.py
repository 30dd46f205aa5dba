"""Mixing overlapping sources to target weights by min-cost flow.

Documents with the same set of sources form one membership pattern; only the patterns' sizes
enter the flow.  Each pattern offers its tokens once at low cost, a second time at a higher
one and so on (convex repetition costs), and sends them to the sources it belongs to, up to
their quotas.  The flow says how many tokens of each pattern the mix takes; a seeded order
of documents then says which.  The order is a hash, cut by two histograms, so that only the
documents of one bucket in 16 million are ever sorted, and a source with a third of all rows
is no different from any other.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from metricblock.llm.common import WORD, stored, table, text_of

#: The patterns and sources that the flow is solved for on the driver.
MAX_PATTERNS = 100_000
FINE = 12  # bits of a histogram


class FlowNetwork:
    """Min-cost maximum flow by cheapest augmenting paths with node potentials; whole numbers."""

    def __init__(self, nodes: int):
        self.out: list[list[int]] = [[] for _ in range(nodes)]
        self.to: list[int] = []
        self.room: list[int] = []
        self.cost: list[int] = []

    def arc(self, a: int, b: int, room: int, cost: int = 0) -> int:
        for x, y, r, c in ((a, b, room, cost), (b, a, 0, -cost)):
            self.out[x].append(len(self.to))
            self.to.append(y)
            self.room.append(r)
            self.cost.append(c)
        return len(self.to) - 2

    def sent(self, arc: int) -> int:
        return self.room[arc ^ 1]

    def run(self, source: int, sink: int) -> None:
        price = [0] * len(self.out)  # all costs start at zero or more
        while True:
            far: dict[int, int] = {source: 0}
            via: dict[int, int] = {}
            queue, done = [(0, source)], set()
            while queue:
                d, a = heapq.heappop(queue)
                if a in done:
                    continue
                done.add(a)
                for arc in self.out[a]:
                    b = self.to[arc]
                    if self.room[arc] and b not in done:
                        new = d + self.cost[arc] + price[a] - price[b]
                        if new < far.get(b, new + 1):
                            far[b], via[b] = new, arc
                            heapq.heappush(queue, (new, b))
            if sink not in done:
                return
            most = far[sink]
            for a in range(len(price)):
                price[a] += min(far.get(a, most), most)
            path, a = [], sink
            while a != source:
                path.append(via[a])
                a = self.to[via[a] ^ 1]
            step = min(self.room[arc] for arc in path)
            for arc in path:
                self.room[arc] -= step
                self.room[arc ^ 1] += step


def targets_for(sizes: dict, weights: dict, total: float, most: float) -> dict:
    """``total`` shared by weight; what exceeds ``most`` times a source's size is shared anew."""
    target, open_ = {}, {s for s in sizes if weights[s] > 0}
    target |= {s: 0.0 for s in sizes if s not in open_}
    left = float(total)
    while open_:
        share = sum(weights[s] for s in open_)
        over = {s for s in open_ if left * weights[s] / share > most * sizes[s]}
        if not over:
            return target | {s: left * weights[s] / share for s in open_}
        target |= {s: float(most * sizes[s]) for s in over}
        left -= sum(most * sizes[s] for s in over)
        open_ -= over
    return target


def route(patterns: dict[tuple, int], quotas: dict, most: int, repeat_cost: Callable[[int], int] = lambda copy: copy * copy) -> dict[tuple, int]:
    """Tokens to take of each pattern (a tuple of sources) so that quotas fill at least cost."""
    names, sources = list(patterns), list(quotas)
    at = {s: 2 + len(names) + i for i, s in enumerate(sources)}
    net = FlowNetwork(2 + len(names) + len(sources))
    offers = [[net.arc(0, 2 + i, patterns[p], repeat_cost(copy)) for copy in range(1, most + 1)] for i, p in enumerate(names)]
    for i, p in enumerate(names):
        for s in p:
            net.arc(2 + i, at[s], most * patterns[p])
    for s in sources:
        net.arc(at[s], 1, round(quotas[s]))
    net.run(0, 1)
    return {p: sum(map(net.sent, offers[i])) for i, p in enumerate(names)}


def _reached(histogram: DataFrame, takes: DataFrame, key: str, keep: Sequence[str]) -> DataFrame:
    """For each pattern the bucket ``key`` in which its running size reaches ``need``, and what is needed there.

    A pattern has at most 2**FINE buckets here, whatever its number of documents.
    """
    w = Window.partitionBy("pattern").orderBy(key)
    upto = histogram.withColumn("upto", F.sum("size").over(w))
    return (
        upto.join(F.broadcast(takes), "pattern")
        .where((F.col("upto") >= F.col("need")) & (F.col("upto") - F.col("size") < F.col("need")))
        .select("pattern", *keep, key, (F.col("need") - F.col("upto") + F.col("size")).alias("need"))
    )


def mix(docs: DataFrame, membership, size, weights: Callable[[list], dict], share: float = 1.5, most: int = 2, seed: int = 17, boundary: str = "split") -> DataFrame:
    """``docs`` with ``_size``, ``_pattern``, ``_taken`` (tokens, repeats counted; columns of these names are replaced), and the table of sources.

    ``membership`` is an array of source names (null is a name too); ``size`` a column of whole
    numbers; ``weights`` maps the sorted list of sources to their weights.  The mix takes
    ``share`` of all tokens, and of no document more than ``most`` times its size.  Within a
    pattern, documents come in seeded order, by ``doc_id``; equal ids are ordered by size, so
    repeated rows may be told apart only where they are equal anyway.  The document at the
    quota's edge gives the tokens that are missing (``boundary="split"``) or comes whole if
    at least half of it is wanted (``"whole"``).  Sizes of zero take nothing.  An empty table
    gives no rows.  Returns (documents, sources as dict name -> (size, target)).
    """
    spark = docs.sparkSession
    own = [c for c in docs.columns if c not in ("_size", "_pattern", "_taken")]
    base = stored(
        docs.select(
            F.struct(*[F.col(f"`{c}`") for c in own]).alias("_row"),
            F.col("doc_id").alias("_doc"),
            F.coalesce(size.cast("long"), F.lit(0)).alias("_size"),
            F.array_sort(F.array_distinct(membership), _null_last).alias("_pattern"),
            F.xxhash64(F.lit(seed), F.col("doc_id")).alias("_order"),
        ).withColumns({"_coarse": F.shiftrightunsigned("_order", 64 - FINE), "_fine": F.shiftrightunsigned("_order", 64 - 2 * FINE).bitwiseAND((1 << FINE) - 1)})
    )
    sizes = base.groupBy("_pattern").agg(F.sum("_size").alias("size"))
    rows = sizes.limit(MAX_PATTERNS + 1).collect()
    if len(rows) > MAX_PATTERNS:
        raise ValueError(f"more than {MAX_PATTERNS} membership patterns")
    patterns = {tuple(r["_pattern"]): r["size"] for r in rows}
    source_size: dict = {}
    for p, n in patterns.items():
        for s in p:
            source_size[s] = source_size.get(s, 0) + n
    names = sorted(source_size, key=lambda s: (s is None, s or ""))
    target = targets_for(source_size, weights(names), share * sum(patterns.values()), most)
    takes = route(patterns, target, most)

    plan = [(list(p), takes[p] // n if n else 0, takes[p] % n if n else 0) for p, n in patterns.items()]
    schema = "pattern array<string>, copies long, need long"
    plans = spark.createDataFrame(plan, schema)
    some = spark.createDataFrame([x for x in plan if x[2]], schema).select("pattern", "need")
    named = base.select(F.col("_pattern").alias("pattern"), F.col("_coarse").alias("coarse"), F.col("_fine").alias("fine"), F.col("_size").alias("size"))
    coarse = _reached(named.groupBy("pattern", "coarse").agg(F.sum("size").alias("size")), some, "coarse", [])
    coarse = spark.createDataFrame(coarse.collect(), "pattern array<string>, coarse long, need long")
    inner = named.join(F.broadcast(coarse.drop("need")), ["pattern", "coarse"]).groupBy("pattern", "coarse", "fine").agg(F.sum("size").alias("size"))
    fine = _reached(inner, coarse.select("pattern", "need"), "fine", ["coarse"])
    cuts = spark.createDataFrame(fine.collect(), "pattern array<string>, cut_coarse long, cut_fine long, cut_need long")

    known = base.join(F.broadcast(plans), F.col("_pattern").eqNullSafe(F.col("pattern"))).drop("pattern", "need")
    known = known.join(F.broadcast(cuts), F.col("_pattern").eqNullSafe(F.col("pattern")), "left").drop("pattern")
    key, cut = F.struct("_coarse", "_fine"), F.struct(F.col("cut_coarse").alias("_coarse"), F.col("cut_fine").alias("_fine"))
    at_cut = F.coalesce((key == cut) & F.col("cut_need").isNotNull(), F.lit(False))
    clear = known.where(~at_cut).withColumn("_more", F.when(F.col("cut_need").isNotNull() & (key < cut), F.col("_size")).otherwise(F.lit(0)))
    before = F.sum("_size").over(Window.partitionBy("_pattern").orderBy("_order", "_doc", "_size").rowsBetween(Window.unboundedPreceding, -1))
    want = F.greatest(F.lit(0), F.least(F.col("_size"), F.col("cut_need") - F.coalesce(before, F.lit(0))))
    if boundary == "whole":
        want = F.when(want * 2 >= F.col("_size"), F.col("_size")).otherwise(F.lit(0))
    edge = known.where(at_cut).withColumn("_more", want)
    taken = clear.unionByName(edge).withColumn("_taken", F.col("copies") * F.col("_size") + F.col("_more"))
    report = {s: (source_size[s], target[s]) for s in names}
    return taken.select("_row.*", "_size", "_pattern", "_taken"), report


def _null_last(a, b):
    return F.when(a.isNull() & b.isNull(), 0).when(a.isNull(), 1).when(b.isNull(), -1).when(a < b, -1).when(a > b, 1).otherwise(0)


def cycle_weights(names: list) -> dict:
    """3, 1, 2, repeating."""
    return {s: (3, 1, 2)[i % 3] for i, s in enumerate(names)}


def words(text) -> F.Column:
    return F.regexp_count(text, F.lit(WORD))


def mix_documents(docs: DataFrame, boundary: str = "split") -> tuple[DataFrame, dict]:
    """The mix of op10: each document's one source, words as tokens."""
    return mix(docs, F.array(F.col("source").cast("string")), words(text_of()), cycle_weights, boundary=boundary)


def op10_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    sizes = table(spark, sf_dir, "documents").select("doc_id", "source", words(text_of()).alias("words"))
    mixed, report = mix(sizes, F.array(F.col("source").cast("string")), F.col("words"), cycle_weights)
    found = spark.createDataFrame([(s, n, t) for s, (n, t) in report.items()], "source string, source_size long, target double")
    return (
        mixed.withColumn("source", F.get("_pattern", F.lit(0)))
        .join(F.broadcast(found).withColumnRenamed("source", "of"), F.col("source").eqNullSafe(F.col("of")))
        .select("doc_id", F.col("_size").alias("size"), "source_size", "target", F.col("_taken").alias("taken"))
    )
