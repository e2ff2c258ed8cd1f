"""Operator 3, mixing sources to target weights by min-cost flow.

Documents are summed by membership pattern (the set of sources they belong to).  A flow network
sends each pattern's words to the quotas of its sources; the first use of a word is cheapest and
each repetition costs more, so words are repeated as evenly as the quotas allow.  A pattern's flow
becomes whole uses of every document plus one more use of a seeded part of them.

The seeded part is found without sorting a pattern in one task: documents fall in bins of a
seeded hash, bins are summed and ordered, and only the one bin in which the flow ends is read entry
by entry.  Its documents are taken greedily in hash order while they fit.  Documents of one id, size and pattern are one entry
with a number, so a third of all rows without an id fill no task.

Defined cases: a null text has size 0; documents of size 0 are never taken; a null source is a
source of its own, last in order; an empty membership belongs to no source and is not taken; repeated rows are documents of
their own; a mix of no words takes nothing; other columns are not read.
"""

from __future__ import annotations

import heapq
from fractions import Fraction

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from provspark.llm.common import Scratch, if_small, read_table

WEIGHTS = (5, 2, 1)
MOST_USES = 3
#: Cost of a word's first, second and third use; convex.
USE_COSTS = (0, 1, 3)
SEED = 17
#: About so many entries fall in a bin.
BIN_ROWS = 500
#: Equal documents that one row of the fill stands for when it is unfolded.
UNFOLD = 1000


def word_count(text: F.Column) -> F.Column:
    """Runs of bytes other than 0x20 and 0x09-0x0D; null gives 0."""
    t = F.coalesce(text, F.lit(""))
    return F.regexp_count(t, F.lit(r"[^\x20\x09-\x0D]+")).cast("bigint")


def weights_of(sources: list[str | None], cycle: tuple[int, ...] = WEIGHTS) -> dict[str | None, int]:
    """Weights in turn by code point, null last."""
    order = sorted((x for x in sources if x is not None)) + ([None] if None in sources else [])
    return {s: cycle[i % len(cycle)] for i, s in enumerate(order)}


def targets_of(sizes: dict, weights: dict, total: int, most_uses: int = MOST_USES) -> dict:
    """Exact targets: shares of ``total`` by weight, at most ``most_uses`` times each size, excess shared anew."""
    out, free, left = {}, [s for s in sizes if weights[s] > 0], Fraction(total)
    while free:
        unit = left / sum(weights[s] for s in free)
        over = [s for s in free if unit * weights[s] > most_uses * sizes[s]]
        if not over:
            out |= {s: unit * weights[s] for s in free}
            break
        for s in over:
            out[s] = Fraction(most_uses * sizes[s])
            left -= out[s]
        free = [s for s in free if s not in out]
    return {s: out.get(s, Fraction(0)) for s in sizes}


class FlowNetwork:
    """Successive shortest paths with potentials; capacities and costs are integers."""

    def __init__(self, n: int):
        self.edges: list[list[list[int]]] = [[] for _ in range(n)]

    def add(self, a: int, b: int, capacity: int, cost: int) -> list[int]:
        e, r = [b, capacity, cost, len(self.edges[b])], [a, 0, -cost, len(self.edges[a])]
        self.edges[a].append(e)
        self.edges[b].append(r)
        return e

    def send(self, source: int, sink: int) -> None:
        n = len(self.edges)
        height = [0] * n
        while True:
            far, came, heap = [None] * n, [None] * n, [(0, source)]
            far[source] = 0
            while heap:
                d, a = heapq.heappop(heap)
                if d > far[a]:
                    continue
                for e in self.edges[a]:
                    if e[1] > 0:
                        w = d + e[2] + height[a] - height[e[0]]
                        if far[e[0]] is None or w < far[e[0]]:
                            far[e[0]], came[e[0]] = w, (a, e)
                            heapq.heappush(heap, (w, e[0]))
            if far[sink] is None:
                return
            for i, d in enumerate(far):
                height[i] += d if d is not None else 0
            amount, x = None, sink
            while x != source:
                a, e = came[x]
                amount = e[1] if amount is None else min(amount, e[1])
                x = a
            x = sink
            while x != source:
                a, e = came[x]
                e[1] -= amount
                self.edges[x][e[3]][1] += amount
                x = a


def route(pattern_sizes: dict[tuple, int], quotas: dict, costs: tuple[int, ...] = USE_COSTS) -> dict[tuple, dict]:
    """Words that each pattern gives to each of its sources, of least total repetition cost.

    Sources that no pattern joins are apart from each other, so each group of joined ones is a network of its own; a source with one
    pattern needs none.
    """
    root = {s: s for s in quotas}

    def find(x):
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    inside = {p: [s for s in p if s in quotas] for p in pattern_sizes}
    for mine in inside.values():
        for s in mine[1:]:
            root[find(s)] = find(mine[0])
    groups: dict = {}
    for p, mine in inside.items():
        if mine:
            groups.setdefault(find(mine[0]), []).append(p)
    out: dict[tuple, dict] = {p: {} for p in pattern_sizes}
    for patterns in groups.values():
        if len(patterns) == 1 and len(inside[patterns[0]]) == 1:
            s = inside[patterns[0]][0]
            out[patterns[0]] = {s: min(quotas[s], pattern_sizes[patterns[0]] * len(costs))}
        else:
            out |= route_group({p: pattern_sizes[p] for p in patterns}, {s: quotas[s] for p in patterns for s in inside[p]}, costs)
    return out


def route_group(pattern_sizes: dict[tuple, int], quotas: dict, costs: tuple[int, ...]) -> dict[tuple, dict]:
    patterns, sources = list(pattern_sizes), list(quotas)
    place = {s: 2 + len(patterns) + i for i, s in enumerate(sources)}
    net = FlowNetwork(2 + len(patterns) + len(sources))
    arcs = {}
    for i, p in enumerate(patterns):
        for c in costs:
            net.add(0, 2 + i, pattern_sizes[p], c)
        for s in p:
            if s in place:
                full = pattern_sizes[p] * len(costs)
                arcs[p, s] = (full, net.add(2 + i, place[s], full, 0))
    for s in sources:
        net.add(place[s], 1, quotas[s], 0)
    net.send(0, 1)
    out: dict[tuple, dict] = {p: {} for p in patterns}
    for (p, s), (full, e) in arcs.items():
        out[p][s] = full - e[1]
    return out


#: How sources are written in patterns: a name after a mark, or that there is none.
NAMED, NONE = "=", "-"


def mix(docs: DataFrame, id_col: str, size_col: str, members_col: str, seed: int = SEED, weights: dict | None = None, total: int | None = None, most_uses: int = MOST_USES, costs: tuple[int, ...] = USE_COSTS) -> tuple[DataFrame, dict]:
    """(rows (id, size, members, taken), facts by source) for documents with an array of sources.

    ``members`` holds sources as NAMED + name, or NONE.  Facts: size, weight, target and quota of each source.  What the driver collects
    is a row a pattern, which the flow needs as a whole; documents never pass it.
    """
    members = F.array_sort(F.array_distinct(F.transform(F.coalesce(F.col(members_col), F.array().cast("array<string>")), lambda x: F.coalesce(F.concat(F.lit(NAMED), x), F.lit(NONE)))))
    rows = docs.select(F.col(id_col).alias("id"), F.col(size_col).cast("bigint").alias("size"), members.alias("members"))
    tmp = Scratch()
    # The texts are read once; equal documents become one entry with their number.
    rows = tmp.write(rows.groupBy("id", "size", "members").agg(F.count("*").alias("n")), "sizes")
    sums = rows.groupBy("members").agg(F.sum(F.col("size") * F.col("n")).alias("words"), F.count("*").alias("n")).collect()
    pattern_sizes = {tuple(r["members"]): r["words"] or 0 for r in sums}
    sizes: dict[str, int] = {}
    for p, words in pattern_sizes.items():
        for s in p:
            sizes[s] = sizes.get(s, 0) + words
    named = {s: None if s == NONE else s[len(NAMED) :] for s in sizes}
    weigh = weights or weights_of(list(named.values()))
    by = {s: weigh.get(named[s], 0) for s in sizes}
    targets = targets_of(sizes, by, sum(pattern_sizes.values()) if total is None else total, most_uses)
    quotas = {s: int(t + Fraction(1, 2)) for s, t in targets.items()}
    flow = {p: sum(x.values()) for p, x in route(pattern_sizes, quotas, costs[:most_uses]).items()}
    # Bins: enough that none is large, by the entries of the largest pattern.
    bins = max(1, -(-max([r["n"] for r in sums], default=0) // BIN_ROWS))
    spark = docs.sparkSession
    plan = [(list(p), f // pattern_sizes[p] if pattern_sizes[p] else 0, f % pattern_sizes[p] if pattern_sizes[p] else 0) for p, f in flow.items()]
    plan_table = if_small(spark.createDataFrame(plan, "members array<string>, whole bigint, rest bigint"), len(plan))
    hashed = rows.join(plan_table, "members").withColumn("u", F.xxhash64(F.lit(seed), "id", "size")).withColumn("bin", F.pmod(F.shiftrightunsigned("u", 1), F.lit(bins)).cast("int"))
    before = Window.partitionBy("members").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    starts = tmp.write(hashed.groupBy("members", "bin").agg(F.sum(F.col("size") * F.col("n")).alias("words")).withColumn("before", F.coalesce(F.sum("words").over(before), F.lit(0))), "bins")
    placed = hashed.join(starts, ["members", "bin"])
    inside = F.col("before") + F.col("words") <= F.col("rest")
    ends_here = (F.col("before") < F.col("rest")) & ~inside
    id_type = docs.schema[id_col].dataType.simpleString()
    cols = ["id", "size", "members", "n", "taken"]

    def fill(group: pd.DataFrame) -> pd.DataFrame:
        """Entries split into the documents used once more and the others."""
        group = group.sort_values(["u", "id"], kind="stable")
        left, more = int(group["rest"].iloc[0] - group["before"].iloc[0]), []
        for size, n in zip(group["size"], group["n"]):
            more.append(min(n, left // size) if size > 0 else 0)
            left -= size * more[-1]
        group = group.assign(more=more)
        used = group.assign(taken=group["size"] * (group["whole"] + 1), n=group["more"])
        rest = group.assign(taken=group["size"] * group["whole"], n=group["n"] - group["more"])
        return pd.concat([used[used["n"] > 0], rest[rest["n"] > 0]])[cols]

    edge = placed.filter(ends_here).groupBy("members", "bin").applyInPandas(fill, f"id {id_type}, size long, members array<string>, n long, taken long")
    rest = placed.filter(~ends_here).select("id", "size", "members", "n", (F.col("size") * (F.col("whole") + F.when(inside, 1).otherwise(0))).alias("taken"))
    facts = {named[s]: {"size": sizes[s], "weight": by[s], "target": targets[s], "quota": quotas[s]} for s in sizes}
    return tmp.result(unfolded(rest.unionByName(edge), "n"), "mix"), facts


def unfolded(df: DataFrame, n: str) -> DataFrame:
    """Each row as often as its number says, in steps, so that no array of a row is long."""
    parts = df.withColumn("_part", F.explode(F.sequence(F.lit(0).cast("bigint"), F.floor((F.col(n) - 1) / UNFOLD))))
    return parts.withColumn("_copy", F.explode(F.sequence(F.lit(1).cast("bigint"), F.least(F.lit(UNFOLD).cast("bigint"), F.col(n) - F.col("_part") * UNFOLD)))).drop("_part", "_copy", n)


def mix_by_source(docs: DataFrame, seed: int = SEED) -> DataFrame:
    """Rows (doc_id, size, source_size, target, taken): each document in its one source."""
    sized = docs.select("doc_id", word_count(F.col("text")).alias("size"), F.array("source").alias("members"))
    taken, facts = mix(sized, "doc_id", "size", "members", seed)
    spark = docs.sparkSession
    table = [(NONE if s is None else NAMED + s, f["size"], float(f["target"])) for s, f in facts.items()]
    about = if_small(spark.createDataFrame(table, "source string, source_size bigint, target double"), len(table))
    return taken.withColumn("source", F.col("members")[0]).join(about, "source").select(F.col("id").alias("doc_id"), "size", "source_size", "target", "taken")


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_by_source(read_table(spark, sf_dir, "documents"))
