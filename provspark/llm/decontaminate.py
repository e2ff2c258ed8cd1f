"""Operator 7, benchmark decontamination: pigeonhole pieces, exact hits, bit-parallel verification.

Texts and test items are lower-cased and their white space becomes single spaces.  An item of m
characters may differ by k = floor(share * m) edits.  It is cut into k + 1 pieces, one of which
must occur unchanged in any passage within k edits; an automaton finds all pieces of all items
in one pass over a text, and each hit's surroundings are verified by Myers' bit-parallel distance.

The items of one pass are bounded in bytes; more items take further passes, not a larger automaton.

Defined cases: null and empty texts or items match nothing; items too short for one edit must occur exactly, as whole
words; of equally near passages the first is given; a
null id is reported as null; repeated rows are reported each; an empty table of either kind
gives no rows; other columns are not read.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provspark.llm.common import filter_arrow, map_arrow, read_table, worker_slot, write_read
from provspark.llm.tokens import filled

EDIT_SHARE = 0.08
#: Items of one pass, in bytes of text.
PASS_BYTES = 16 << 20


def plain(text: str) -> str:
    return " ".join(text.lower().split())


def budget(item: str, share: float = EDIT_SHARE) -> int:
    return int(share * len(item) + 1e-9)


def pieces(item: str, k: int) -> list[tuple[int, str]]:
    """(offset, piece): k + 1 consecutive pieces of nearly equal length."""
    cuts = [len(item) * i // (k + 1) for i in range(k + 2)]
    return [(a, item[a:b]) for a, b in zip(cuts, cuts[1:]) if b > a]


class Pattern:
    """An item's bit vectors."""

    def __init__(self, item: str):
        self.size = len(item)
        self.bits: dict[str, int] = {}
        for i, c in enumerate(item):
            self.bits[c] = self.bits.get(c, 0) | 1 << i

    def best_end(self, text: str) -> tuple[int, int]:
        """(distance, end) of the passage of text nearest to the item, the first of equals."""
        full, top = (1 << self.size) - 1, 1 << (self.size - 1)
        up, down, score, bits = full, 0, self.size, self.bits
        best, end = score, 0
        for i, c in enumerate(text):
            eq = bits.get(c, 0)
            x = eq | down
            d = ((((eq & up) + up) ^ up) | eq) & full
            ph, mh = down | (~(d | up) & full), up & d
            if ph & top:
                score += 1
            elif mh & top:
                score -= 1
            ph, mh = (ph << 1) & full, (mh << 1) & full
            up, down = mh | (~(x | ph) & full), ph & x
            if score < best:
                best, end = score, i + 1
        return best, end


def automaton_of(items: list[tuple[int, str]], share: float):
    import ahocorasick

    where: dict[str, list[tuple[int, int]]] = {}
    for number, (_, item) in enumerate(items):
        for at, piece in pieces(item, budget(item, share)):
            where.setdefault(piece, []).append((number, at))
    out = ahocorasick.Automaton()
    for piece, at in where.items():
        out.add_word(piece, (len(piece), at))
    if where:
        out.make_automaton()
    return out if where else None


def whole_words(text: str, a: int, b: int) -> bool:
    """Whether text[a:b] neither begins nor ends inside a word."""
    inside = lambda i: 0 < i < len(text) and text[i - 1].isalnum() and text[i].isalnum()
    return not inside(a) and not inside(b)


class Matcher:
    def __init__(self, items: list[tuple[int, str]], share: float = EDIT_SHARE):
        self.items = [(i, plain(t)) for i, t in items if t]
        self.items = [(i, t) for i, t in self.items if t]
        self.share = share
        self.automaton = automaton_of(self.items, share)
        self.patterns: dict[int, tuple[Pattern, Pattern, int]] = {}

    def pattern(self, number: int) -> tuple[Pattern, Pattern, int]:
        if number not in self.patterns:
            item = self.items[number][1]
            self.patterns[number] = (Pattern(item), Pattern(item[::-1]), budget(item, self.share))
        return self.patterns[number]

    def matches(self, text: str) -> list[tuple[int, int, int, int]]:
        """(item id, distance, start, end) of the nearest passage of each item within its budget, in the plain text."""
        text = plain(text)
        if not text or self.automaton is None:
            return []
        hits: dict[int, set[int]] = {}
        for end, (size, at) in self.automaton.iter(text):
            for number, offset in at:
                hits.setdefault(number, set()).add(end + 1 - size - offset)
        out = []
        for number, starts in hits.items():
            item = self.items[number][1]
            if budget(item, self.share) == 0:
                at = next((a for a in sorted(starts) if whole_words(text, a, a + len(item))), None)
                if at is not None:
                    out.append((self.items[number][0], 0, at, at + len(item)))
                continue
            ahead, back, k = self.pattern(number)
            best = None
            last = None
            for start in sorted(starts):  # starts whose windows meet share one
                if last is not None and start <= last[1] + 2 * k + 1:
                    last[1] = start
                    continue
                if last is not None:
                    best = self.nearer(best, text, last, ahead, back, k)
                last = [start, start]
            best = self.nearer(best, text, last, ahead, back, k)
            if best is not None:
                out.append((self.items[number][0], *best))
        return out

    def nearer(self, best, text: str, span: list[int], ahead: Pattern, back: Pattern, k: int):
        a, b = max(0, span[0] - k), span[1] + ahead.size + k
        distance, end = ahead.best_end(text[a:b])
        if distance > k or best is not None and distance >= best[0]:
            return best
        _, length = back.best_end(text[a : a + end][::-1])
        return (distance, a + end - length, a + end)


def blocks_of(benchmark: DataFrame, id_col: str, text_col: str, pass_bytes: int) -> list[DataFrame]:
    rows = benchmark.select(F.col(id_col).alias("item"), F.col(text_col).alias("text")).filter("text IS NOT NULL")
    size = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    n = max(1, -(-size // pass_bytes))
    return [rows.filter(F.pmod(F.xxhash64("item", "text"), F.lit(n)) == i) for i in range(n)]


def benchmark_matches(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", share: float = EDIT_SHARE, pass_bytes: int = PASS_BYTES) -> DataFrame:
    """Rows (id, item_id, distance, span_start, span_end): each item found in each text, at its nearest passage."""
    kind, item_kind = docs.schema[id_col].dataType.simpleString(), benchmark.schema[item_col].dataType.simpleString()
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    out = None
    for matcher in shared_matchers(benchmark, item_col, item_text, share, pass_bytes):

        def per_slice(batch, matcher=matcher):
            find = matcher().matches
            at, found = [], []
            for i, text in enumerate(filled(batch.column("text")).to_pylist()):
                got = find(text)
                at += [i] * len(got)
                found += got
            cols = list(zip(*found)) if found else [[]] * 4
            item_type = pa.int64() if item_kind == "bigint" else pa.int32() if item_kind == "int" else pa.string()
            return pa.RecordBatch.from_arrays([batch.column("id").take(pa.array(at, pa.int64())), pa.array(cols[0], item_type), *(pa.array(c, pa.int64()) for c in cols[1:])], names=["id", "item_id", "distance", "span_start", "span_end"])

        part = map_arrow(rows, f"id {kind}, item_id {item_kind}, distance long, span_start long, span_end long", "text", per_slice)
        out = part if out is None else out.unionByName(part)
    return out


def shared_matchers(benchmark: DataFrame, item_col: str, item_text: str, share: float, pass_bytes: int) -> list:
    """For each pass a function that gives a worker's matcher of that pass's items."""
    out = []
    for block in blocks_of(benchmark, item_col, item_text, pass_bytes):
        items = benchmark.sparkSession.sparkContext.broadcast(sorted(((r["item"], r["text"]) for r in block.collect()), key=str))
        number = items._jbroadcast.id()

        def get(items=items, number=number) -> Matcher:
            return worker_slot(("matcher", number), lambda: Matcher(items.value, share))

        out.append(get)
    return out


def without_matches(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text: str = "text", share: float = EDIT_SHARE, pass_bytes: int = PASS_BYTES) -> DataFrame:
    """The rows in which no item is found, all columns as they are; a pass over what is left for each block of items.

    What a pass leaves is written before the next, so a worker holds one automaton.  A null or empty text holds no item and stays, as
    does every row if there are no items; repeated rows stay or go together.
    """
    for number, matcher in enumerate(shared_matchers(benchmark, item_col, item_text, share, pass_bytes)):
        docs = write_read(docs, "left") if number else docs
        docs = filter_arrow(docs, text_col, lambda batch, matcher=matcher: [not matcher().matches(t) for t in filled(batch.column(text_col)).to_pylist()])
    return docs


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return benchmark_matches(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark")).withColumnRenamed("id", "doc_id")
