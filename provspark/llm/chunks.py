"""Operator 6, substring dedup: content-defined chunks by a gear rolling hash, checked at word level.

A chunk ends after a byte at which the gear hash of the last 16 bytes is small, or at a multiple of MOST bytes
after the last such end, and never inside a character.  Ends depend on nearby bytes only, so a passage has the same
inner chunks wherever it stands and insertions shift nothing.  Chunks with the same digest in two or more documents
are repeats.  Runs of them with PASSAGE_WORDS words are passages.  Shorter runs from SEED_WORDS words on, and the edges of
long ones, are only seeds: all windows of PASSAGE_WORDS words that hold a seed or hang over an edge are digested as well, and those in
two or more documents are passages, whatever part of them the chunks left out.  Windows in which the hash leaves no such
seed (one word over and over, or by chance) are always digested.  Short chunks at the ends of a run may be common bits that other
documents share, so they count only with a window.

The first document (the least id) keeps a chunk or window.  A later one drops stretches of PASSAGE_WORDS words of chunks that
others own, and windows that another owns; what it drops always stands in a document of a lesser id, and so on down to one that keeps
it.  A passage is cut into spans where that changes.

Defined cases: null and empty texts have no chunks; a null id takes no part in counting and owns nothing, its
repeats are reported; a repeated id counts once; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provspark.llm.common import drop_table, map_arrow, read_table, small_batches, text_bytes, write_read
from provspark.llm.shingles import mixed

#: An end is expected every MEAN bytes.
MEAN, MOST = 32, 256
#: Bytes that the hash looks back on.
REACH = 16
#: Words of a passage; of a run of chunks that is worth a check; and over an edge of a long run.
PASSAGE_WORDS, SEED_WORDS, EDGE_WORDS = 51, 8, 24
#: Words of a chunk that may end a run.
END_WORDS = 3
GEAR = (mixed(np.arange(256, dtype=np.uint64) + np.uint64(1)) >> np.uint64(48)).astype(np.uint16)
SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
_BASE = np.uint64(0x9E3779B97F4A7C15)


def gear_hashes(data: np.ndarray) -> np.ndarray:
    """The rolling hash h = 2 h + gear[byte] modulo 2**16 at each byte, by doubling the reach four times."""
    h = GEAR[data]
    for k in range(4):
        step = 1 << k
        if step >= len(h):
            break
        later = h[:-step] << np.uint16(step)
        h[step:] += later
    return h


def content_ends(data: np.ndarray) -> np.ndarray:
    """Ends that the hash sets, each known from the REACH bytes before it and the next byte."""
    inner = np.append(data[1:] & 0xC0 == 0x80, False)  # the next byte continues a character
    return np.flatnonzero((gear_hashes(data) < (1 << 16) // MEAN) & ~inner) + 1


def chunk_ends(data: np.ndarray) -> np.ndarray:
    """Ends of one text's chunks, the last being its length."""
    n = len(data)
    if n == 0:
        return np.zeros(0, np.int64)
    inner = np.append(data[1:] & 0xC0 == 0x80, False)
    ends = np.unique(np.append(content_ends(data), n))
    starts = np.concatenate([[0], ends[:-1]])
    more = (ends - starts - 1) // MOST
    if more.any():
        extra = np.repeat(starts, more) + MOST * (np.arange(more.sum()) - np.repeat(np.cumsum(more) - more, more) + 1)
        for _ in range(3):
            extra += inner[extra - 1]
        ends = np.unique(np.concatenate([ends, extra]))
    return ends


def span_digests(data: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> np.ndarray:
    """A 64-bit digest of each span of bytes from prefix sums of a polynomial, finished with the length."""
    n = len(data)
    powers = np.full(n + 1, _BASE)
    powers[0] = 1
    powers = np.cumprod(powers)
    inverse = np.full(n + 1, np.uint64(pow(int(_BASE), -1, 2**64)))
    inverse[0] = 1
    inverse = np.cumprod(inverse)
    values = mixed(data.astype(np.uint64) + np.uint64(1))
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(values * powers[:n])])
    return mixed((total[stops] - total[starts]) * inverse[starts] + mixed((stops - starts).astype(np.uint64))).view(np.int64)


def chunk_starts(ends: np.ndarray) -> np.ndarray:
    return np.concatenate([[0], ends[:-1]]).astype(np.int64) if len(ends) else ends


def word_bounds(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and stops of the words of a text."""
    edge = np.diff(np.concatenate([[False], ~SPACE[data], [False]]).astype(np.int8))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def stretches(flags: np.ndarray) -> list[tuple[int, int]]:
    edge = np.diff(np.concatenate([[False], flags, [False]]).astype(np.int8))
    return list(zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist()))


def chunk_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, text, digests), the digests of a text's chunks."""
    kind = docs.schema[id_col].dataType.simpleString()

    def per_slice(batch):
        digests, bounds = [np.zeros(0, np.int64)], [0]
        for raw in text_bytes(batch.column("text")).to_pylist():
            data = np.frombuffer(raw, np.uint8)
            ends = chunk_ends(data)
            digests.append(span_digests(data, chunk_starts(ends), ends))
            bounds.append(bounds[-1] + len(ends))
        lists = pa.ListArray.from_arrays(pa.array(bounds, pa.int32()), pa.array(np.concatenate(digests), pa.int64()))
        return pa.RecordBatch.from_arrays([batch.column("id"), batch.column("text"), lists], names=["id", "text", "digests"])

    return map_arrow(docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")), f"id {kind}, text string, digests array<long>", "text", per_slice)


def repeated_digests(table: DataFrame) -> DataFrame:
    """Rows (digest, owner): digests in two or more documents and the least id that has each.

    Least and greatest ids are partial aggregates: a chunk in a third of all documents costs one row a task.
    """
    each = table.select("id", F.explode(F.array_distinct("digests")).alias("digest")).filter("id IS NOT NULL")
    return each.groupBy("digest").agg(F.min("id").alias("owner"), F.max("id").alias("other")).filter("owner < other").select("digest", "owner")


def with_marks(table: DataFrame, found: DataFrame) -> DataFrame:
    """The table with marks: (at, own) of a row's repeated digests, null if none."""
    each = table.select("row", F.posexplode("digests").alias("at", "digest"))
    marks = each.join(found, "digest").groupBy("row").agg(F.collect_list(F.struct("at", "owner")).alias("marks"))
    own = F.transform("marks", lambda m: F.struct(m["at"].alias("at"), F.coalesce(m["owner"] == F.col("id"), F.lit(False)).alias("own")))
    return table.drop("digests").join(marks, "row", "left").withColumn("marks", own)


def marked(marks: pa.Scalar) -> tuple[np.ndarray, np.ndarray]:
    if not marks.is_valid:
        return np.zeros(0, np.int64), np.zeros(0, bool)
    return marks.values.field("at").to_numpy(), marks.values.field("own").to_numpy(zero_copy_only=False)


def blind_windows(data: np.ndarray, first: np.ndarray, last: np.ndarray, words: int, least: int) -> np.ndarray:
    """First words of the windows whose own bytes set no two ends with ``least`` words in between."""
    n = len(first) - words + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    ends = content_ends(data)
    a = np.searchsorted(ends, first[:n] + REACH)
    b = np.searchsorted(ends, last[words - 1 :]) - 1
    begun = np.append(np.searchsorted(first, ends), 0)
    return np.flatnonzero((b <= a) | (begun[b] - begun[a] < least))


def seeds_of(data: np.ndarray, hit: np.ndarray, own: np.ndarray, words: int, least: int) -> dict:
    """What the repeated chunks of one text say.

    whole, drop: (start, stop, first word, last word) of long runs and of their stretches that others own;
    hits: starts of the chunks of runs; w_start, w_stop, w_word, digests: windows to check.
    """
    ends = chunk_ends(data)
    begin = chunk_starts(ends)
    first, last = word_bounds(data)
    begun = np.searchsorted(first, np.append(begin, len(data)))  # words begun before each chunk
    whole, drop, hits, windows = [], [], [], [blind_windows(data, first, last, words, least)]

    def look(a: int, b: int, out: list) -> None:
        """A long stretch of chunks goes to ``out``, its edges to the windows; a short one is a seed."""
        x0, y0 = int(begun[a]), int(np.searchsorted(last, ends[b - 1], side="right"))
        while begun[a + 1] - begun[a] < END_WORDS and begun[b] - begun[a + 1] >= least:
            a += 1
        while begun[b] - begun[b - 1] < END_WORDS and begun[b - 1] - begun[a] >= least:
            b -= 1
        start, stop, x, y = int(begin[a]), int(ends[b - 1]), int(begun[a]), int(begun[b])
        done = int(np.searchsorted(last, stop, side="right"))  # words ended by the stop
        if y - x >= words:
            out.append((start, stop, x, y))
            windows.append(np.arange(max(x0 - EDGE_WORDS, 0), x))
            windows.append(np.arange(done - words + 1, y0 - words + 1 + EDGE_WORDS))
        elif y - x >= least:
            windows.append(np.arange(max(done - words, 0), x + 1))

    for a, b in stretches(hit):
        if begun[b] - begun[a] < least:
            continue
        hits.extend(begin[a:b].tolist())
        look(a, b, whole)
        if begun[b] - begun[a] >= words:
            for c, d in stretches(~own[a:b]):
                if begun[a + d] - begun[a + c] >= least:
                    look(a + c, a + d, drop)
    at = np.unique(np.concatenate(windows))
    at = at[(at >= 0) & (at + words <= len(first))]
    w_start, w_stop = first[at], last[at + words - 1]
    return {"whole": whole, "drop": drop, "hits": hits, "w_start": w_start, "w_stop": w_stop, "w_word": at, "digests": span_digests(data, w_start, w_stop) if len(at) else at}


def spans_of(ident: dict, hit: np.ndarray, own: np.ndarray, words: int) -> list[dict]:
    """Spans of one text from its long runs and the windows found to be repeated."""
    number: dict[int, int] = {}
    report, drop = [], []
    for rows, out in ((ident["whole"], report), (ident["drop"], drop)):
        for r in rows:
            out.append((r["start"], r["stop"]))
            number[r["start"]], number[r["stop"]] = r["first"], r["last"]
    for k, mine in zip(hit.tolist(), own.tolist()):
        a, b, w = ident["w_start"][k], ident["w_stop"][k], ident["w_word"][k]
        number[a], number[b] = w, w + words
        report.append((a, b))
        if not mine:
            drop.append((a, b))
    points = np.array(sorted(number), np.int64)
    if not len(points):
        return []

    def inside(pairs: list) -> np.ndarray:
        change = np.zeros(len(points), np.int64)
        for side, sign in ((0, 1), (1, -1)):
            np.add.at(change, np.searchsorted(points, [p[side] for p in pairs]), sign)
        return np.cumsum(change)[:-1] > 0

    hits = np.array(ident["hits"], np.int64)
    away, out = inside(drop) if drop else np.zeros(len(points) - 1, bool), []
    for flags, owned in ((inside(report) & ~away, True), (away, False)):
        for a, b in stretches(flags):
            start, stop = int(points[a]), int(points[b])
            chunks = int(((hits >= start) & (hits < stop)).sum())
            out.append({"start": start, "stop": stop, "n_words": number[stop] - number[start], "n_chunks": chunks, "owned": owned})
    return sorted(out, key=lambda s: s["start"])


PIECE = "array<struct<start:int,stop:int,first:int,last:int>>"


def repeated_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = PASSAGE_WORDS, least: int = SEED_WORDS) -> DataFrame:
    """Rows (id, n_bytes, n_chunks, spans), one for each row of docs.

    spans: (start, stop, n_words, n_chunks, owned) of repeated passages in bytes, cut where ``owned`` changes: whether this
    document keeps the text; n_chunks counts the repeated chunks that begin inside.
    """
    kind = docs.schema[id_col].dataType.simpleString()
    table = write_read(chunk_table(docs, id_col, text_col).withColumn("row", F.monotonically_increasing_id()), "chunks", compression="zstd")
    found = write_read(repeated_digests(table), "repeats")
    piece = pa.list_(pa.struct([(k, pa.int32()) for k in ("start", "stop", "first", "last")]))
    ints, longs = pa.list_(pa.int32()), pa.list_(pa.int64())
    kinds = {"whole": piece, "drop": piece, "hits": ints, "w_start": ints, "w_stop": ints, "w_word": ints, "digests": longs}

    def seed(batches):
        for batch in batches:
            sizes, counts, out = [], [], {k: [] for k in kinds}
            chunks, marks = batch.column("n_chunks"), batch.column("marks")
            for i, raw in enumerate(text_bytes(batch.column("text")).to_pylist()):
                n = chunks[i].as_py()
                at, mine = marked(marks[i])
                hit, own = np.zeros(n, bool), np.zeros(n, bool)
                hit[at] = True
                own[at] = mine
                got = seeds_of(np.frombuffer(raw, np.uint8), hit, own, words, least)
                sizes.append(len(raw))
                counts.append(n)
                for k in kinds:
                    value = got[k]
                    out[k].append([dict(zip(("start", "stop", "first", "last"), p)) for p in value] if k in ("whole", "drop") else value)
            lists = [pa.array(out[k], t) for k, t in kinds.items()]
            yield pa.RecordBatch.from_arrays([batch.column("row"), batch.column("id"), pa.array(sizes, pa.int64()), pa.array(counts, pa.int64()), *lists], names=["row", "id", "n_bytes", "n_chunks", *kinds])

    rows = with_marks(table.withColumn("n_chunks", F.size("digests")), found).select("row", "id", "text", "n_chunks", "marks")
    schema = f"row long, id {kind}, n_bytes long, n_chunks long, whole {PIECE}, drop {PIECE}, hits array<int>, w_start array<int>, w_stop array<int>, w_word array<int>, digests array<long>"
    seeds = write_read(small_batches(rows).mapInArrow(seed, schema), "seeds", compression="zstd")
    drop_table(table)
    drop_table(found)
    checked = with_marks(seeds, write_read(repeated_digests(seeds), "windows"))

    def finish(batches):
        for batch in batches:
            marks, parts = batch.column("marks"), batch.select([k for k in kinds if k != "digests"]).to_pylist()
            spans = [spans_of(p, *marked(marks[i]), words) for i, p in enumerate(parts)]
            kind_of = pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64()), ("n_words", pa.int64()), ("n_chunks", pa.int64()), ("owned", pa.bool_())]))
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in ("id", "n_bytes", "n_chunks")), pa.array(spans, kind_of)], names=["id", "n_bytes", "n_chunks", "spans"])

    return checked.mapInArrow(finish, f"id {kind}, n_bytes long, n_chunks long, spans array<struct<start:bigint,stop:bigint,n_words:bigint,n_chunks:bigint,owned:boolean>>")


def without_repeats(text: F.Column, spans: F.Column) -> F.Column:
    """The text without the spans that another document owns, in bytes of UTF-8."""
    raw = F.encode(text, "UTF-8")
    drop = F.filter(spans, lambda s: ~s["owned"])
    stops = F.concat(F.array(F.lit(0).cast("bigint")), F.transform(drop, lambda s: s["stop"]))
    begins = F.concat(F.transform(drop, lambda s: s["start"]), F.array(F.octet_length(text).cast("bigint")))
    return F.aggregate(F.arrays_zip(stops.alias("a"), begins.alias("b")), F.encode(F.lit(""), "UTF-8"), lambda acc, x: F.concat(acc, F.substring(raw, (x["a"] + 1).cast("int"), (x["b"] - x["a"]).cast("int"))), lambda acc: F.decode(acc, "UTF-8"))


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = repeated_passages(read_table(spark, sf_dir, "documents"))
    total = lambda f: F.aggregate("spans", F.lit(0).cast("bigint"), lambda a, s: a + f(s))
    return found.select(
        F.col("id").alias("doc_id"),
        "n_bytes",
        "n_chunks",
        F.size(F.filter("spans", lambda s: ~F.exists("spans", lambda before: before["stop"] == s["start"]))).cast("bigint").alias("n_passages"),
        total(lambda s: s["stop"] - s["start"]).alias("repeated_bytes"),
        total(lambda s: F.when(s["owned"], F.lit(0)).otherwise(s["stop"] - s["start"])).alias("dropped_bytes"),
        F.array_join(F.transform("spans", lambda s: F.concat_ws("-", s["start"], s["stop"])), ",").alias("passages"),
    )
