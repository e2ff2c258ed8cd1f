"""Operators 2 and 4: token ids in Parquet list columns, and exact token counts at every prefix.

Both rest on one fact about the public vocabulary file: its patterns never cross white space, a digit, or the place
between a letter and an ASCII sign, so a text's ids are those of its parts in turn.  The tokenizers library encodes each
distinct part once a worker; texts are then joined from those by array gathers.

Prefix counts are a dynamic programme over prefixes: the count at a character is that at the start of its part plus that of the
part's own beginning.  The latter is the library's count of that beginning, memoised; in one run of letters or signs longer than
LONG characters it comes from a second recurrence, over the last token of each prefix.  A prefix's count may be less than
that of a shorter one.

Defined cases: a null text is the empty text and has no ids; a null id stays null and comes first in ascending
order; repeated ids are ordered by text; other columns are not read; empty tables give empty results.
"""

from __future__ import annotations

import unicodedata
import zlib
from collections.abc import Iterator
from functools import cache
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from provspark.llm.common import gathered, map_arrow, new_path, ragged_take, read_table, worker_slot, write_read

VOCABULARY = "word_bpe_49k.json"
END_ID = 1
TOKEN_LIMIT = 2048
#: Parts that a worker remembers, and beginnings of parts; on reaching a bound that memory starts anew.
MEMO_PARTS, MEMO_STEMS = 600_000, 400_000
#: Beginnings of up to so many characters are remembered: longer ones are seldom shared.
STEM = 6
#: Longer parts are cut by pattern, and longer runs counted by their last tokens.
LONG = 64

# White space as the tokenizers library takes it, and signs that Arrow's split takes for white space as well.
SPACES = "\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
ODD_SPACE = "[\x1c-\x1f\u180e]"
IS_SPACE = np.zeros(0x3001, bool)
IS_SPACE[[*range(9, 14), 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]] = True
#: Digits stand alone; a letter and an ASCII sign after it, or an ASCII sign but the apostrophe and a letter, are never in one pattern.
CUTS = (("[0-9]", " \\0 "), ("([A-Za-zÀ-ÖØ-öø-įı-ɏЀ-ҁ])([[:punct:]])", "\\1 \\2"), ("([!-&(-/:-@\\[-`{-~])([A-Za-zÀ-ÖØ-öø-įı-ɏЀ-ҁ])", "\\1 \\2"))
#: What the vocabulary's patterns match in text that is not yet lower-cased.  The lower case of İ ends with a sign.
PATTERN = regex.compile(r"'[sS]|'[tT]|'[rR][eE]|'[vV][eE]|'[mM]|'[lL][lL]|'[dD]|[^\P{L}İ]*İ[^\p{L}\p{N}]*|\p{L}+|\p{N}|[^\p{L}\p{N}]+")
#: Runs that are one match.
ONE_MATCH, NO_MATCH = (regex.compile(r"[^\P{L}İ]+"), regex.compile(r"[^\p{L}\p{N}]+")), regex.compile(r"(?!)")
WORD_END = "</w>"


def vocabulary_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def split_words(texts: pa.Array) -> pa.ListArray:
    """The texts split at white space as the library takes it; empty words are possible."""
    odd = pc.any(pc.match_substring_regex(texts, ODD_SPACE)).as_py()
    return pc.split_pattern_regex(texts, f"[{SPACES}]+") if odd else pc.utf8_split_whitespace(texts)


def split_parts(words: pa.Array) -> pa.ListArray:
    """Words in lower ASCII case, cut at places that no pattern crosses; words that may hold special strings stay whole."""
    cut = pc.ascii_lower(words)
    for pattern, to in CUTS:
        cut = pc.replace_substring_regex(cut, pattern, to)
    return pc.ascii_split_whitespace(pc.if_else(pc.match_substring(words, "<|"), words, cut))


def offsets_of(lists: pa.ListArray) -> tuple[np.ndarray, pa.Array]:
    """(bounds from 0, values) of a list array that may be a slice."""
    bounds = lists.offsets.to_numpy().astype(np.int64)
    return bounds - bounds[0], lists.values.slice(bounds[0], bounds[-1] - bounds[0])


class PartMemory:
    """A row of integers for each part met, one after another in one array."""

    kind = np.int32

    def __init__(self, path: str):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        vocab = self.library.get_vocab(with_added_tokens=False)
        self.ends = np.zeros(max(vocab.values()) + 1, bool)
        self.ends[[i for w, i in vocab.items() if w.endswith(WORD_END)]] = True
        self.forget()

    def forget(self) -> None:
        self.at: dict[str, int] = {}
        self.start, self.size, self.n = np.zeros(1 << 12, np.int64), np.zeros(1 << 12, np.int64), 0
        self.flat, self.used = np.zeros(1 << 14, self.kind), 0

    def keep(self, parts: list[str], flat: np.ndarray, sizes: np.ndarray) -> None:
        m, total = len(sizes), len(flat)
        while self.n + m > len(self.start):
            self.start, self.size = np.append(self.start, np.zeros_like(self.start)), np.append(self.size, np.zeros_like(self.size))
        while self.used + total > len(self.flat):
            self.flat = np.append(self.flat, np.zeros_like(self.flat))
        self.start[self.n : self.n + m], self.size[self.n : self.n + m] = self.used + np.cumsum(sizes) - sizes, sizes
        self.flat[self.used : self.used + total] = flat
        self.at.update(zip(parts, range(self.n, self.n + m)))
        self.used, self.n = self.used + total, self.n + m

    def whole(self, texts: list[str]) -> list[list[int]]:
        return [e.ids for e in self.library.encode_batch_fast(texts, add_special_tokens=False)]

    def ids_of(self, parts: list[str]) -> Iterator[tuple[list[str], np.ndarray, np.ndarray]]:
        """(parts, their ids, numbers of ids), by groups.

        A run of letters is one pattern match, so it ends with the one id that ends a word: such runs are encoded as one
        text a thousand and cut after those ids.
        """
        runs = [p for p in parts if p.isalpha()]
        others = [p for p in parts if not p.isalpha()]
        for group in (runs[i : i + 1000] for i in range(0, len(runs), 1000)):
            ids = np.array(self.whole([" ".join(group)])[0], np.int32)
            cuts = np.flatnonzero(self.ends[ids]) + 1
            if len(cuts) == len(group) and cuts[-1] == len(ids):
                yield group, ids, np.diff(cuts, prepend=0)
            else:
                others += group
        if others:
            lists = self.whole(others)
            sizes = np.fromiter(map(len, lists), np.int64, len(lists))
            yield others, np.fromiter(chain.from_iterable(lists), np.int32, int(sizes.sum())), sizes

    def learn(self, parts: list[str]) -> None:
        for group, ids, sizes in self.ids_of(parts):
            self.keep(group, ids, sizes)

    def places(self, parts: list[str]) -> np.ndarray:
        """Places of distinct parts in the memory."""
        if len(self.at) + len(parts) > MEMO_PARTS:
            self.forget()
        at = self.at
        if unknown := [p for p in parts if p not in at]:
            self.learn(unknown)
        return np.fromiter(map(at.__getitem__, parts), np.int64, len(parts))

    def rows(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(all rows of the texts' parts in turn, their total size in each text)."""
        bounds, words = offsets_of(split_words(texts))
        if not len(words):
            return np.zeros(0, self.kind), np.zeros(len(texts), np.int64)
        coded = words.dictionary_encode()
        part_at, parts = offsets_of(split_parts(coded.dictionary))
        distinct = parts.dictionary_encode()
        place = self.places(distinct.dictionary.to_pylist())[distinct.indices.to_numpy()] if len(parts) else np.zeros(0, np.int64)
        word = coded.indices.to_numpy()
        many = np.diff(part_at)[word]
        place = ragged_take(place, part_at[word], many)
        sizes = self.size[place]
        before = np.concatenate([[0], np.cumsum(sizes)])[np.concatenate([[0], np.cumsum(many)])[bounds]]
        return ragged_take(self.flat, self.start[place], sizes), np.diff(before)


class WordEncoder(PartMemory):
    """Ids of whole texts."""

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(all ids, number of ids of each text)."""
        return self.rows(texts)


@cache
def second_signs() -> frozenset[str]:
    """Characters that may join one before them when a text is normalised."""
    pairs = (unicodedata.decomposition(chr(c)).split() for c in range(0x110000))
    return frozenset(chr(int(p[1], 16)) for p in pairs if len(p) == 2 and not p[0].startswith("<")) | frozenset(map(chr, [*range(0x1161, 0x1176), *range(0x11A8, 0x11C3)]))


def stands_alone(sign: str) -> bool:
    """Normalising a text that begins with this sign does not depend on what stands before."""
    return sign.isascii() or unicodedata.combining(sign) == 0 and sign not in second_signs()


class PrefixCounter(PartMemory):
    """The change of the exact token count at each character of a part.

    Changes fit in eight bits: a character adds at most the tokens of its bytes, and takes away fewer than one token has characters.
    """

    kind = np.int8

    def forget(self) -> None:
        super().forget()
        self.stems: dict[str, int] = {}

    def learn(self, parts: list[str]) -> None:
        short = [p for p in parts if len(p) <= LONG]
        counts = self.counted({p[:i] for p in short for i in range(1, len(p) + 1)})
        flat = np.fromiter((counts[p[:i]] for p in short for i in range(1, len(p) + 1)), np.int64)
        sizes = np.fromiter(map(len, short), np.int64, len(short))
        self.keep_counts(short, flat, sizes)
        for p in parts:
            if len(p) > LONG:
                self.keep_counts([p], self.long_part(p), np.array([len(p)]))

    def keep_counts(self, parts: list[str], counts: np.ndarray, sizes: np.ndarray) -> None:
        change = np.diff(counts, prepend=0)
        first = (np.cumsum(sizes) - sizes)[sizes > 0]
        change[first] = counts[first]
        if len(change) and (change.min() < -128 or change.max() > 127):
            raise OverflowError("a token count changes by more than eight bits hold")
        self.keep(parts, change.astype(np.int8), sizes)

    def counted(self, beginnings: set[str]) -> dict[str, int]:
        """Token counts of beginnings; short ones are remembered."""
        out = {b: self.stems[b] for b in beginnings if b in self.stems}
        for group, _, sizes in self.ids_of([b for b in beginnings if b not in out]):
            out.update(zip(group, sizes.tolist()))
        if len(self.stems) > MEMO_STEMS:
            self.stems = {}
        self.stems.update((b, n) for b, n in out.items() if len(b) <= STEM)
        return out

    def long_part(self, part: str) -> np.ndarray:
        """Counts at each character of a long part: piece by piece, anew after each special string."""
        specials = sorted((t.content for t in self.library.get_added_tokens_decoder().values()), key=len, reverse=True)
        out, base, at = [], 0, 0
        for m in regex.finditer("|".join(map(regex.escape, specials)), part):
            plain = self.pieces(part[at : m.end()])
            plain[-1] = (plain[m.start() - at - 1] if m.start() > at else 0) + 1
            out.append(plain + base)
            base, at = base + int(plain[-1]), m.end()
        return np.concatenate([*out, self.pieces(part[at:]) + base])

    def pieces(self, text: str) -> np.ndarray:
        """Counts at each character of text without special strings: match by match of the pattern."""
        clusters = split_before(text, stands_alone)
        plain = [unicodedata.normalize("NFC", c) for c in clusters]
        at = {a: k for k, a in enumerate(np.cumsum([0, *map(len, plain)]).tolist())}
        cuts = [at[m.start()] for m in PATTERN.finditer("".join(plain)) if m.start() in at]
        out, base = [np.zeros(0, np.int64)], 0
        for a, b in zip(cuts, [*cuts[1:], len(clusters)]):
            piece = "".join(clusters[a:b])
            got = self.library_counts(piece, range(1, len(piece) + 1)) if len(piece) <= LONG else self.last_tokens(clusters[a:b])
            out.append(np.array(got, np.int64) + base)
            base += int(got[-1])
        return np.concatenate(out)

    def library_counts(self, text: str, at) -> list[int]:
        return [len(x) for x in self.whole([text[:i] for i in at])]

    @property
    def models(self):
        """(the library's model, the same merges without word ends, all token strings, length of the longest)."""
        if not hasattr(self, "_models"):
            import json

            from tokenizers.models import BPE

            told = json.loads(self.library.to_str())["model"]
            merges = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in told["merges"]]
            self._models = (self.library.model, BPE(told["vocab"], merges), told["vocab"], max(map(len, told["vocab"])))
            self.pairs: dict[tuple[str, str, bool], bool] = {}
        return self._models

    def stays(self, a: str, b: str, last: bool) -> bool:
        """Whether two tokens side by side are what the merges make of their string; ``last``: the second ends a word."""
        key = (a, b, last)
        if key not in self.pairs:
            if len(self.pairs) > MEMO_STEMS:
                self.pairs.clear()
            model = self.models[0 if last else 1]
            self.pairs[key] = [t.value for t in model.tokenize(a + b)] == [x for x in (a, b + WORD_END * last) if x]
        return self.pairs[key]

    def last_tokens(self, clusters: list[str]) -> list[int]:
        """Counts at each character of a long run of letters or signs, given as characters with what joins them.

        Merged tokens stand side by side if and only if each two neighbours do, so the tokens of a prefix are its last one and
        those of the prefix before it.  A prefix's own last token ends a word, those before it do not.  The few prefixes that
        are no single match of the pattern are left to the library.
        """
        _, _, vocab, longest = self.models
        kind = next((k for k in ONE_MATCH if k.match(clusters[0])), NO_MATCH)
        s, last, count, out, done = "", [""], [0], [], 0

        def token(text: str, i: int, tail: str) -> tuple[str, int]:
            for a in range(i - 1, max(-1, i - 1 - longest), -1):
                t = text[a:i]
                if t + tail in vocab and self.stays(last[a], t, bool(tail)):
                    return t, count[a] + 1
            raise ValueError("no token ends here")

        single = True
        for c in clusters:
            for j in range(1, len(c) + 1):
                fits = single and kind.fullmatch(unicodedata.normalize("NFC", c[:j]))
                if not fits:
                    out += self.library_counts("".join(clusters), [done + j])
                    continue
                coded = s + "".join(x for x, _ in self.library.pre_tokenizer.pre_tokenize_str(self.library.normalizer.normalize_str(c[:j])))
                del last[len(s) + 1 :], count[len(s) + 1 :]
                for i in range(len(s) + 1, len(coded) + 1):
                    t, n = token(coded, i, "")
                    last.append(t)
                    count.append(n)
                out.append(token(coded, len(coded), WORD_END)[1])
            single, s, done = bool(fits), coded if fits else s, done + len(c)
        return out

    def prefix_changes(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(bounds, changes): changes[bounds[i] : bounds[i + 1]] sum up to text i's exact count at each of its characters."""
        changes, _ = self.rows(texts)
        points = np.frombuffer("".join(texts.to_pylist()).encode("utf-32-le", "surrogatepass"), np.uint32)
        space = IS_SPACE[np.minimum(points, 0x3000)] & (points <= 0x3000)
        out = np.zeros(len(points), np.int8)
        out[~space] = changes
        return np.concatenate([[0], np.cumsum(pc.utf8_length(texts).to_numpy(zero_copy_only=False))]).astype(np.int64), out


def split_before(text: str, where) -> list[str]:
    cuts = [i for i, c in enumerate(text) if i == 0 or where(c)]
    return [text[a:b] for a, b in zip(cuts, [*cuts[1:], len(text)])]


def encoder(path: str) -> WordEncoder:
    return worker_slot(("encoder", path), lambda: WordEncoder(path))


def prefix_counter(path: str) -> PrefixCounter:
    return worker_slot(("prefixes", path), lambda: PrefixCounter(path))


def filled(column) -> pa.Array:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return pc.fill_null(column.cast(pa.string()), "")


def prefix_table(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str | None = None) -> DataFrame:
    """Rows (id, n_bytes, prefix_changes): a byte for each character of the text, signed, by which the exact count of the
    prefix that ends there differs from that of the prefix before.  prefix_counts() turns them into counts."""
    path, kind = vocabulary or vocabulary_path(), df.schema[id_col].dataType.simpleString()

    def per_slice(batch):
        texts = filled(batch.column("text"))
        bounds, changes = prefix_counter(path).prefix_changes(texts)
        stored = pa.Array.from_buffers(pa.binary(), len(texts), [None, pa.py_buffer(bounds.astype(np.int32).tobytes()), pa.py_buffer(changes.tobytes())])
        return pa.RecordBatch.from_arrays([batch.column("id"), pc.cast(pc.binary_length(texts), pa.int64()), stored], names=["id", "n_bytes", "prefix_changes"])

    return map_arrow(df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), f"id {kind}, n_bytes long, prefix_changes binary", "text", per_slice)


def prefix_counts(changes: bytes) -> np.ndarray:
    """Exact token counts of all prefixes, that of the empty one first."""
    return np.concatenate([[0], np.cumsum(np.frombuffer(changes, np.int8), dtype=np.int64)])


def tokens_at(offset: int, changes: bytes) -> int:
    """Tokens of the first ``offset`` characters, from what is stored."""
    return int(np.frombuffer(changes, np.int8, offset).sum(dtype=np.int64))


def longest_prefix(budget: int, changes: bytes) -> int:
    """The largest offset whose prefix has at most ``budget`` tokens, from what is stored."""
    return int(np.flatnonzero(prefix_counts(changes) <= budget)[-1])


def stored_counts(table: DataFrame) -> DataFrame:
    """Rows (id, n_bytes, n_tokens) of a prefix table: the count at the last prefix of each text."""
    kind = table.schema["id"].dataType.simpleString()

    def per_slice(batch):
        stored = batch.column("prefix_changes")
        bounds = np.frombuffer(stored.buffers()[1], np.int32)[stored.offset : stored.offset + len(stored) + 1].astype(np.int64)
        changes = np.frombuffer(stored.buffers()[2] or b"", np.int8)[bounds[0] : bounds[-1]]
        total = np.concatenate([[0], np.cumsum(changes, dtype=np.int64)])[bounds - bounds[0]]
        return pa.RecordBatch.from_arrays([batch.column("id"), batch.column("n_bytes"), pa.array(np.diff(total))], names=["id", "n_bytes", "n_tokens"])

    return map_arrow(table.select("id", "n_bytes", "prefix_changes"), f"id {kind}, n_bytes long, n_tokens long", "prefix_changes", per_slice)


def truncate_to_budget(df: DataFrame, budget: int, id_col: str = "doc_id", text_col: str = "text", vocabulary: str | None = None) -> DataFrame:
    """Rows (id, text, n_tokens): the longest prefix of each text within the budget."""
    path, kind = vocabulary or vocabulary_path(), df.schema[id_col].dataType.simpleString()

    def per_slice(batch):
        texts = filled(batch.column("text"))
        bounds, changes = prefix_counter(path).prefix_changes(texts)
        cut, own = [], []
        for text, a, b in zip(texts.to_pylist(), bounds, bounds[1:]):
            stored = changes[a:b].tobytes()
            end = longest_prefix(budget, stored)
            cut.append(text[:end])
            own.append(tokens_at(end, stored))
        return pa.RecordBatch.from_arrays([batch.column("id"), pa.array(cut, pa.string()), pa.array(own, pa.int64())], names=["id", "text", "n_tokens"])

    return map_arrow(df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), f"id {kind}, text string, n_tokens long", "text", per_slice)


def write_tokens(df: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", vocabulary: str | None = None, end_id: int | None = END_ID, encoding: str = "dictionary", row_group_bytes: int = 16 << 20, page_rows: int = 2000) -> None:
    """Write Parquet files of (id, part, local_start, n_tokens, tokens) in ascending id order.

    Texts are dealt by range and sorted before they are encoded, so only text is shuffled and ids
    go straight to the files.  ``encoding`` is "dictionary" or "delta"; row groups and pages are
    bounded, and Parquet's page indexes let a reader skip pages by id.  ``local_start`` counts the ids
    before the document in its part; token_index() gives what stands before each part.
    """
    source, kind = vocabulary or vocabulary_path(), df.schema[id_col].dataType.simpleString()
    rows = df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).repartitionByRange("id").sortWithinPartitions("id", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, done, enc = TaskContext.get().partitionId(), 0, encoder(source)
        for piece in gathered(batches, "text"):
            ids, counts = enc.encode(filled(piece.column("text")))
            if end_id is not None:
                ids, counts = np.insert(ids, np.cumsum(counts), end_id), counts + 1
            ends = np.cumsum(counts)
            n = len(counts)
            yield pa.RecordBatch.from_arrays(
                [piece.column("id"), pa.array(np.full(n, part, np.int32)), pa.array(done + ends - counts), pa.array(counts, pa.int64()), pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]), pa.int32()), pa.array(ids, pa.int32()))],
                names=["id", "part", "local_start", "n_tokens", "tokens"],
            )
            done += int(counts.sum())

    delta = encoding == "delta"
    coded = rows.mapInArrow(run, f"id {kind}, part int, local_start long, n_tokens long, tokens array<int>")
    (
        coded.write.option("compression", "zstd")
        .option("parquet.block.size", row_group_bytes)
        .option("parquet.page.row.count.limit", page_rows)
        .option("parquet.writer.version", "PARQUET_2_0" if delta else "PARQUET_1_0")
        .option("parquet.enable.dictionary#tokens.list.element", str(not delta).lower())
        .parquet(path)
    )


def token_index(files: DataFrame) -> DataFrame:
    """Rows (part, base): ids before each part.  Reads two small columns; as many rows as parts."""
    parts = files.groupBy("part").agg(F.sum("n_tokens").alias("n"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    return parts.select("part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))


def read_tokens(spark: SparkSession, path: str, id_type: str = "bigint") -> DataFrame:
    """The files' rows with ``start``, the ids of all documents before.  Columns not asked for are not read."""
    files = spark.read.schema(f"id {id_type}, part int, local_start long, n_tokens long, tokens array<int>").parquet(path)
    # One row for each written part: its size is the number of files, not that of the data.
    return files.join(F.broadcast(token_index(files)), "part").select("id", (F.col("base") + F.col("local_start")).alias("start"), "n_tokens", "tokens")


def token_digests(rows: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) from the ids read back, as little-endian unsigned 32-bit integers."""
    kind = rows.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            tokens = batch.column("tokens")
            off, values = tokens.offsets.to_numpy(), memoryview(tokens.values.to_numpy(zero_copy_only=False).astype("<u4")).cast("B")
            crc = [zlib.crc32(values[4 * a : 4 * b]) for a, b in zip(off, off[1:])]
            yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("start"), pa.array(np.diff(off).astype(np.int64)), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return rows.select("id", "start", "tokens").mapInArrow(run, f"doc_id {kind}, start long, n_tokens long, ids_crc32 long")


def op2_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens_of(read_table(spark, sf_dir, "documents"))


def tokens_of(docs: DataFrame) -> DataFrame:
    spark, path = docs.sparkSession, new_path(docs.sparkSession, "tokens")
    write_tokens(docs, path)
    return token_digests(read_tokens(spark, path, docs.schema["doc_id"].dataType.simpleString()))


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    stored = write_read(prefix_table(read_table(spark, sf_dir, "documents")), "prefixes", compression="zstd")
    return stored_counts(stored).select(F.col("id").alias("doc_id"), "n_bytes", "n_tokens", (F.col("n_tokens") > TOKEN_LIMIT).alias("over_limit"))
