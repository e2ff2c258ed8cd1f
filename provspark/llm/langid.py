"""Operator 5, language identification by words first, then shorter and shorter character n-grams.

Learning: words of a sample of labelled texts are counted per language; they and their character n-grams of each length form
tables of log frequencies, n-grams among those of their length.  Only the number of texts learned from is bounded.  Prediction: a
known word adds its log frequency in each language; an unseen word adds the mean log frequency
of its known n-grams of the greatest length at which any is known.

Defined cases: a null text or one without a letter is ``und`` with score 0, as is any text when
nothing was learned; a text with letters of which nothing is known takes the first learned language with an even
score; rows with a null id or language teach nothing; a null id is not held out; repeated rows
are repeated; other columns are not read; ties go to the language that sorts first.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provspark.llm.common import drop_table, filter_arrow, if_small, map_arrow, read_table, worker_slot, write_read
from provspark.llm.tokens import filled

#: The classifier is fitted on about so many labelled texts of each language, taken by hash; on fewer where that would be more than
#: FIT_ROWS in all.
FIT_TEXTS, FIT_ROWS = 600, 200_000
LONGEST_GRAM = 4
UNDETERMINED = "und"
#: Texts below this score are rejected by with_language; those that no learned word or n-gram tells apart always are.
LEAST_SCORE = 0.0
MEMO_WORDS = 200_000


@dataclass
class Model:
    """Log frequencies by language; the tables hold what is in the bounded sample of texts."""

    languages: list[str]
    words: dict[str, int]
    grams: dict[str, int]
    word_scores: np.ndarray
    gram_scores: np.ndarray


def words_of(texts: pa.Array) -> pa.ListArray:
    """Runs of letters of the lower-cased texts; empty strings at the ends are possible."""
    return pc.ascii_split_whitespace(pc.replace_substring_regex(pc.utf8_lower(texts), r"[^\p{L}]+", " "))


def word_counts(docs: DataFrame) -> DataFrame:
    """(lang, word, n) of rows (text, lang), partly summed by slice."""

    def per_slice(batch):
        split = words_of(filled(batch.column("text")))
        langs = batch.column("lang").dictionary_encode()
        sizes = np.diff(split.offsets.to_numpy())
        coded = split.flatten().dictionary_encode()
        n = max(1, len(coded.dictionary))
        both, counts = np.unique(np.repeat(langs.indices.to_numpy(), sizes).astype(np.int64) * n + coded.indices.to_numpy(), return_counts=True)
        return pa.RecordBatch.from_arrays([langs.dictionary.take(pa.array(both // n)).cast(pa.string()), coded.dictionary.take(pa.array(both % n)).cast(pa.string()), pa.array(counts, pa.int64())], names=["lang", "word", "n"])

    return map_arrow(docs.select("text", "lang"), "lang string, word string, n long", "text", per_slice).filter("word <> ''").groupBy("lang", "word").agg(F.sum("n").alias("n"))


def as_table(rows: list, languages: list[str], part=lambda key: 0) -> tuple[dict[str, int], np.ndarray]:
    """(place of each key, log frequencies by language) of rows (lang, key, n), smoothed by half a count; frequencies
    are those among the keys of one part."""
    at: dict[str, int] = {}
    for _, key, _ in rows:
        at.setdefault(key, len(at))
    place = {x: i for i, x in enumerate(languages)}
    counts = np.zeros((len(at), len(languages)), np.float32)
    for lang, key, n in rows:
        counts[at[key], place[lang]] += n
    parts = np.fromiter((part(key) for key in at), np.int64, len(at))
    for p in np.unique(parts):
        mine = parts == p
        counts[mine] = np.log((counts[mine] + 0.5) / (counts[mine].sum(axis=0) + 0.5 * mine.sum()))
    return at, counts


def fit(labelled: DataFrame, fit_texts: int = FIT_TEXTS, fit_rows: int = FIT_ROWS) -> Model:
    """labelled: (doc_id, text, lang) to learn from.  What reaches the driver is the vocabulary of the texts learned from."""
    rows = labelled.filter("lang IS NOT NULL AND doc_id IS NOT NULL")
    per = write_read(rows.groupBy("lang").agg(F.count("*").alias("n_lang")), "langs")
    languages = per.count()
    if not languages:
        return Model([], {}, {}, np.zeros((0, 0), np.float32), np.zeros((0, 0), np.float32))
    share = F.lit(float(min(fit_texts, fit_rows / languages))) / F.col("n_lang")
    taken = rows.join(if_small(per, languages), "lang").filter(F.pmod(F.xxhash64(F.lit("fit"), "doc_id"), F.lit(1 << 30)) < share * (1 << 30))
    counts = write_read(word_counts(taken), "words")
    padded = F.concat(F.lit(" "), "word", F.lit(" "))
    grams = F.flatten(F.transform(F.sequence(F.lit(1), F.lit(LONGEST_GRAM)), lambda n: F.transform(F.sequence(F.lit(1), F.greatest(F.length(padded) - n + 1, F.lit(1))), lambda i: F.substring(padded, i, n))))
    gram_counts = counts.select("lang", "n", F.explode(grams).alias("gram")).filter("trim(gram) <> ''").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    words, some = counts.select("lang", "word", "n").collect(), gram_counts.select("lang", "gram", "n").collect()
    known = sorted({r["lang"] for r in words})
    drop_table(counts)
    drop_table(per)
    (word_at, word_scores), (gram_at, gram_scores) = as_table(words, known), as_table(some, known, len)
    return Model(known, word_at, gram_at, word_scores, gram_scores)


class Scorer:
    """Scores of words by language, remembered up to a bound."""

    def __init__(self, model: Model):
        self.model = model
        self.forget()

    def forget(self) -> None:
        self.at: dict[str, int] = {}
        self.scores = np.zeros((1 << 12, len(self.model.languages)), np.float32)

    def learn(self, words: list[str]) -> None:
        m, n = self.model, len(self.at)
        out = np.zeros((len(words), len(m.languages)), np.float32)
        flat, sizes, rows = [], [], []
        grams = m.grams
        for k, w in enumerate(words):
            if (i := m.words.get(w)) is not None:
                out[k] = m.word_scores[i]
                continue
            p = f" {w} "
            for size in range(LONGEST_GRAM, 0, -1):
                found = [g for i in range(len(p) - size + 1) if (g := grams.get(p[i : i + size])) is not None]
                if found:
                    flat += found
                    sizes.append(len(found))
                    rows.append(k)
                    break
        if rows:
            starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
            out[rows] = np.add.reduceat(m.gram_scores[flat], starts, axis=0) / np.array(sizes, np.float32)[:, None]
        while n + len(words) > len(self.scores):
            self.scores = np.concatenate([self.scores, np.zeros_like(self.scores)])
        self.scores[n : n + len(words)] = out
        self.at.update(zip(words, range(n, n + len(words))))

    def rows(self, words: list[str]) -> np.ndarray:
        if len(self.at) + len(words) > MEMO_WORDS:
            self.forget()
        if new := [w for w in words if w not in self.at]:
            self.learn(new)
        return np.fromiter(map(self.at.__getitem__, words), np.int64, len(words))

    def predict(self, texts: pa.Array) -> tuple[list[str], np.ndarray]:
        """(language, probability) of each text."""
        languages = self.model.languages
        split = words_of(texts)
        bounds = split.offsets.to_numpy().astype(np.int64) - split.offsets[0].as_py()
        coded = split.flatten().dictionary_encode()
        n = len(texts)
        if not languages or not len(coded):
            return [UNDETERMINED] * n, np.zeros(n)
        words = coded.dictionary.to_pylist()
        place, codes = self.rows(words), coded.indices.to_numpy()
        real = np.fromiter(map(len, words), np.int64, len(words)) > 0
        weights = np.where(real[:, None], self.scores[place], 0).astype(np.float64)
        sums = np.zeros((n, len(languages)))
        for j in range(len(languages)):
            total = np.concatenate([[0], np.cumsum(weights[codes, j])])
            sums[:, j] = total[bounds[1:]] - total[bounds[:-1]]
        some = np.concatenate([[0], np.cumsum(real[codes])])
        lettered = some[bounds[1:]] > some[bounds[:-1]]
        best = np.round(sums, 6).argmax(axis=1)
        p = 1 / np.exp(np.minimum(sums - sums[np.arange(n), best][:, None], 0)).sum(axis=1)
        return [languages[b] if ok else UNDETERMINED for b, ok in zip(best, lettered)], np.where(lettered, p, 0)


def shared_scorer(spark: SparkSession, model: Model):
    """A function that gives a worker's scorer.  The model is broadcast; its size is bounded by its parameters."""
    shared = spark.sparkContext.broadcast(model)
    number = shared._jbroadcast.id()

    def get() -> Scorer:
        return worker_slot(("scorer", number), lambda: Scorer(shared.value))

    return get


def identify(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, lang_pred, score)."""
    kind, scorer = docs.schema[id_col].dataType.simpleString(), shared_scorer(docs.sparkSession, model)

    def per_slice(batch):
        lang, score = scorer().predict(filled(batch.column("text")))
        return pa.RecordBatch.from_arrays([batch.column("id"), pa.array(lang, pa.string()), pa.array(score, pa.float64())], names=["id", "lang_pred", "score"])

    return map_arrow(docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), f"id {kind}, lang_pred string, score double", "text", per_slice)


def with_language(docs: DataFrame, model: Model, text_col: str = "text", least_score: float = LEAST_SCORE) -> DataFrame:
    """The rows whose text is in a learned language with at least this score; with nothing learned, those with a letter."""
    scorer = shared_scorer(docs.sparkSession, model)

    def keep(batch):
        texts = filled(batch.column(text_col))
        if not scorer().model.languages:
            return pc.match_substring_regex(texts, r"\p{L}")
        lang, score = scorer().predict(texts)
        k = len(scorer().model.languages)
        return (np.array(lang) != UNDETERMINED) & (score >= least_score) & ((score > (1 + 1e-9) / k) | (k == 1))

    return filter_arrow(docs, text_col, keep)


def remainder(id_col: str = "doc_id") -> F.Column:
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % 3


def fit_on_documents(docs: DataFrame) -> Model:
    return fit(docs.select("doc_id", "text", "lang").filter(remainder() != 1))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    found = identify(docs, fit_on_documents(docs))
    return found.select(F.col("id").alias("doc_id"), F.coalesce(remainder("id") == 1, F.lit(False)).alias("held_out"), "lang_pred", "score")
