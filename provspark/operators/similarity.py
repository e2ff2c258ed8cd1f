"""Encoders and top-k retrieval by cosine: exact blocks, token prefixes, hyperplane bands, cells, and MinHash for text."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from provspark.functions.text import hashed_shingles, let, words
from provspark.operators.shared import cut, spread

#: Bytes of vectors in one broadcast block of the exact strategy.
BLOCK_BYTES = 64 << 20
#: Cells of the matrix of a slice of the left side and a block that are held at once.
SLICE_CELLS = 8 << 20


def term_counts(df: DataFrame, id_col: str, text: str) -> DataFrame:
    """Exact sparse encoding: (id, token, weight), weights being counts over the vector's norm."""
    counts = df.select(F.col(id_col).alias("id"), F.explode(words(F.col(text))).alias("token")).groupBy("id", "token").agg(F.count("*").alias("n"))
    norms = counts.groupBy("id").agg(F.sqrt(F.sum(F.col("n") * F.col("n"))).alias("norm"))
    return counts.join(norms, "id").select("id", "token", (F.col("n") / F.col("norm")).alias("weight"))


def hashed_ngrams(df: DataFrame, id_col: str, text: str, dims: int = 256, n: int = 3) -> DataFrame:
    """(id, embedding): signed hashing of distinct character n-grams, unit length, all in code generation."""
    grams = let(F.lower(F.col(text)), lambda t: F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.length(t) - (n - 1), F.lit(1))), lambda i: F.substring(t, i, n))))
    g = df.select(F.col(id_col).alias("id"), F.explode(grams).alias("g")).select("id", F.pmod(F.xxhash64("g"), F.lit(dims)).alias("d"), F.when(F.pmod(F.hash("g"), F.lit(2)) == 0, 1.0).otherwise(-1.0).alias("s"))
    cells = g.groupBy("id", "d").agg(F.sum("s").alias("v"))
    vec = cells.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("d", "v"))).alias("m"), F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))
    return vec.select("id", F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda i: F.coalesce(F.try_element_at("m", i.cast("bigint")), F.lit(0.0)) / F.when(F.col("norm") > 0, F.col("norm")).otherwise(1.0)).cast("array<float>").alias("embedding"))


def callable_encoder(df: DataFrame, id_col: str, text: str, load: Callable[[], Callable[[list[str]], np.ndarray]]) -> DataFrame:
    """(id, embedding) from any model: ``load`` runs once a worker and gives a function of texts."""

    @F.pandas_udf("array<float>")
    def encode(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        model = load()
        for batch in batches:
            yield pd.Series(list(np.asarray(model(batch.fillna("").tolist()), dtype=np.float32)))

    return df.select(F.col(id_col).alias("id"), encode(F.col(text)).alias("embedding"))


def best_per_item(pairs: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("id").orderBy(F.desc("sim"), "other")
    return pairs.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def raw_rows(embeddings: pd.Series) -> np.ndarray:
    return np.array(embeddings.tolist(), dtype=np.float64).reshape(len(embeddings), -1)


def unit_rows(m: np.ndarray) -> np.ndarray:
    """Unit rows in double; zero vectors stay zero."""
    return m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300)


def numbers(embeddings: pd.Series) -> np.ndarray:
    return unit_rows(raw_rows(embeddings))


def cosines(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.round(np.clip(x @ y.T, -1, 1), 12)


#: (r, c, sim) of pairs of a slice's and a block's rows.
Hits = tuple[np.ndarray, np.ndarray, np.ndarray]


@dataclass(frozen=True)
class Strategy:
    """How slices of the left side meet a block of the right one inside a task.

    ``prepare(rows, unit)`` makes what is kept of a block, ``row_bytes`` for each of its rows; ``find(rows, same, kept)`` gives a
    slice's hits, ``same`` being true where a row would meet itself.
    """

    prepare: Callable[[np.ndarray, np.ndarray], object]
    find: Callable[[np.ndarray, np.ndarray, object], Hits]
    row_bytes: int = 0


def every_pair(threshold: float, k: int | None = None) -> Strategy:
    """All pairs at the threshold, or of each left row its k best and what ties with the last of them."""

    def find(rows: np.ndarray, same: np.ndarray, unit: np.ndarray) -> Hits:
        sims = cosines(unit_rows(rows), unit)
        sims[same] = -2
        least = np.full(len(rows), threshold)
        if k is not None and k < len(unit):
            least = np.maximum(least, -np.partition(-sims, k - 1, axis=1)[:, k - 1])
        r, c = np.nonzero(sims >= least[:, None])
        return r, c, sims[r, c]

    return Strategy(lambda rows, unit: unit, find)


def pair_rows(own: np.ndarray, ids: np.ndarray, hits: list[Hits]) -> pd.DataFrame:
    r, c, sim = hits[0]
    return pd.DataFrame({"id": own[r], "other": ids[c], "sim": sim})


def blocked(left: DataFrame, right: DataFrame, strategies: list[Strategy], schema: str = "id long, other long, sim double", rows_of: Callable[[np.ndarray, np.ndarray, list[Hits]], pd.DataFrame] = pair_rows, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """``rows_of(own, ids, hits)`` of every slice of the left side and block of the right one, with the hits of each strategy.

    A right side within ``block_bytes`` is sent to every worker once.  A larger one and the left side are dealt into blocks of that
    size, and each pair of blocks meets in a task; nothing of either goes through the driver.  Pairs are never shuffled.
    """
    spark, n = left.sparkSession, right.count()
    dims = len(right.select("embedding").first()[0] or []) if n else 0
    row_bytes = dims * 8 + sum(s.row_bytes for s in strategies)
    blocks = max(1, -(-n * row_bytes // block_bytes))
    # Columns named anew: sides made of one table would lose theirs in a cogroup.
    left, right = (x.filter("embedding IS NOT NULL").select(F.col("id").alias("id"), F.col("embedding").alias("embedding")) for x in (left, right))

    def prepared(part: pd.DataFrame) -> tuple[np.ndarray, list]:
        rows = raw_rows(part["embedding"])
        return part["id"].to_numpy(dtype=np.int64), [s.prepare(rows, unit_rows(rows)) if len(rows) else None for s in strategies]

    def met(frame: pd.DataFrame, ids: np.ndarray, kept: list) -> Iterator[pd.DataFrame]:
        """Slices of the left side, each with a bounded number of cells."""
        none = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        step = max(1, SLICE_CELLS // max(1, len(ids)))
        for at in range(0, max(1, len(frame)), step):
            part = frame.iloc[at : at + step]
            own = part["id"].to_numpy(dtype=np.int64)
            if not len(own) or not len(ids):
                yield rows_of(own, ids, [none] * len(kept))
                continue
            rows, same = raw_rows(part["embedding"]), own[:, None] == ids[None, :]
            yield rows_of(own, ids, [s.find(rows, same, k) for s, k in zip(strategies, kept)])

    if blocks == 1:
        held = spark.sparkContext.broadcast(right.toPandas())

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            block = None
            for f in frames:
                block = block or prepared(held.value)
                yield from met(f, *block)

        return spread(left).mapInPandas(run, schema)
    # Enough pairs of blocks for all cores.
    rows = max(1, -(-left.count() * dims * 8 // block_bytes), -(-2 * spark.sparkContext.defaultParallelism // blocks))
    deal = lambda df, own, size, other, count: df.withColumn(own, F.pmod(F.xxhash64("id"), F.lit(size))).withColumn(other, F.explode(F.sequence(F.lit(0), F.lit(count - 1))))
    a, b = deal(left, "i", rows, "j", blocks), deal(right, "j", blocks, "i", rows)
    meet = lambda x, y: pd.concat(list(met(x, *prepared(y))), ignore_index=True)
    return a.withColumn("j", F.col("j").cast("bigint")).groupBy("i", "j").cogroup(b.withColumn("i", F.col("i").cast("bigint")).groupBy("i", "j")).applyInPandas(meet, schema)


def blocked_pairs(left: DataFrame, right: DataFrame, threshold: float, k: int | None = None, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """(id, other, sim) of all pairs at the threshold by matrix products, or of those that may be among an id's k best."""
    return blocked(left, right, [every_pair(threshold, k)], block_bytes=block_bytes)


def exact_pairs(left: DataFrame, right: DataFrame, threshold: float) -> DataFrame:
    return blocked_pairs(left, right, threshold)


def exact_blocked(left: DataFrame, right: DataFrame, threshold: float, k: int, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The k best of each id, ties to the least other id."""
    return best_per_item(blocked_pairs(left, right, threshold, k, block_bytes), k)


def prefix_pairs(left: DataFrame, right: DataFrame, threshold: float) -> DataFrame:
    """Pairs (id, other, sim) of sparse unit vectors (id, token, weight) with a cosine of at least ``threshold``, none missed.

    Tokens are ordered from rare to frequent.  What follows the shortest prefix whose rest is shorter than the threshold cannot reach
    it alone, so two similar vectors share a token of both prefixes; the frequent tokens, which would pair everything, seldom are.
    Candidates are then scored in full.
    """
    df = right.groupBy("token").agg(F.count("*").alias("df"))
    order = Window.partitionBy("id").orderBy("df", "token").rowsBetween(Window.unboundedPreceding, -1)

    def prefix(vectors: DataFrame) -> DataFrame:
        before = F.coalesce(F.sum(F.col("weight") * F.col("weight")).over(order), F.lit(0.0))
        return vectors.join(df, "token").withColumn("before", before).filter(F.lit(1.0) - F.col("before") >= threshold * threshold - 1e-9).select("id", "token")

    cands = prefix(left).join(prefix(right).withColumnRenamed("id", "other"), "token").filter("id <> other").select("id", "other").distinct()
    r = right.select(F.col("id").alias("other"), "token", F.col("weight").alias("w"))
    return cands.join(left, "id").join(r, ["other", "token"]).groupBy("id", "other").agg(F.round(F.sum(F.col("weight") * F.col("w")), 6).alias("sim")).filter(F.col("sim") >= threshold)


def hyperplane_keys(rows: np.ndarray, bands: int, bits: int, seed: int = 7) -> np.ndarray:
    """A key a band and row: the signs of random projections."""
    planes = np.random.default_rng(seed).standard_normal((bands * bits, rows.shape[1])).reshape(bands, bits, -1)
    weights = np.left_shift(1, np.arange(bits), dtype=np.int32 if bits < 31 else np.int64)
    return np.stack([(rows @ p.T > 0) @ weights for p in planes])


def band_shape(rows: int, threshold: float, recall: float = 0.97, bucket: int = 16) -> tuple[int, int]:
    """(bands, bits): bits grow with the logarithm of the rows, so buckets keep their size; bands follow from the wished recall."""
    bits = max(4, int(np.ceil(np.log2(max(1, rows) / bucket))))
    same = (1 - np.arccos(min(1.0, threshold)) / np.pi) ** bits
    return max(1, int(np.ceil(np.log(1 - recall) / np.log1p(-same)))), bits


def hyperplanes(threshold: float, bands: int, bits: int) -> Strategy:
    """Rows that share a band's key, verified.  A block keeps its keys in order; a pair counts once whatever the bands that it shares."""

    def prepare(rows: np.ndarray, unit: np.ndarray) -> tuple:
        keys = hyperplane_keys(rows, bands, bits)
        order = np.argsort(keys, axis=1, kind="stable")
        return unit, np.take_along_axis(keys, order, axis=1), order.astype(np.int32)

    def find(rows: np.ndarray, same: np.ndarray, kept: tuple) -> Hits:
        unit, keys, order = kept
        shared = np.zeros(same.shape, bool)
        for own, theirs, at in zip(hyperplane_keys(rows, bands, bits), keys, order):
            low = np.searchsorted(theirs, own)
            n = np.searchsorted(theirs, own, "right") - low
            shared[np.repeat(np.arange(len(own)), n), at[np.arange(n.sum()) + np.repeat(low - np.cumsum(n) + n, n)]] = True
        shared &= ~same
        cols = np.nonzero(shared.any(axis=0))[0]
        sims = cosines(unit_rows(rows), unit[cols])
        r, c = np.nonzero((sims >= threshold) & shared[:, cols])
        return r, cols[c], sims[r, c]

    return Strategy(prepare, find, (8 if bits < 31 else 12) * bands)


def hyperplane_strategy(right: DataFrame, threshold: float, bands: int | None = None, bits: int | None = None) -> Strategy:
    if bands is None or bits is None:
        bands, bits = band_shape(right.count(), threshold)
    return hyperplanes(threshold, bands, bits)


def hyperplane_pairs(left: DataFrame, right: DataFrame, threshold: float, dims: int | None = None, bands: int | None = None, bits: int | None = None) -> DataFrame:
    """Pairs that share a band's key, verified where they meet; ``dims`` is read from the vectors."""
    return blocked(left, right, [hyperplane_strategy(right, threshold, bands, bits)])


def some_rows(df: DataFrame, rows: int, seed: int) -> DataFrame:
    """About ``rows`` rows, by a seeded hash of their ids."""
    share = min(1.0, rows / max(1, df.count()))
    return df.filter(F.pmod(F.xxhash64(F.lit(seed), "id"), F.lit(1 << 30)) < int(share * (1 << 30)))


def nearest_cells(centers: np.ndarray, x: np.ndarray) -> np.ndarray:
    return ((centers**2).sum(1)[None, :] - 2 * x @ centers.T).argsort(axis=1, kind="stable")


def cell_model(left: DataFrame, right: DataFrame, threshold: float, cells: int | None = None, recall: float = 0.95, fit_rows: int = 20_000, probe_rows: int = 500, seed: int = 7) -> tuple[np.ndarray, int, list[float]]:
    """(centers, probes, recall by number of probes): k-means on a bounded sample of about the square root of the rows' number of cells.

    Probes are the fewest that reach the wished recall between a sample of the left side and that of the right one.
    """
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    left, right = left.filter("embedding IS NOT NULL"), right.filter("embedding IS NOT NULL")
    cells = cells or max(2, round(right.count() ** 0.5))
    sample = some_rows(right, fit_rows, seed).select("id", "embedding")
    fitted = KMeans(k=cells, seed=seed, featuresCol="v", maxIter=10).fit(sample.select(array_to_vector(F.col("embedding").cast("array<double>")).alias("v")))
    centers = np.array(fitted.clusterCenters())
    probe, held = some_rows(left, probe_rows, seed + 1).select("id", "embedding").toPandas(), sample.toPandas()
    if not len(probe) or not len(held):
        return centers, len(centers), [1.0] * len(centers)
    x, y = numbers(probe["embedding"]), numbers(held["embedding"])
    r, c = np.nonzero((x @ y.T >= threshold) & (probe["id"].to_numpy()[:, None] != held["id"].to_numpy()[None, :]))
    cell = nearest_cells(centers, np.array(held["embedding"].tolist(), float))[:, 0]
    near = nearest_cells(centers, np.array(probe["embedding"].tolist(), float))
    place = (near[r] == cell[c][:, None]).argmax(axis=1)
    reached = [float((place <= p).mean()) if len(place) else 1.0 for p in range(len(centers))]
    return centers, next((p + 1 for p, v in enumerate(reached) if v >= recall), len(centers)), reached


def cells_probed(threshold: float, centers: np.ndarray, probes: int) -> Strategy:
    """Rows of which the right one lies in one of the left one's nearest cells, verified: a product for each cell."""

    def prepare(rows: np.ndarray, unit: np.ndarray) -> tuple:
        cell = nearest_cells(centers, rows)[:, 0]
        return unit, [np.nonzero(cell == c)[0] for c in range(len(centers))]

    def find(rows: np.ndarray, same: np.ndarray, kept: tuple) -> Hits:
        unit, members = kept
        x, near = unit_rows(rows), np.zeros((len(rows), len(centers)), bool)
        np.put_along_axis(near, nearest_cells(centers, rows)[:, :probes], True, axis=1)
        hits = []
        for c, cols in enumerate(members):
            own = np.nonzero(near[:, c])[0]
            if len(own) and len(cols):
                sims = cosines(x[own], unit[cols])
                i, j = np.nonzero((sims >= threshold) & ~same[np.ix_(own, cols)])
                hits.append((own[i], cols[j], sims[i, j]))
        return tuple(np.concatenate(x) for x in zip(*hits)) if hits else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))

    return Strategy(prepare, find, 8)


def cell_strategy(left: DataFrame, right: DataFrame, threshold: float, cells: int | None = None, probes: int | None = None) -> Strategy:
    centers, enough, _ = cell_model(left, right, threshold, cells)
    return cells_probed(threshold, centers, probes or enough)


def cell_pairs(left: DataFrame, right: DataFrame, threshold: float, cells: int | None = None, probes: int | None = None) -> DataFrame:
    """Pairs whose right side lies in one of the left side's nearest cells, verified where they meet."""
    return blocked(left, right, [cell_strategy(left, right, threshold, cells, probes)])


def strategies_quality(left: DataFrame, right: DataFrame, threshold: float, strategies: dict[str, Strategy], block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """(n_exact, n_found, recall, precision, strategy) of each strategy against all pairs at the threshold.

    Both are counted where a slice meets a block, so a pair is never shuffled to be compared; ids are those of one row a side.
    """
    names = list(strategies)

    def counts(own: np.ndarray, ids: np.ndarray, hits: list[Hits]) -> pd.DataFrame:
        codes = [r.astype(np.int64) * max(1, len(ids)) + c for r, c, _ in hits]
        return pd.DataFrame({"strategy": names, "n_exact": len(codes[0]), "n_found": [len(c) for c in codes[1:]], "hits": [int(np.isin(c, codes[0]).sum()) for c in codes[1:]]})

    each = blocked(left, right, [every_pair(threshold), *strategies.values()], "strategy string, n_exact long, n_found long, hits long", counts, block_bytes)
    total = each.groupBy("strategy").agg(*[F.sum(c).alias(c) for c in ("n_exact", "n_found", "hits")])
    share = lambda n: F.round(F.try_divide("hits", n), 6)
    return total.select("n_exact", "n_found", share("n_exact").alias("recall"), share("n_found").alias("precision"), "strategy")


def minhash_signature(sh: Column, hashes: int) -> Column:
    """One least hash for each seed."""
    return let(sh, lambda x: F.transform(F.sequence(F.lit(1), F.lit(hashes)), lambda i: F.array_min(F.transform(x, lambda s: F.xxhash64(i, s)))))


def minhash_pairs(df: DataFrame, id_col: str, text: str, least: float, bands: int = 20, rows: int = 3, n: int = 5) -> DataFrame:
    """(a, b, jaccard) of class representatives by their n-word shingles.

    Equal sets collapse first, so copies are never paired.  Bands propose, sizes and then signatures sort out (a pair whose agreeing
    share of the signature is far below the threshold is no candidate), and sets of what is left verify; sets are never shuffled
    for other texts.
    """
    sets = df.select(F.col(id_col).alias("id"), hashed_shingles(F.col(text), n).alias("sh")).filter(F.size("sh") > 0).withColumn("set_key", F.sha1(F.to_json(F.array_sort("sh")).cast("binary")))
    reps = cut(sets.groupBy("set_key").agg(F.min("id").alias("id"), F.first("sh").alias("sh")).select("id", "sh", F.size("sh").alias("n"), minhash_signature(F.col("sh"), bands * rows).alias("sig")), "sets")
    band_keys = let(F.col("sig"), lambda sig: F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda b: F.xxhash64(b, F.slice(sig, b * rows + 1, rows))))
    keys = reps.select("id", "n", F.explode(band_keys).alias("k"))
    pairs = keys.select(F.col("id").alias("a"), F.col("n").alias("na"), "k").join(keys.select(F.col("id").alias("b"), F.col("n").alias("nb"), "k"), "k").filter("a < b").filter(F.least("na", "nb") >= least * F.greatest("na", "nb"))
    pairs = pairs.select("a", "b").distinct()
    side = lambda x, *cols: reps.select(F.col("id").alias(x), *[F.col(c).alias(f"{c}_{x}") for c in cols])
    same = F.size(F.filter(F.zip_with("sig_a", "sig_b", lambda x, y: x == y), lambda e: e)) / (bands * rows)
    close = pairs.join(side("a", "sig"), "a").join(side("b", "sig"), "b").filter(same >= least - 0.35).select("a", "b")
    both = close.join(side("a", "sh"), "a").join(side("b", "sh"), "b")
    common = F.size(F.array_intersect("sh_a", "sh_b"))
    return both.select("a", "b", F.round(common / (F.size("sh_a") + F.size("sh_b") - common), 6).alias("jaccard")).filter(F.col("jaccard") >= least)


def recall_at(found: DataFrame, exact: DataFrame) -> DataFrame:
    """(n_exact, n_found, recall, precision) of found pairs against exact ones."""
    e, f = exact.select("id", "other").distinct(), found.select("id", "other").distinct()
    hit = f.join(e, ["id", "other"], "left_semi").agg(F.count("*").alias("hits"))
    return e.agg(F.count("*").alias("n_exact")).crossJoin(f.agg(F.count("*").alias("n_found"))).crossJoin(hit).select("n_exact", "n_found", F.round(F.col("hits") / F.col("n_exact"), 6).alias("recall"), F.round(F.col("hits") / F.col("n_found"), 6).alias("precision"))


__all__ = ["band_shape", "blocked_pairs", "callable_encoder", "cell_model", "cell_pairs", "cell_strategy", "exact_blocked", "exact_pairs", "hashed_ngrams", "hyperplane_pairs", "hyperplane_strategy", "minhash_pairs", "prefix_pairs", "recall_at", "strategies_quality", "term_counts"]
