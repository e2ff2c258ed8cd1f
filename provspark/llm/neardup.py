"""Operator 1, near duplicates: HyperMinHash candidates, exact verification, components.

1. Each text becomes its set of five-word shingles, a digest of that set, 16-bit HyperMinHash registers and 32 band
   keys of four registers each.  Equal sets collapse to their least id before anything is paired.
2. In each bucket of a band, members are paired with one leader, which differs from band to band.
   Pairs whose collision-corrected estimate reaches FAMILY join one family.  Texts similar enough to be linked
   share about ten buckets, and fall apart only if the leaders of all of them are far from both.
3. The texts of a small family meet in a task, each once.  Counting through posting lists gives exact intersections; texts that
   are linked with the first one need no further look, as what is linked with them finds them.  What is emitted is a spanning
   forest of the links, so rows never exceed members.
4. A large family is never in one task.  Each of its texts is compared with the family's hub (the member met most often) where
   it lies; those that are not linked with it, few in a group of copies, are then compared with all, a block of either at a time.

No candidate is capped.  Only tables of checked size are broadcast; larger ones are shuffled.

Defined cases: null and empty texts have empty sets and link with nothing; rows with a null id
keep a null component and are not kept; a repeated id links through each of its texts and gives
as many rows; an empty table gives an empty result; other columns are not read; of equal texts and of ties
the least id stands for all.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provspark.llm import shingles as S
from provspark.llm.common import Scratch, if_small, map_arrow, ragged_take, read_table, slices
from provspark.llm.components import connected_components
from provspark.llm.tokens import filled

THRESHOLD_PERCENT = 75
BANDS = 32
ROWS = S.BUCKETS // BANDS
#: Least estimated similarity of a member and a leader of one family.
FAMILY = 0.35
#: Shingles and texts of a family that meet in one task; families with more of either are large, and have blocks of that size.
BLOCK_SHINGLES, BLOCK_TEXTS = 200_000, 400
#: Bytes of hubs' texts that may be sent to all workers; beyond, every text of a large family is compared with all.
HUB_BYTES = 32 << 20


def band_keys(registers: np.ndarray, kind: int) -> np.ndarray:
    """One 64-bit key a band that has a filled register."""
    parts = registers.reshape(BANDS, ROWS)
    words = parts.astype("<u2").tobytes()
    step = 2 * ROWS
    return np.array([xxhash.xxh3_64_intdigest(words[i * step : (i + 1) * step], seed=2 * i + kind) for i in range(BANDS) if parts[i].any()], np.uint64)


def described(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = S.WIDTH) -> DataFrame:
    """Rows (id, n, digest, few, many, bands): set size, digest of the set, registers by function and by bucket."""
    kind = docs.schema[id_col].dataType.simpleString()

    def per_slice(batch):
        sets = S.shingle_sets(filled(batch.column("text")), width)
        n, digest, few, many, bands = [], [], [], [], []
        for h in sets:
            f, m = S.sketches(h)
            n.append(len(h))
            digest.append(xxhash.xxh3_128_digest(h.tobytes()) if len(h) else None)
            few.append(None if f is None else f.tobytes())
            many.append(None if m is None else m.tobytes())
            keys = [band_keys(r, k) for k, r in enumerate((f, m)) if r is not None]
            bands.append(np.concatenate(keys).view(np.int64) if keys else np.zeros(0, np.int64))
        return pa.RecordBatch.from_arrays(
            [batch.column("id"), pa.array(n, pa.int64()), pa.array(digest, pa.binary()), pa.array(few, pa.binary()), pa.array(many, pa.binary()), pa.array(bands, pa.list_(pa.int64()))],
            names=["id", "n", "digest", "few", "many", "bands"],
        )

    return map_arrow(docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), f"id {kind}, n long, digest binary, few binary, many binary, bands array<long>", "text", per_slice)


def close_sizes(n: F.Column, m: F.Column, percent: int) -> F.Column:
    return F.least(n, m) * 100 >= F.greatest(n, m) * percent


def as_registers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(rows that have registers, registers of all rows with zeros elsewhere)."""
    have = ~np.array(column.is_null())
    out = np.zeros((len(have), S.BUCKETS), np.uint16)
    if have.any():
        out[have] = np.frombuffer(b"".join(x for x in column.to_pylist() if x is not None), np.uint16).reshape(-1, S.BUCKETS)
    return have, out


def estimated(pairs: DataFrame, sets: DataFrame, least: float) -> DataFrame:
    """Pairs (a, b) whose registers give an estimate of at least ``least``."""
    kind = pairs.schema["a"].dataType.simpleString()
    side = lambda x: sets.select(F.col("id").alias(x), F.col("n").alias(f"n_{x}"), F.col("few").alias(f"few_{x}"), F.col("many").alias(f"many_{x}"))
    rows = pairs.join(side("a"), "a").join(side("b"), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, m = (batch.column(k).to_numpy().astype(float) for k in ("n_a", "n_b"))
            ok = np.zeros(batch.num_rows, bool)
            for name, share in (("few", 1), ("many", S.BUCKETS)):
                (ha, a), (hb, b) = (as_registers(batch.column(f"{name}_{x}")) for x in "ab")
                both = ha & hb
                if both.any():
                    ok[both] |= S.estimated_jaccard(a[both], b[both], n[both] / share, m[both] / share)[0] >= least
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], names=["a", "b"]).filter(pa.array(ok))

    return rows.mapInArrow(run, f"a {kind}, b {kind}").distinct()


def forest(sets: list[np.ndarray], ids: list, percent: int, probe: np.ndarray | None = None) -> list[tuple]:
    """Links (greater id, lesser id) that span the components of a group's exact similarity graph.

    With ``probe`` only links between the marked sets and the others are looked for.  Without, sets that are by then in the first one's component are
    passed over: a set that is linked with one of them and is not in it finds that link itself.
    """
    m = len(sets)
    sizes = np.array([len(x) for x in sets], np.int64)
    owner = np.repeat(np.arange(m), sizes)
    values, inverse = np.unique(np.concatenate(sets), return_inverse=True)
    listed = np.ones(len(owner), bool) if probe is None else ~probe[owner]
    order = np.argsort(inverse[listed], kind="stable")
    posting, bounds = owner[listed][order], np.concatenate([[0], np.cumsum(np.bincount(inverse[listed], minlength=len(values)))])
    at = np.concatenate([[0], np.cumsum(sizes)])
    root = list(range(m))
    out = []

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for i in range(m) if probe is None else np.flatnonzero(probe).tolist():
        if probe is None and i and find(i) == find(0):
            continue
        mine = inverse[at[i] : at[i + 1]]
        both = np.bincount(ragged_take(posting, bounds[mine], bounds[mine + 1] - bounds[mine]), minlength=m)
        for j in np.flatnonzero((both > 0) & (100 * both >= percent * (sizes + sizes[i] - both))).tolist():
            a, b = find(i), find(j)
            if a != b:
                root[max(a, b)] = min(a, b)
                if ids[i] != ids[j]:
                    out.append((max(ids[i], ids[j]), min(ids[i], ids[j])))
    return out


def links_in_groups(rows: DataFrame, percent: int, width: int, probing: bool = False) -> DataFrame:
    """rows: (family, block, probe, id, text).  Pairs (a, b) that span the linked texts of each group; with ``probing`` only links
    between a group's probes and its other texts."""
    kind = rows.schema["id"].dataType.simpleString()
    dealt = rows.repartition("family", "block").sortWithinPartitions("family", "block").select("family", "block", "probe", "id", "text")

    def links_of(group: list[pa.RecordBatch]) -> pa.RecordBatch:
        ids = [x for g in group for x in g.column("id").to_pylist()]
        sets = [h for g in group for part in slices(g, "text") for h in S.shingle_sets(filled(part.column("text")), width)]
        probe = np.concatenate([g.column("probe").to_numpy(zero_copy_only=False) for g in group]).astype(bool)
        some = len(ids) > 1 and (probe.any() and not probe.all() or not probing)
        pairs = forest(sets, ids, percent, probe if probing else None) if some else []
        kept = group[0].schema.field("id").type
        return pa.RecordBatch.from_arrays([pa.array([p[0] for p in pairs], kept), pa.array([p[1] for p in pairs], kept)], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        mark = None
        for batch in batches:
            cols = [batch.column(k).to_numpy() for k in ("family", "block")]
            cuts = np.flatnonzero(np.any([c[1:] != c[:-1] for c in cols], axis=0)) + 1
            for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), batch.num_rows]):
                if a == b:
                    continue
                now = tuple(c[a] for c in cols)
                if held and now != mark:
                    yield links_of(held)
                    held = []
                held.append(batch.slice(a, b - a))
                mark = now
        if held:
            yield links_of(held)

    return dealt.mapInArrow(run, f"a {kind}, b {kind}").distinct()


def compared_with_hubs(rows: DataFrame, hubs: list, percent: int, width: int) -> DataFrame:
    """rows: (family, id, part, text).  Rows (family, id, part, hub, linked): whether each text is linked with its family's hub."""
    kind = rows.schema["id"].dataType.simpleString()
    shared = rows.sparkSession.sparkContext.broadcast({h["family"]: (h["hub"], h["text"]) for h in hubs})

    def per_slice(batch):
        held: dict = {}
        names, linked = [], []
        for family, h in zip(batch.column("family").to_pylist(), S.shingle_sets(filled(batch.column("text")), width)):
            hub, text = shared.value[family]
            if family not in held:
                held[family] = S.shingle_sets(pa.array([text], pa.string()), width)[0]
            both = len(np.intersect1d(h, held[family], assume_unique=True))
            names.append(hub)
            linked.append(bool(both and 100 * both >= percent * (len(h) + len(held[family]) - both)))
        return pa.RecordBatch.from_arrays([batch.column("family"), batch.column("id"), batch.column("part"), pa.array(names, batch.schema.field("id").type), pa.array(linked)], names=["family", "id", "part", "hub", "linked"])

    return map_arrow(rows.select("family", "id", "part", "text"), f"family {kind}, id {kind}, part long, hub {kind}, linked boolean", "text", per_slice)


def links_in_families(rows: DataFrame, hubs: DataFrame, percent: int, width: int, tmp: Scratch) -> DataFrame:
    """rows: (family, blocks, id, text); hubs: (family, hub) of families with more than one block.  Pairs that span the linked texts."""
    small = rows.filter("blocks = 1").select("family", F.lit(0).alias("block"), F.lit(False).alias("probe"), "id", "text")
    links = links_in_groups(small, percent, width)
    if not hubs.limit(1).count():
        return links
    large = tmp.write(rows.filter("blocks > 1").withColumn("part", F.xxhash64("id", "text")), "large", compression="zstd")
    texts = tmp.write(large.join(hubs, "family").filter(F.col("id") == F.col("hub")).groupBy("family", "hub").agg(F.min("text").alias("text")), "hubs")
    place = F.pmod("part", F.col("blocks")).cast("int").alias("block")
    if texts.agg(F.sum(F.octet_length("text"))).first()[0] <= HUB_BYTES:
        looked = tmp.write(compared_with_hubs(large, texts.collect(), percent, width), "looked")
        links = links.unionByName(looked.filter("linked AND id <> hub").select(F.greatest("id", "hub").alias("a"), F.least("id", "hub").alias("b")).distinct())
        left = looked.filter("NOT linked").select("family", "id", "part").distinct()
    else:
        left = large.select("family", "id", "part").distinct()
    left = tmp.write(left, "left")
    # A group is one block of a family's texts and one part of those left, which are no more than a block has.
    whole = large.groupBy("family").agg(F.max("blocks").alias("blocks"), F.count("*").alias("rows"))
    parts = whole.join(left.groupBy("family").agg(F.count("*").alias("left")), "family").select("family", F.greatest(F.ceil(F.col("blocks") * F.col("left") / F.col("rows")), F.lit(1)).cast("int").alias("parts"))
    parts = tmp.write(parts, "parts")
    dealt = large.join(parts, "family")
    members = dealt.withColumn("p", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).select("family", (place * F.col("parts") + F.col("p")).alias("block"), F.lit(False).alias("probe"), "id", "text")
    mine = F.pmod(F.xxhash64("part"), F.col("parts")).cast("int")
    probes = dealt.join(left, ["family", "id", "part"], "left_semi").withColumn("b", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select("family", (F.col("b") * F.col("parts") + mine).alias("block"), F.lit(True).alias("probe"), "id", "text")
    return links.unionByName(links_in_groups(members.unionByName(probes), percent, width, probing=True)).distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = THRESHOLD_PERCENT, width: int = S.WIDTH, block_shingles: int = BLOCK_SHINGLES, block_texts: int = BLOCK_TEXTS) -> DataFrame:
    """Rows (id, n_shingles, component_id, kept), one for each row of docs.  Ids are integers."""
    tmp = Scratch()
    base = tmp.write(described(docs, id_col, text_col, width), "sets")
    whole = base.filter("n > 0 AND id IS NOT NULL")
    classes = tmp.write(whole.groupBy("digest").agg(F.min("id").alias("rep"), F.count("*").alias("rows")), "classes")
    copied = classes.filter("rows > 1").select("digest", "rep")
    copied = if_small(copied, copied.count())
    # Copies go; what stays is a row for each distinct set.
    sets = whole.join(copied, "digest", "left").filter("rep IS NULL OR rep = id").select("id", "n", "few", "many", "bands")
    bands = sets.select("id", "n", F.explode("bands").alias("key"))
    leader = tmp.write(bands.groupBy("key").agg(F.min(F.struct(F.xxhash64("key", "id").alias("h"), F.col("id").alias("leader"), F.col("n").alias("m"))).alias("x"), F.count("*").alias("size")).filter("size > 1").select("key", "x.leader", "x.m"), "leaders")
    star = bands.join(if_small(leader, leader.count()), "key").filter((F.col("id") != F.col("leader")) & close_sizes(F.col("n"), F.col("m"), FAMILY * 100))
    star = tmp.write(star.select(F.greatest("id", "leader").alias("a"), F.least("id", "leader").alias("b")).distinct(), "star")
    met = tmp.write(star.select(F.explode(F.array("a", "b")).alias("id")).distinct(), "met")
    known = tmp.write(sets.join(if_small(met, met.count()), "id", "left_semi").select("id", "n", "few", "many"), "registers")
    close = tmp.write(estimated(star, known, FAMILY), "close")
    family = connected_components(close, tmp)
    family = family.unionByName(family.select(F.col("component").alias("id"), "component").distinct()).withColumnRenamed("component", "family")
    sizes = family.join(known.groupBy("id").agg(F.max("n").alias("n")), "id")
    blocks = sizes.groupBy("family").agg(F.greatest(F.ceil(F.sum("n") / block_shingles), F.ceil(F.count("*") / block_texts)).cast("int").alias("blocks"))
    family = tmp.write(family.join(blocks, "family"), "families")
    met_by = close.select(F.explode(F.array("a", "b")).alias("id")).groupBy("id").agg(F.count("*").alias("met"))
    hubs = tmp.write(family.filter("blocks > 1").join(met_by, "id").groupBy("family").agg(F.max(F.struct("met", (-F.col("id")).alias("i"), "id")).alias("x")).select("family", F.col("x.id").alias("hub")), "hub_ids")
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).filter("id IS NOT NULL")
    rows = texts.join(if_small(family, family.count()), "id").select("family", "blocks", "id", "text")
    final = connected_components(links_in_families(rows, hubs, percent, width, tmp), tmp)
    of_class = classes.join(final, F.col("rep") == F.col("id"), "left").select("digest", F.coalesce("component", "rep").alias("component_id"))
    out = base.select("id", "n", "digest").join(of_class, "digest", "left").withColumn("component_id", F.coalesce("component_id", "id"))
    return tmp.result(out.select("id", F.col("n").alias("n_shingles"), "component_id", F.coalesce(F.col("id") == F.col("component_id"), F.lit(False)).alias("kept")), "groups")


def op1_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(read_table(spark, sf_dir, "documents")).withColumnRenamed("id", "doc_id")


OP1_SQL = """
WITH RECURSIVE w AS (
  SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS ws FROM documents
), s AS (
  SELECT doc_id, CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
    ELSE list_distinct(list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i+4], ' '))) END AS sh FROM w
), c AS (SELECT doc_id, len(sh) AS n FROM s
), e AS (SELECT doc_id, unnest(sh) AS g FROM s
), p AS (
  SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS i FROM e a JOIN e b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2
), l AS (
  SELECT x, y FROM p JOIN c a ON a.doc_id = x JOIN c b ON b.doc_id = y WHERE 100 * i >= 75 * (a.n + b.n - i)
), both_ways AS (SELECT x, y FROM l UNION ALL SELECT y, x FROM l
), r AS (
  SELECT doc_id AS x, doc_id AS y FROM documents UNION SELECT r.x, b.y FROM r JOIN both_ways b ON r.y = b.x
), m AS (SELECT x, min(y) AS component_id FROM r GROUP BY x)
SELECT c.doc_id, CAST(c.n AS BIGINT) AS n_shingles, m.component_id, c.doc_id = m.component_id AS kept
FROM c JOIN m ON m.x = c.doc_id
"""
