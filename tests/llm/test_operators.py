import hashlib
import io
import math
import random
import re
import wave
import zlib

import numpy as np
import public_tokenizers as P
import pyarrow as pa
import pytest
from hypothesis import example, given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from provspark.llm import chunks, decontaminate, htmltext, langid, media, mixing, neardup, shingles, tokens, warc

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"
random.seed(5)
VOCAB = [f"w{i}" for i in range(400)]


def words(n, seed):
    r = random.Random(seed)
    return " ".join(r.choice(VOCAB) for _ in range(n))


LONG = words(3000, 1)
ODD = [None, "", " \n\t ", "one two", "ONE two", "a b c d e", "a b c d e", LONG, LONG + " end", words(60, 2), "é ñ 中文 ß x", "12345 !!! ???"]


def docs(spark, texts, extra=False):
    rows = [(i, t, "en" if i % 2 else None, f"s{i % 3}" if i % 4 else None, None) for i, t in enumerate(texts)]
    rows.append((None, "row without id", None, None, None))
    df = spark.createDataFrame(rows, DOCS)
    if extra:
        for c in ("id", "key", "n", "component", "size", "host", "tokens", "media", "digest", "row"):
            df = df.withColumn(c, F.lit("clash"))
    return df


def shingle_set(text):
    w = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    for c in "\t\n\x0b\x0c\r":
        w = w.replace(c, " ")
    w = [x for x in w.split(" ") if x]
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())


def brute_components(texts):
    sets = [shingle_set(t) for t in texts]
    root = list(range(len(texts)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(texts)):
        for j in range(i):
            a, b = sets[i], sets[j]
            if a and b and 100 * len(a & b) >= 75 * len(a | b):
                x, y = find(i), find(j)
                root[max(x, y)] = min(x, y)
    return [find(i) for i in range(len(texts))], [len(s) for s in sets]


def family(n, length, edits, seed):
    r = random.Random(seed)
    base = words(length, seed).split()
    out = []
    for _ in range(n):
        w = list(base)
        for _ in range(r.randint(0, edits)):
            w[r.randrange(len(w))] = r.choice(VOCAB)
        out.append(" ".join(w))
    return out


def test_near_duplicates_against_brute_force(spark, monkeypatch):
    texts = ODD + family(40, 120, 6, 11) + family(25, 700, 20, 12) + family(20, 8, 1, 13) + [words(150, 100 + i) for i in range(20)]
    want, sizes = brute_components(texts)
    for block, hubs in ((neardup.BLOCK_SHINGLES, neardup.HUB_BYTES), (900, neardup.HUB_BYTES), (900, 0)):  # large families with and without hubs
        monkeypatch.setattr(neardup, "HUB_BYTES", hubs)
        got = {r["id"]: r for r in neardup.near_duplicates(docs(spark, texts, extra=True), block_shingles=block).collect()}
        assert [got[i]["component_id"] for i in range(len(texts))] == want
        assert [got[i]["n_shingles"] for i in range(len(texts))] == sizes
        assert all(got[i]["kept"] == (want[i] == i) for i in range(len(texts)))
        assert got[None]["component_id"] is None and got[None]["kept"] is False
    empty = neardup.near_duplicates(docs(spark, texts).limit(0))
    assert empty.count() == 0


def test_sketch_estimates(spark):
    r = np.random.default_rng(3)
    for n in (100, 2000):
        base = np.unique(r.integers(0, 2**64, 3 * n, dtype=np.uint64))
        a, b = np.sort(base[: 2 * n]), np.sort(base[n : 3 * n])
        kind, per = (1, shingles.BUCKETS) if 2 * n >= shingles.FEW else (0, 1)
        x, y = shingles.sketches(a)[kind], shingles.sketches(b)[kind]
        j, filled = shingles.estimated_jaccard(x[None], y[None], np.array([len(a) / per]), np.array([len(b) / per]))
        assert abs(j[0] - len(np.intersect1d(a, b)) / len(np.union1d(a, b))) < 0.2 and filled[0] > 100
    assert 0 < shingles.chance_matches(np.array([1000.0]), np.array([1000.0]))[0] < 2**-9


LIB = Tokenizer.from_file(P.path("word_bpe_49k.json"))


SIGNS = list("abC D'é\n\t.,!|<>12ß中\u0301\x1c 🙂\u180e\u0307İK\u0e34กſ≮\u0338\u3000\x85")


@settings(max_examples=150, deadline=None, derandomize=True)
@example(["><\x1c1"])
@example(["<<|endoftext|>a<|startoftext|>!'s"])
@given(st.lists(st.text(alphabet=st.sampled_from(SIGNS), max_size=30), min_size=1, max_size=3))
def test_ids_and_all_prefix_counts_are_the_librarys(texts):
    column = pa.array(texts, pa.string())
    ids, counts = tokens.encoder(tokens.vocabulary_path()).encode(column)
    want = [LIB.encode(t, add_special_tokens=False).ids for t in texts]
    assert counts.tolist() == [len(w) for w in want] and ids.tolist() == [i for w in want for i in w]
    bounds, changes = tokens.prefix_counter(tokens.vocabulary_path()).prefix_changes(column)
    for k, t in enumerate(texts):
        stored = changes[bounds[k] : bounds[k + 1]].tobytes()
        exact = [len(LIB.encode(t[:at], add_special_tokens=False).ids) for at in range(len(t) + 1)]
        assert tokens.prefix_counts(stored).tolist() == exact == [tokens.tokens_at(at, stored) for at in range(len(t) + 1)]
        for budget in (0, 1, 3):
            assert tokens.longest_prefix(budget, stored) == max(at for at, n in enumerate(exact) if n <= budget)


@settings(max_examples=25, deadline=None, derandomize=True)
@given(st.lists(st.sampled_from(["internationalization", "thing", "nes", "ß", "中文", "é", "e\u0301", "!!", "'s", "'", "...", "<|endoftext|>", "7", "กิ", "\x1c", "Straße", "x\u0307\u0301"]), min_size=12, max_size=40))
def test_prefix_counts_of_long_words(parts):
    word = "".join(parts)
    bounds, changes = tokens.prefix_counter(tokens.vocabulary_path()).prefix_changes(pa.array([word], pa.string()))
    assert tokens.prefix_counts(changes.tobytes()).tolist() == [len(LIB.encode(word[:at], add_special_tokens=False).ids) for at in range(len(word) + 1)]


def test_prefix_counts_of_long_runs():
    r = random.Random(8)
    for alphabet in ("etaoinsrhl", "aé中ß", "=-!.", "a", "—…!"):
        run = "".join(r.choice(alphabet) for _ in range(150))
        counter = tokens.prefix_counter(tokens.vocabulary_path())
        want = [len(LIB.encode(run[:at], add_special_tokens=False).ids) for at in range(1, 151)]
        assert counter.pieces(run).tolist() == want
        if len(set(alphabet) & set("=-!.—…a")) == len(alphabet) or alphabet.isalpha():
            assert counter.last_tokens(list(run)) == want


def test_white_space_is_the_librarys():
    points = [c for c in range(1, 0x3100) if not 0xD800 <= c < 0xE000]
    column = pa.array([f"ab{chr(c)}cd" for c in points], pa.string())
    ids, counts = tokens.encoder(tokens.vocabulary_path()).encode(column)
    assert ids.tolist() == [i for t in column.to_pylist() for i in LIB.encode(t, add_special_tokens=False).ids]
    _, changes = tokens.prefix_counter(tokens.vocabulary_path()).prefix_changes(column)
    assert np.add.reduceat(changes.astype(int), np.arange(0, 5 * len(points), 5)).tolist() == counts.tolist()


def test_special_strings_and_truncation(spark):
    enc = tokens.encoder(tokens.vocabulary_path())
    t = "ab<|endoftext|>cd It's we'll x<|startoftext|>"
    assert enc.encode(pa.array([t]))[0].tolist() == LIB.encode(t, add_special_tokens=False).ids
    for r in tokens.truncate_to_budget(docs(spark, ODD), 5).collect():
        assert r["n_tokens"] == len(LIB.encode(r["text"], add_special_tokens=False).ids) <= 5


def test_stored_counts(spark):
    got = {r["id"]: r for r in tokens.stored_counts(tokens.prefix_table(docs(spark, ODD, extra=True))).collect()}
    for i, t in enumerate(ODD):
        assert got[i]["n_tokens"] == len(LIB.encode(t or "", add_special_tokens=False).ids) and got[i]["n_bytes"] == len((t or "").encode())
    assert tokens.stored_counts(tokens.prefix_table(docs(spark, ODD).limit(0))).count() == 0


@pytest.mark.parametrize("encoding", ["dictionary", "delta"])
def test_token_files_round_trip(spark, encoding, tmp_path):
    path = f"file://{tmp_path}/t"
    tokens.write_tokens(docs(spark, ODD, extra=True), path, encoding=encoding)
    rows = tokens.read_tokens(spark, path).orderBy("start").collect()
    order = [None, *range(len(ODD))]
    assert [r["id"] for r in rows] == order
    at = 0
    for r in rows:
        want = LIB.encode("row without id" if r["id"] is None else ODD[r["id"]] or "", add_special_tokens=False).ids + [tokens.END_ID]
        assert (r["start"], r["n_tokens"], list(r["tokens"])) == (at, len(want), want)
        at += len(want)
    d = tokens.token_digests(tokens.read_tokens(spark, path)).filter("doc_id = 3").first()
    ids = LIB.encode("one two", add_special_tokens=False).ids + [1]
    assert d["ids_crc32"] == zlib.crc32(np.array(ids, "<u4").tobytes())
    assert tokens.tokens_of(docs(spark, ODD).limit(0)).count() == 0


def test_mixing_reaches_targets(spark):
    rows = [(i, words(random.Random(i).randint(1, 60), i), None, [None, "b", "a", "a", "a", "c"][i % 6], None) for i in range(600)] + [(1000, None, None, "a", None), (1001, "", None, "d", None)]
    df = spark.createDataFrame(rows, DOCS)
    got = mixing.mix_by_source(df).collect()
    assert sorted(r["doc_id"] for r in got) == sorted(r[0] for r in rows)
    src = {r[0]: r[3] for r in rows}
    size, taken, target = {}, {}, {}
    for r in got:
        s = src[r["doc_id"]]
        assert r["size"] == len((rows[r["doc_id"]][1] if r["doc_id"] < 1000 else "" or "").split())
        assert r["taken"] <= 3 * r["size"] and (r["size"] == 0 or r["taken"] % r["size"] == 0)
        size[s], taken[s], target[s] = size.get(s, 0) + r["size"], taken.get(s, 0) + r["taken"], r["target"]
    assert target == pytest.approx({k: float(v) for k, v in mixing.targets_of(size, mixing.weights_of(list(size)), sum(size.values())).items()})
    for s in size:
        assert abs(taken[s] - target[s]) <= 15 and target[s] <= 3 * size[s]
    assert sorted(map(tuple, got)) == sorted(map(tuple, mixing.mix_by_source(df.repartition(5)).collect()))
    assert mixing.mix_by_source(df.limit(0)).count() == 0


def test_rows_without_ids_and_a_source_named_like_none(spark):
    rows = [(None, "a b c", None, None, None)] * 400 + [(None, "a b c", None, "-", None)] * 90 + [(None, "x y", None, "\0null", None)] * 100
    got = mixing.mix_by_source(spark.createDataFrame(rows, DOCS)).collect()
    assert len(got) == 590 and len({r["target"] for r in got}) == 3
    for size, n in ((1200, 400), (270, 90), (200, 100)):
        mine = [r for r in got if r["source_size"] == size]
        assert len(mine) == n and abs(sum(r["taken"] for r in mine) - mine[0]["target"]) <= 3


def test_flow_cost_against_all_flows():
    sizes, quotas = {("a",): 2, ("b",): 1, ("a", "b"): 2}, {"a": 5, "b": 4}
    cost = lambda used, n: sum(min(n, max(0, used - k * n)) * c for k, c in enumerate(mixing.USE_COSTS))
    best = min(cost(x, 2) + cost(y, 1) + cost(9 - x - y, 2) for x in range(6) for y in range(4) if 0 <= 5 - x <= 9 - x - y <= 6 and 9 - x - y == (5 - x) + (4 - y) and y <= 4)
    out = mixing.route(sizes, quotas)
    assert sum(cost(sum(out[p].values()), n) for p, n in sizes.items()) == best
    assert mixing.route({("a",): 3, ("b",): 4}, {"a": 5, "b": 20}) == {("a",): {"a": 5}, ("b",): {"b": 12}}


def test_flow_spreads_repetition_over_overlapping_sources():
    out = mixing.route({("a",): 10, ("b",): 5, ("a", "b"): 20}, {"a": 30, "b": 25})
    assert sum(out[p].get("a", 0) for p in out) == 30 and sum(out[p].get("b", 0) for p in out) == 25
    assert all(sum(v.values()) <= 2 * n for (p, n), v in zip({("a",): 10, ("b",): 5, ("a", "b"): 20}.items(), out.values()))  # nothing is used three times


def test_targets_stop_at_three_times_the_size():
    got = mixing.targets_of({"x": 1, "y": 100, "z": 100}, {"x": 5, "y": 2, "z": 1}, 201)
    assert got["x"] == 3 and got["y"] == 132 and got["z"] == 66


def test_language_is_identified_on_held_out_text(spark):
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    found = langid.identify(df, langid.fit_on_documents(df)).withColumnRenamed("id", "doc_id").join(df.select("doc_id", "lang"), "doc_id").filter(langid.remainder() == 1)
    n, ok = found.agg(F.count("*"), F.count_if(F.col("lang") == F.col("lang_pred"))).first()
    assert n > 200 and ok / n > 0.97
    odd = {r["id"]: r for r in langid.identify(docs(spark, ODD, extra=True), langid.fit_on_documents(df)).collect()}
    assert odd[0]["lang_pred"] == odd[1]["lang_pred"] == odd[11]["lang_pred"] == "und" and odd[3]["lang_pred"] != "und"
    assert all(0 <= r["score"] <= 1 for r in odd.values())
    nothing = langid.identify(docs(spark, ODD), langid.fit_on_documents(df.limit(0)))
    assert {r["lang_pred"] for r in nothing.collect()} == {"und"}
    model = langid.fit_on_documents(df)
    assert langid.identify(df.limit(0), model).count() == 0 and langid.with_language(df.limit(0), model).count() == 0


def test_language_scores_against_brute_force(spark):
    rows = [(i, t, lang, None, None) for i, (t, lang) in enumerate([("aa ab ab", "x"), ("ab ba bb", "y"), ("ba ba", "y")])]
    model = langid.fit(spark.createDataFrame(rows, DOCS), fit_texts=10)
    counts = {"x": {"aa": 1, "ab": 2}, "y": {"ab": 1, "ba": 3, "bb": 1}}
    kinds = {w for c in counts.values() for w in c}
    logs = {k: {w: math.log((c.get(w, 0) + 0.5) / (sum(c.values()) + 0.5 * len(kinds))) for w in kinds} for k, c in counts.items()}
    pairs = {k: {} for k in counts}
    for k, c in counts.items():
        for w, n in c.items():
            for i in range(len(w) + 1):
                pairs[k][f" {w} "[i : i + 2]] = pairs[k].get(f" {w} "[i : i + 2], 0) + n
    two = set(pairs["x"]) | set(pairs["y"])
    of = {k: {g: math.log((c.get(g, 0) + 0.5) / (sum(c.values()) + 0.5 * len(two))) for g in two} for k, c in pairs.items()}
    for text in ("ab", "ba aa", "ab bb bb"):
        sums = {k: sum(logs[k][w] for w in text.split()) for k in counts}
        lang, p = langid.Scorer(model).predict(pa.array([text]))
        assert lang[0] == max(sums, key=sums.get) and p[0] == pytest.approx(1 / sum(math.exp(v - max(sums.values())) for v in sums.values()), abs=1e-4)
    unseen = {k: np.mean([of[k][g] for g in (" a",)]) for k in counts}  # of "ac" only " a" is known at length 2, nothing longer
    lang, _ = langid.Scorer(model).predict(pa.array(["ac"]))
    assert lang[0] == max(unseen, key=unseen.get)


def test_shifted_passages_share_chunks_and_are_reported(spark):
    passage = words(80, 77)
    texts = [*ODD, words(200, 50) + " " + passage + " " + words(90, 51), "x" + words(31, 52) + " " + passage, words(300, 53), "short common line here", "short common line here"]
    got = {r["id"]: r for r in chunks.repeated_passages(docs(spark, texts, extra=True)).collect()}
    n = len(ODD)
    for i in (n, n + 1):
        assert any(s["n_words"] >= 50 for s in got[i]["spans"])
        start = (texts[i].encode()).index(passage.encode())
        for s in got[i]["spans"]:
            assert start <= s["start"] and s["stop"] <= start + len(passage)
    assert got[n]["spans"][0]["owned"] and not got[n + 1]["spans"][0]["owned"]
    assert not got[n + 2]["spans"] and not got[n + 3]["spans"] and not got[0]["spans"]
    kept = docs(spark, texts).join(spark.createDataFrame([(i, [tuple(s) for s in got[i]["spans"]]) for i in (n, n + 1)], "doc_id bigint, spans array<struct<start:bigint,stop:bigint,n_words:bigint,n_chunks:bigint,owned:boolean>>"), "doc_id")
    cut = {r[0]: r[1] for r in kept.select("doc_id", chunks.without_repeats(F.col("text"), F.col("spans"))).collect()}
    assert cut[n] == texts[n] and len(cut[n + 1]) < len(texts[n + 1]) - 200
    for t in texts:
        data = np.frombuffer((t or "").encode(), np.uint8)
        ends = chunks.chunk_ends(data)
        assert (ends[-1] == len(data) if len(data) else not len(ends)) and all((t or "").encode()[:e].decode() is not None for e in ends)


def test_every_passage_of_51_words_is_found_whole(spark):
    passages = [words(51, 9000 + i) for i in range(99)] + [" ".join(["lala"] * 51)]
    left = [f"{words(70, 9200 + i)} {i} < {p} > {words(40, 9400 + i)}" for i, p in enumerate(passages)]
    right = [f"{words(33, 9600 + i)} {i} [ {p} ] {words(20, 9800 + i)}" for i, p in enumerate(passages)]
    short = [f"{words(60, 8000 + i)} s{i} {words(50, 8200 + i // 2)} t{i} {words(60, 8400 + i)}" for i in range(20)]
    texts = [*left, *right, *short]
    got = {r["id"]: r["spans"] for r in chunks.repeated_passages(docs(spark, texts)).collect()}
    for i, t in enumerate(texts[:200]):
        start = t.index(passages[i % 100])
        assert [(s["start"], s["stop"], s["n_words"], s["owned"]) for s in got[i]] == [(start, start + len(passages[i % 100]), 51, i < 100)]
    assert not any(got[i] for i in range(200, len(texts)))


def test_each_repeated_text_stays_in_one_document(spark):
    p, q = words(300, 7001), words(120, 7002)
    texts = [p, f"{p} {q}", f"{p} {q}", words(200, 7003) + f" own {q}"]
    df = docs(spark, texts)
    found = chunks.repeated_passages(df).withColumnRenamed("id", "doc_id")
    cut = {r[0]: r[1] for r in df.join(found, "doc_id").select("doc_id", chunks.without_repeats(F.col("text"), F.col("spans"))).collect()}
    assert cut[0] == p and cut[2] == "" and len(cut[3]) < len(texts[3]) - len(q) + 100
    assert q in cut[1] and len(cut[1]) < len(q) + 100


def edit_distance_inside(p, t):
    row = list(range(len(p) + 1))
    best = len(p)
    for c in t:
        new = [0]
        for i in range(1, len(p) + 1):
            new.append(min(row[i - 1] + (p[i - 1] != c), row[i] + 1, new[i - 1] + 1))
        row = new
        best = min(best, row[-1])
    return best


def test_edit_matching_against_brute_force(spark):
    r = random.Random(9)
    items = [(i, "".join(r.choice("abcd ") for _ in range(r.randint(0, 40)))) for i in range(12)] + [(50, None)]
    texts = []
    for i in range(60):
        t = "".join(r.choice("abcd ") for _ in range(r.randint(0, 120)))
        if i % 2:
            p = list(items[i % 12][1])
            for _ in range(r.randint(0, 4)):
                if p:
                    p[r.randrange(len(p))] = r.choice("abcd")
            t += "".join(p) + "zz"
        texts.append(t)
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    df = docs(spark, texts, extra=True)
    got = {(x["id"], x["item_id"]): x["distance"] for x in decontaminate.benchmark_matches(df, bench, share=0.1).collect() if x["id"] is not None}
    want = {}
    for i, t in enumerate(texts):
        for k, p in items:
            q, whole = decontaminate.plain(p or ""), decontaminate.plain(t)
            if q and not (least := decontaminate.budget(q, 0.1)):
                if re.search(rf"(?<![a-z]){re.escape(q)}(?![a-z])", whole):
                    want[i, k] = 0
            elif q and (d := edit_distance_inside(q, whole)) <= least:
                want[i, k] = d
    assert got == want
    several = {(x["id"], x["item_id"]) for x in decontaminate.benchmark_matches(df, bench, share=0.1, pass_bytes=60).collect() if x["id"] is not None}
    assert several == set(want)
    clean = {x["doc_id"] for x in decontaminate.without_matches(df, bench, share=0.1).collect() if x["doc_id"] is not None}
    assert clean == set(range(len(texts))) - {i for i, _ in want}
    assert decontaminate.benchmark_matches(df, bench.limit(0)).count() == 0


PAGE = "<!doctype html><html><head><title>T</title><style>p{}</style></head><body><header>Site name</header><nav><ul><li>Home<li>News</ul></nav><div class='cookie-notice'>We use cookies</div>{0}<aside>More</aside><footer>&copy; x</footer><script>var a='<p>no</p>'</script></body></html>"


def test_main_text_of_pages(spark):
    article = "<article><h1>Head &amp; tail</h1><p>One  <b>two</b><br>three<p>four &lt;b&gt;<!-- c --><div class='comments'><p>nice!</div><p class=ad>Buy</article>"
    shared = "this host repeats the same long sentence on each of its pages every time"
    plain = [PAGE.replace("{0}", f"<div><p>{shared}</p><p>unique words number {i} are {words(12, 900 + i)}</p></div>") for i in range(6)]
    htmls = [PAGE.replace("{0}", article), None, "", "no markup at all", "<p>open <div>inner", *plain, PAGE.replace("{0}", article)]
    rows = [(i, None if i == 1 else f"http://h.example/{i}", h) for i, h in enumerate(htmls)] + [(None, "not a url", "<p>x")]
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string").withColumn("host", F.lit("clash")).withColumn("part", F.lit(0))
    got = {r["page_id"]: r for r in htmltext.main_text(df).collect()}
    assert len(got) == len(rows)
    assert got[0]["text"] == got[11]["text"] == "Head & tail\nOne two three\nfour <b>"
    assert got[1]["text"] == got[2]["text"] == "" and got[3]["text"] == "no markup at all" and got[4]["text"] == "open\ninner"
    for i in range(5, 11):
        assert shared not in got[i]["text"] and "unique words number" in got[i]["text"] and "cookies" not in got[i]["text"]
        assert got[i]["n_chars"] == len(got[i]["text"])
    assert htmltext.main_text(df.limit(0)).count() == 0


def kept_of(page):
    out = htmltext.blocks_of(page)
    best = max((r for _, r in out), default=0)
    return [t for t, r in out if r == best]


def test_articles_inside_a_page_wrapper_are_kept():
    body = "<p>menu</p><article><p>body text</p><form><p>send</p></form></article>"
    for wrap in ("<form>{}</form>", "<div class='content-sidebar-wrap'>{}</div>", "<div id='page' class='has-sidebar'><div>{}</div></div>", "<div class='sidebar'>{}</div>"):
        assert kept_of(wrap.format(body)) == ["body text"]
    for wrap in ("<div class='comments'>{}</div>", "<aside>{}</aside>", "<div hidden>{}</div>", "<article>own</article><div class='sidebar'>{}</div>"):
        assert {t: r for t, r in htmltext.blocks_of(wrap.format(body))}["body text"] == 0


def test_article_content_is_not_judged_by_parts_of_names():
    body = "<h2 id='related-work'>Work</h2><section class='side-effects'>Side</section><div id='search-algorithms'>Search</div><p class='share-prices'>Prices</p>"
    assert kept_of(f"<article>{body}</article>") == ["Work", "Side", "Search", "Prices"]
    assert kept_of("<article><header><h1>Title</h1></header><p>x</article>") == ["Title", "x"] == kept_of("<article><div><header><h1>Title</h1></header></div><p>x</article>")
    assert kept_of("<main><div>notice</div><article><p>text</article><div>promo</div></main>") == ["text"]
    assert kept_of("<main><header><h1>Title</h1></header><p>text<div class='ad wide'>buy</div></main>") == ["Title", "text"]
    assert kept_of("<article>a<p class=ad>b<p>c<div id=comments><article class=comment>d</article></div>e</article>") == ["a", "c", "e"]


def test_pages_without_articles_against_brute_force(spark):
    r = random.Random(12)
    common = [" ".join(r.choice(VOCAB) for _ in range(r.randint(6, 14))) for _ in range(5)]
    pages = []
    for i in range(40):
        blocks = [r.choice(common) if r.random() < 0.5 else words(r.randint(4, 20), 5000 + 50 * i + k) for k in range(6)]
        pages.append(blocks if i % 8 else pages[0] if pages else blocks)  # some pages are copies
    df = spark.createDataFrame([(i, "http://h.example/", "".join(f"<div>{b}</div>" for b in p)) for i, p in enumerate(pages)], "page_id bigint, url string, html string")
    got = {x["page_id"]: x["text"] for x in htmltext.main_text(df).collect()}
    streams = {tuple(" ".join(p).split()) for p in pages}
    on = {}
    for k, s in enumerate(streams):
        for j in range(len(s) - 7):
            on.setdefault(s[j : j + 8], set()).add(k)
    for i, p in enumerate(pages):
        s, at, want = " ".join(p).split(), 0, []
        cover = [False] * len(s)
        for j in range(len(s) - 7):
            if len(on[tuple(s[j : j + 8])]) >= 3:
                cover[j : j + 8] = [True] * 8
        for b in p:
            n = len(b.split())
            if sum(cover[at : at + n]) < 0.8 * n:
                want.append(b)
            at += n
        assert got[i] == "\n".join(want)


def test_boilerplate_inside_articles(spark):
    line = "share this story with all of your friends on every network now"
    page = lambda i: f"<article><p>{words(40, 600 + i)}</p><p>{line}</p></article>"
    copy = f"<article><p>{words(40, 77)}</p><p>{words(12, 78)}</p></article>"
    rows = [(i, "http://h.example/", page(i) if i < 12 else copy + f"<div>{words(9, 900 + i)}</div>") for i in range(20)]
    got = {x["page_id"]: x["text"] for x in htmltext.main_text(spark.createDataFrame(rows, "page_id bigint, url string, html string")).collect()}
    assert all(got[i] == words(40, 600 + i) for i in range(12)) and all(got[i] == words(40, 77) + "\n" + words(12, 78) for i in range(12, 20))


def test_host_shares_do_not_depend_on_groups(spark):
    common = [words(12, 7000 + k) for k in range(6)]
    # Each common block is on 2 to 4 distinct pages of 60, far apart; page 0 has 40 copies, page 1 five, and all pages stand in an order by chance.
    pages = [[words(15, 7100 + i), *[c for k, c in enumerate(common) if i % (15 + 6 * k) == k], words(9, 7300 + i)] for i in range(60)]
    pages += [pages[0]] * 40 + [pages[1]] * 5
    line = "share this story with all of your friends on every network now"
    html = ["".join(f"<div>{b}</div>" for b in p) for p in pages]
    rows = [(i, "http://h.example/", h) for i, h in enumerate(html)]
    rows += [(1000 + i, "http://other.example/", f"<article><p>{words(40, 7500 + i)}</p>" + (f"<p>{line}</p>" if i % 2 else "") + "</article>") for i in range(30)]
    rows += [(2000, None, "<p>alone"), (None, "http://h.example/", None)]
    random.Random(5).shuffle(rows)
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    streams = {tuple(" ".join(p).split()) for p in pages}
    on = {}
    for k, s in enumerate(streams):
        for j in range(len(s) - 7):
            on.setdefault(s[j : j + 8], set()).add(k)
    least = max(3, -(-2 * (len(streams) + 1) // 100))  # the null page is one more stream
    want = {1000 + i: words(40, 7500 + i) for i in range(30)} | {2000: "alone", None: ""}
    for i, p in enumerate(pages):
        gone = {b for b in p if len(on[tuple(b.split()[:8])]) >= least}
        want[i] = "\n".join(b for b in p if b not in gone)
    assert 0 < sum(len(want[i].split("\n")) < len(pages[i]) for i in range(60)) < 60
    whole = sorted(map(str, htmltext.main_text(df).collect()))
    for n in (3, 10, 1000):
        out = htmltext.main_text(df, group_pages=n).collect()
        assert {x["page_id"]: x["text"] for x in out} == want and sorted(map(str, out)) == whole


def test_suffix_cover_against_brute_force():
    r = random.Random(4)
    toks = np.array([r.randrange(6) for _ in range(300)])
    page = np.repeat(np.arange(10), 30)
    got = htmltext.repeated_cover(toks, page, 4, 3)
    want = np.zeros(300, bool)
    runs = {}
    for i in range(297):
        if page[i] == page[i + 3]:
            runs.setdefault(tuple(toks[i : i + 4]), []).append(i)
    for at in runs.values():
        if len({page[i] for i in at}) >= 3:
            for i in at:
                want[i : i + 4] = True
    assert (got == want).all()


def test_warc_round_trip(spark, tmp_path):
    rows = [(1, "http://a/x?q=1", "same"), (2, "http://b/", "same"), (3, None, None), (4, "http://c/", ""), (5, "http://d/", "é" * 3000), (5, "http://d/", "é" * 3000), (None, "http://e", "same"), (6, "http://f/\r\nX: y", "WARC/1.1\r\n\r\n")]
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string").withColumn("digest", F.lit(1)).withColumn("n_first", F.lit(2))
    found = warc.assemble(warc.read_archives(warc.write_archives(warc.elect_responses(df), f"file://{tmp_path}/w", archive_bytes=500))).collect()
    assert len(found) == len(rows) and all(r["request"] and r["response"] and r["metadata"] for r in found)
    by = {}
    for r in found:
        by.setdefault(r["metadata"]["page_id"], []).append(r)
    assert by[2][0]["response"]["record_type"] == "response" and bytes(by[2][0]["response"]["payload"]) == b"same"
    assert by[1][0]["response"]["record_type"] == by[None][0]["response"]["record_type"] == "revisit" and by[1][0]["metadata"]["refers_to"] == 2
    assert by[1][0]["response"]["payload_bytes"] == 4 and by[1][0]["response"]["refers_to_id"] == by[2][0]["response"]["record_id"] is not None
    assert by[4][0]["response"]["record_type"] == "response" and by[3][0]["metadata"]["refers_to"] == 4 and by[3][0]["response"]["target_uri"] is None
    assert [x["response"]["record_type"] for x in by[5]] == ["response", "response"] and by[6][0]["metadata"]["url"] == "http://f/\r\nX: y"
    assert bytes(by[6][0]["response"]["payload"]) == b"WARC/1.1\r\n\r\n"


def test_media_round_trip(spark):
    rows = {r["id"]: r for r in media.fingerprints(media.media_column(docs(spark, ODD, extra=True))).withColumn("feature", media.feature_of()).collect()}
    assert media.fingerprints(media.media_column(docs(spark, ODD).limit(0))).count() == 0
    for i, t in enumerate(ODD):
        raw = (t or "").encode()
        want = raw + b"\0" * ((-len(raw)) % 64 if raw else 64)
        assert rows[i]["payload_sha256"] == hashlib.sha256(want).hexdigest() and rows[i]["payload_bytes"] == len(want)
        assert rows[i]["n_bytes"] == len(raw) and rows[i]["tail_crc32"] == zlib.crc32(want[-64:])
        assert list(rows[i]["pair_times"]) == sorted(rows[i]["pair_times"])
    assert rows[5]["feature"] == rows[6]["feature"] != rows[7]["feature"]
    with wave.open(io.BytesIO(media.to_wav(b"\x01" * 64))) as w:
        assert (w.getsampwidth(), w.getnframes()) == (1, 64)


def test_peaks_do_not_depend_on_blocks(monkeypatch):
    x = LONG.encode()[:9000]
    whole = media.peak_pairs(x)
    monkeypatch.setattr(media, "FRAMES_AT_ONCE", 7)
    part = media.peak_pairs(x)
    assert (whole[0] == part[0]).all() and (whole[1] == part[1]).all()
