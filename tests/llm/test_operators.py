"""The training-data operators: brute force, round trips, and odd tables.

Odd tables have nulls in every column, empty and very long texts, ties and repeated rows, and
columns whose names clash with ones that operators use inside.
"""

import hashlib
import re
import zlib
from collections import Counter
from itertools import combinations, product

import numpy as np
import pytest
import xxhash
from conftest import SF, same
from pyspark.sql import functions as F

from dpsynth.llm import backoff, bpe, chat, fmindex, langid, licences, linededup, nearcopies, pii, quality, registry, simhash

DOCS = "doc_id long, text string, lang string, source string, n_chars long, fp long, h1 string, llm_key int, score double, grp string, seen int"
LONG = "Le the chat und 12 " * 20_000
ROWS = [
    (1, "A shared line here\nThe quick brown fox", "en", "s", 1), (1, "A shared line here\nThe quick brown fox", "en", "s", 1), (2, "a shared LINE here \n\nÉtoile", "fr", None, 2),
    (3, None, None, None, None), (None, "A shared line here", "en", "s", 3), (None, None, "en", None, 0), (4, "", "en", "s", 0), (5, "\n\n \t", "de", "s", 4),
    (6, LONG, "en", "s", len(LONG)), (7, "1234 ... !!", "en", "s", 5), (8, "日本語 текст emoji 😀", None, "t", 9), (9, "all RIGHTS reserved cc-by", "en", "t", 9),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(*r, 1, "x", 2, 0.5, "g", 3) for r in ROWS], DOCS).repartition(3)


@pytest.fixture(scope="module")
def documents(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def spaced(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def worded(text):
    return re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", lower(text))


def sha(text):
    return hashlib.sha256(text.encode()).hexdigest()


RUNS = {
    "langid": langid.predict_languages, "quality": quality.judge, "backoff": backoff.score_documents, "simhash": simhash.component_digests, "near": nearcopies.signatures, "lines": linededup.line_digests,
    "licences": licences.scan, "pii": pii.find, "bpe": bpe.encode_digests, "fm": lambda d: fmindex.contamination_digests(d, d.selectExpr("doc_id as item_id", "text").where("doc_id = 9")),
}


@pytest.mark.parametrize("name", list(RUNS))
def test_odd_and_empty_tables(odd, name):
    run = RUNS[name]
    found = run(odd).collect()
    assert len(found) == len(ROWS)
    assert sorted(r["doc_id"] or -1 for r in found) == sorted(r[0] or -1 for r in ROWS)
    by = {}
    for r in found:  # repeated rows have equal results
        by.setdefault(r["doc_id"], []).append(r)
    assert by[1][0] == by[1][1]
    assert run(odd.limit(0)).count() == 0


@pytest.mark.parametrize(("name", "sql"), [(n, q) for n, (_, q) in registry.REGISTERED.items() if q])
def test_queries_equal_their_sql(spark, duck, name, sql):
    same(registry.REGISTERED[name][0](spark, SF).toPandas(), duck(sql))


# -- 1 chat -----------------------------------------------------------------------------------------
def test_chat_round_trip():
    rng = np.random.default_rng(2)
    bits = [*chat.CONTROL, "\\", "<", "[", "x", "é", "/", ">>", "\n"]
    for _ in range(2000):
        turns = [(str(rng.choice(["user", "assistant", "system", "tool", "<s>\\"])), "".join(rng.choice(bits, rng.integers(0, 9)))) for _ in range(rng.integers(0, 5))]
        text, spans = chat.render(turns)
        assert chat.read_back(text) == turns
        assert [chat.unescape(text[a:b]) for a, b in spans] == [t for r, t in turns if r == "assistant"]


def test_chat_layouts(spark):
    frames = {
        "messages array<struct<role:string,content:string>>, n int": ([("human", "a"), ("assistant", None)], 1),
        "conversations array<struct<`from`:string,value:string>>": ([("human", "a"), ("gpt", "")],),
        "prompt string, response string": ("a", None),
        "instruction string, output string, input string": ("a", None, None),
        "question string, answer string, system string": ("a", None, "s"),
    }
    for schema, row in frames.items():
        turns = [(t["role"], t["text"]) for t in chat.canonical_turns(spark.createDataFrame([row], schema)).first()["turns"]]
        assert [t for t in turns if t[0] != "system"] == [("user", "a"), ("assistant", "")]
    with pytest.raises(ValueError):
        chat.canonical_turns(spark.createDataFrame([(1,)], "x int"))


def test_chat_records_and_nulls(spark):
    rows = [(1, '{"messages":[{"role":"user","content":"x"}]}'), (2, '{"question":"q","answer":"a"}'), (3, "no json"), (None, None), (5, "[1]")]
    found = {r["conv_id"]: r for r in chat.canonical_records(spark.createDataFrame(rows, "conv_id long, record string")).collect()}
    assert found[1]["layout"] == "messages" and found[2]["layout"] == "question_answer" and found[3]["turns"] is None and found[5]["turns"] is None
    turns = spark.createDataFrame([(1, 1, "assistant", None), (1, 0, None, "a"), (None, None, "user", "b"), (1, 0, None, "a")], "conv_id long, turn long, role string, text string")
    out = {r["conv_id"]: r for r in chat.chat_digests(turns).collect()}
    assert out[1]["n_turns"] == 3 and out[1]["turns_sha256"] == sha("\na\n\na\nassistant\n\n") and out[None]["n_turns"] == 1
    assert chat.chat_digests(turns.limit(0)).count() == 0


# -- 2 languages ------------------------------------------------------------------------------------
def test_languages_on_held_out_documents(documents):
    found = langid.predict_languages(documents).join(documents.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert np.mean([r["lang_pred"] == r["lang"] for r in found]) > 0.97
    assert all(0 <= r["score"] <= 1 for r in found)


def test_language_of_nothing(odd):
    found = {r["doc_id"]: r for r in langid.predict_languages(odd).collect()}
    assert all(found[k]["lang_pred"] == "und" and found[k]["score"] == 0 for k in (3, 4, 5, 7))
    unlabelled = langid.predict_languages(odd.selectExpr("doc_id", "text", "cast(null as string) as lang"))
    assert {r["lang_pred"] for r in unlabelled.collect()} == {"und"}


def brute_grams(text, bits):
    """Buckets of the bi- and trigrams with a letter; everything but letters is a blank."""
    c = [ord(x) if x.isalpha() else 32 for x in text.lower()]
    m = (1 << 32) - 1
    for n, salt in ((2, 0), (3, 0x27D4EB2F)):
        for i in range(len(c) - n + 1):
            if any(x != 32 for x in c[i : i + n]):
                h = (c[i] * 0x9E3779B1 & m) ^ (c[i + 1] * 0x85EBCA6B & m) ^ (c[i + 2] * 0xC2B2AE35 & m if n == 3 else 0) ^ salt
                h = (h ^ h >> 15) * 0x2C1B3C6D & m
                yield h >> 32 - bits


@pytest.mark.parametrize("block_bytes", [1 << 30, 4 << langid.BUCKET_BITS])
def test_predictions_equal_a_plain_naive_bayes(spark, documents, block_bytes):
    rows = [(r["doc_id"], r["text"], r["lang"]) for r in documents.collect()]
    learn = [r for r in rows if zlib.crc32(str(r[0]).encode()) % 3 != 1]
    langs = sorted({lang for _, _, lang in learn})
    cnt = {lang: Counter(g for _, t, x in learn if x == lang for g in brute_grams(t, 16)) for lang in langs}
    size = {lang: sum(cnt[lang].values()) + 0.5 * (1 << 16) for lang in langs}
    model = langid.train(documents)
    found = {r["doc_id"]: r for r in langid.identify(documents.select("doc_id", "text"), model, block_bytes=block_bytes).collect()}
    for i, text, _ in [r for r in rows if len(r[1]) < 20_000][:80]:
        grams = list(brute_grams(text, 16))
        joint = [np.log(sum(x == lang for _, _, x in learn) / len(learn)) + sum(np.log((cnt[lang][g] + 0.5) / size[lang]) for g in grams) for lang in langs]
        cold = np.array(joint) * min(1, langid.EVIDENCE / len(grams))
        assert found[i]["lang_pred"] == langs[int(np.argmax(joint))]
        assert found[i]["score"] == pytest.approx(1 / np.exp(cold - cold.max()).sum(), abs=1e-3)


def test_long_texts_score_like_their_grams():
    index = langid.GramIndex(12)
    text = "Thé quick brown fox. " * 60_000
    total = sum(np.bincount(row, minlength=4097)[:-1] for _, _, _, rows in index.batches([text]) for row in rows)
    langid_segment, langid.SEGMENT = langid.SEGMENT, 1 << 30
    try:
        whole = sum(np.bincount(row, minlength=4097)[:-1] for _, _, _, rows in index.batches([text]) for row in rows)
    finally:
        langid.SEGMENT = langid_segment
    assert (total == whole).all()


# -- 3 quality --------------------------------------------------------------------------------------
def brute_statistics(text):
    text = text or ""
    words, lines = spaced(text), [x for x in text.split("\n") if spaced(x)]
    grams = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    hit = {i + k for i, g in enumerate(grams) if grams.count(g) > 1 for k in range(3)}
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(hit)


def test_word_statistics(documents):
    for r in documents.limit(60).collect():
        assert quality.word_statistics(r["text"][:4000]) == brute_statistics(r["text"][:4000])
    for text in (None, "", "a b a b a b", "x y z\x0bq", "a\na\n \n \nb"):
        assert quality.word_statistics(text) == brute_statistics(text)


def test_outliers_are_found(spark):
    rng = np.random.default_rng(0)
    word = lambda: "".join(rng.choice(list("abcdefghij"), rng.integers(3, 8)))
    clean = [(i, " ".join(word() for _ in range(80)), "en", "s") for i in range(120)]
    junk = [(1000 + i, " ".join(word() + "###" for _ in range(80)), "en", "s") for i in range(10)]
    found = {r["doc_id"]: r["kept"] for r in quality.judge(spark.createDataFrame(clean + junk, "doc_id long, text string, lang string, source string")).collect()}
    assert all(found[i] for i in range(120)) and not any(found[1000 + i] for i in range(10))


def test_repeated_lines_are_rejected_in_a_clean_group(spark):
    rng = np.random.default_rng(1)
    word = lambda: "".join(rng.choice(list("abcdefghij"), rng.integers(3, 8)))
    text = lambda n: "\n".join(" ".join(word() for _ in range(10)) for _ in range(n))
    clean = [(i, text(30), "en", "s") for i in range(120)]
    line = " ".join(word() for _ in range(10))
    half = [(1000, text(16) + ("\n" + line) * 14, "en", "s")]
    once = [(1001, text(28) + ("\n" + line) * 2, "en", "s")]
    found = {r["doc_id"]: r for r in quality.judge(spark.createDataFrame(clean + half + once, "doc_id long, text string, lang string, source string")).collect()}
    assert not found[1000]["base_failed"] and not found[1000]["kept"]
    assert all(found[i]["kept"] for i in (*range(120), 1001))


def test_determinant_is_the_smallest_of_all_subsets():
    rng = np.random.default_rng(4)
    for _ in range(6):
        v = rng.standard_normal((13, 4)) @ rng.standard_normal((4, 4)) * 2
        v[:3] += rng.standard_normal(4) * 20
        found, mean, cov = quality.least_determinant(quality.Moments.of_points(v))
        every = [(quality.objective(np.cov(v[list(k)].T, bias=True)), k) for k in combinations(range(13), 10)]
        least, best = min(every)
        assert found == pytest.approx(least) and mean == pytest.approx(v[list(best)].mean(0)) and cov == pytest.approx(np.cov(v[list(best)].T, bias=True))
    assert (quality.consistency(0.75), quality.consistency(0.975)) == pytest.approx((1.4866, 1.0645), abs=1e-3)


def test_verdict_is_not_that_of_the_start():
    rng = np.random.default_rng(5)
    v = rng.standard_normal((400, 1)) @ np.array([[3.0, 3.0, 3.0, 3.0]]) + 0.8 * rng.standard_normal((400, 4))
    v[:20] = np.array([3.0, -3.0, 3.0, -3.0]) + 0.3 * rng.standard_normal((20, 4))  # usual on each axis, against the correlation
    cells = quality.Moments.of_points(v)
    mean, cov = next(quality.starting_points(cells, rng))
    assert (cells.distances(mean, cov)[:20] <= quality.CUTOFF).all()
    mean, inverse, scale = quality.robust_estimate(cells)
    far = np.einsum("ij,jk,ik->i", v - mean, inverse, v - mean) / scale
    assert (far[:20] > quality.CUTOFF).all() and (far[20:] > quality.CUTOFF).mean() < 0.02


def test_verdicts_equal_those_without_cells(spark):
    """A plain version: every group's vectors in one array, no grid."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = quality.with_groups(quality.with_vectors(quality.statistics(docs)), quality.MIN_GROUP).toPandas()
    got = {r["doc_id"]: r for r in quality.judge(docs).collect()}
    assert rows["grp"].nunique() > 10  # some per language and source
    differ = 0
    for _, g in rows[~rows["base_failed"]].groupby("grp"):
        v = g[[f"v{i}" for i in range(4)]].to_numpy()
        mean, inverse, scale = quality.robust_estimate(quality.Moments.of_points(v))
        far = np.einsum("ij,jk,ik->i", v - mean, inverse, v - mean) / scale
        for i, d in zip(g["doc_id"], far, strict=True):
            differ += got[i]["kept"] != (d <= quality.CUTOFF)
    assert differ <= 0.005 * len(rows)
    assert not any(got[i]["kept"] for i in rows[rows["base_failed"]]["doc_id"])


def test_verdicts_against_quality_labels(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    by = {r["quality"]: r["kept"] for r in quality.judge(docs).join(labels, "doc_id").where("not base_failed").groupBy("quality").agg(F.avg(F.col("kept").cast("int")).alias("kept")).collect()}
    assert by[0] < 0.15 and by[1] > 0.98


def test_cells_are_bounded(spark):
    rng = np.random.default_rng(6)
    rows = spark.createDataFrame([("g", *map(float, r)) for r in rng.uniform(0, 4, (3000, 4))] + [("h", 1.0, 0.0, 0.0, 0.0)] * 500, "grp string, v0 double, v1 double, v2 double, v3 double")
    cells = quality.cells_of(rows, 500).toPandas()
    assert cells["m"].sum() == 3500 and (cells["grp"] == "h").sum() == 1 and (cells["grp"] == "g").sum() < 3000
    assert cells["s0"].sum() == pytest.approx(rows.agg({"v0": "sum"}).first()[0])


def test_gram_keys_are_whole_and_sizes_are_counted(spark):
    assert backoff.KEY_BITS == 64
    unknown = spark.createDataFrame(spark.sparkContext.parallelize([(i, "x" * 1000) for i in range(5000)]), "doc_id long, text string")
    assert backoff.input_bytes(unknown) == 5_000_000


def test_relays_change_nothing(spark, documents):
    assert [backoff.hops(n) for n in (1, 81, 5000, 16384, 16385, 1 << 24)] == [(1, 1), (1, 7), (1, 13), (1, 14), (2, 8), (2, 12)]
    plain = backoff.score_documents(documents).toPandas()
    for chunks, bits in ((9, 2), (6, 1)):  # two and three hops
        assert backoff.hops(chunks, bits)[0] == 4 - bits
        same(backoff.score_documents(documents, chunks=chunks, fan_bits=bits).toPandas(), plain)


# -- 5 benchmark ------------------------------------------------------------------------------------
def test_fm_index_against_scanning():
    rng = np.random.default_rng(0)
    seq = np.concatenate([[*rng.integers(1, 4, rng.integers(1, 30)), 0] for _ in range(20)])
    index = fmindex.FMIndex(seq, 3)
    for n in (1, 2, 4):
        patterns = rng.integers(1, 4, (30, n))
        who, at = index.locate(*index.search(patterns))
        found = sorted(zip(who.tolist(), at.tolist(), strict=True))
        assert found == sorted((i, p) for i, x in enumerate(patterns.tolist()) for p in range(len(seq) - n + 1) if seq[p : p + n].tolist() == x)


def test_benchmark_blocks_agree(spark, documents):
    bench = spark.read.parquet(f"{SF}/benchmark.parquet")
    rows = lambda **k: sorted(map(str, fmindex.mark(documents.select("doc_id", "text"), bench, **k).collect()))
    assert rows() == rows(block_bytes=400, shard_bytes=20_000)
    assert fmindex.remove_spans("One, two (three) four", [(1, 3)]) == "One, ) four"


# -- 6 fingerprints ---------------------------------------------------------------------------------
def brute_fingerprint(text):
    w = spaced(lower(text))
    grams = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [" ".join(w)] * bool(w)
    h = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(fps, radius=3):
    parent = list(range(len(fps)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, j in np.argwhere(np.triu(np.bitwise_count(fps[:, None] ^ fps[None, :]) <= radius, 1)):
        a, b = find(i), find(j)
        parent[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(fps))]


def test_components_against_all_pairs(documents):
    rows = documents.select("doc_id", "text").collect()
    fps = np.array([brute_fingerprint(r["text"]) for r in rows], np.uint64)
    root, ids = brute_components(fps), [r["doc_id"] for r in rows]
    least = {}
    for i, k in zip(ids, root, strict=True):
        least[k] = min(i, least.get(k, i))
    want = {i: (f"{f:016x}", least[k]) for i, f, k in zip(ids, fps.tolist(), root, strict=True)}
    assert {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in simhash.component_digests(documents).collect()} == want


@pytest.mark.parametrize(("blocks", "shard", "limit"), [(None, 10**6, 10**6), (4, 100, 80), (6, 100, 10**6), (None, 10**6, 300)])
def test_links_of_clustered_fingerprints(spark, blocks, shard, limit):
    rng = np.random.default_rng(0)
    x = np.repeat(rng.integers(0, 2**63, 40).astype(np.uint64), 30)
    for _ in range(6):
        x ^= (np.uint64(1) << rng.integers(0, 64, len(x)).astype(np.uint64)) * (rng.random(len(x)) < 0.35).astype(np.uint64)
    x = np.unique(x)
    root, signed = brute_components(x), x.view(np.int64).tolist()
    frame = spark.createDataFrame([(v,) for v in signed], "fp long")
    found = {r["node"]: r["root"] for r in simhash.components(simhash.links(frame, 3, blocks, shard, limit)).collect()}
    groups = {}
    for v, k in zip(signed, root, strict=True):
        groups.setdefault(k, []).append(v)
    for g in groups.values():
        assert {found.get(v, v) for v in g} == {min(g)}


def test_cutting_saves_pairs_and_keeps_near_ones_together(spark):
    rng = np.random.default_rng(2)
    x = rng.integers(0, 2**63, 3000).astype(np.uint64)
    x = np.unique(np.concatenate([x, x[:200] ^ np.uint64(5)]))
    homes = spark.createDataFrame([(7, v) for v in x.view(np.int64).tolist()], "shard long, fp long")
    shards = {}
    for r in simhash.cut_large(homes, 3, 400).collect():
        shards.setdefault(r["shard"], set()).add(r["fp"])
    assert len(shards) > 4 and set().union(*shards.values()) == set(x.view(np.int64).tolist())
    assert sum(len(s) ** 2 for s in shards.values()) < 0.75 * len(x) ** 2
    near = [(a, b) for i, a in enumerate(x) for b in x[i + 1 :][np.bitwise_count(x[i + 1 :] ^ a) <= 3]]
    signed = lambda v: int(np.uint64(v).astype(np.int64))
    assert near and all(any({signed(a), signed(b)} <= s for s in shards.values()) for a, b in near)


def test_trees_prune_and_equal_all_pairs():
    rng = np.random.default_rng(1)
    x = np.unique(np.concatenate([rng.integers(0, 2**63, 2000).astype(np.uint64)] * 2) ^ (np.uint64(1) << rng.integers(0, 64, 4000).astype(np.uint64)))
    forest, tally = simhash.Forest(len(x)), Counter()
    simhash.link_within(x, np.arange(len(x)), 3, forest, tally)
    assert [forest.find(i) for i in range(len(x))] == brute_components(x)
    assert tally["nodes"] > 20 and tally["pruned"] > 0.5 * len(x) ** 2 / 2 and tally["compared"] + tally["pruned"] >= len(x) * (len(x) - 1) // 2


def test_trees_run_at_default_settings(spark):
    """On sf0.1 the search of shards of the default size goes through trees that prune."""
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet").select("doc_id", "text")
    x = np.unique(np.array([r["fp"] for r in simhash.fingerprint(docs).select("fp").collect()], np.int64).view(np.uint64))
    assert len(x) > simhash.SHARD  # so several shards, each far beyond a leaf
    tally = Counter()
    a, b = simhash.shard_edges(np.zeros(simhash.SHARD, np.int64), x[: simhash.SHARD], 3, tally)
    assert tally["nodes"] > 30 and tally["pruned"] > 2 * tally["compared"]
    root, of = brute_components(x[: simhash.SHARD]), dict(zip(a.tolist(), b.tolist(), strict=True))
    assert all(of.get(v, v) == int(x[r]) for v, r in zip(x[: simhash.SHARD].tolist(), root, strict=True))


def test_one_of_each_component_stays(odd):
    kept = simhash.keep_one(odd)
    assert kept.columns == odd.columns
    groups = {r["component_id"] for r in simhash.component_digests(odd).collect()}
    assert kept.count() == len(groups)


# -- 7 lines ----------------------------------------------------------------------------------------
def test_lines_first_occurrence_stays(odd):
    texts = sorted(r["text"] for r in linededup.dedup_lines(odd, "later", 2).collect() if "hared" in r["text"])
    assert texts == ["A shared line here"]  # the row without doc_id comes first
    everywhere = linededup.dedup_lines(odd, "all", 3)
    assert not any("hared" in r["text"] for r in everywhere.collect())
    assert everywhere.columns[-2:] == ["llm_n_lines", "llm_n_dropped"]


def test_line_plan_has_no_python(odd):
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    hashes = linededup.occurrences(odd)
    counted = plan(linededup.key_statistics(hashes))  # the two steps before this one are cut
    assert "rangepartitioning" in counted
    for p in (plan(linededup.line_digests(odd)), counted, plan(odd.select(linededup.line_keys(odd["text"])))):
        assert "Python" not in p and "Arrow" not in p


def test_min_chars_counts_code_points(spark):
    df = spark.createDataFrame([(i, "é\nab") for i in range(3)], "doc_id long, text string")
    assert {r["text"] for r in linededup.dedup_lines(df, "all", 3, 2).collect()} == {"é"}


def test_second_line_hash_is_not_seeded_by_the_first(spark):
    lines = ["a shared line", "other"]
    text = spark.createDataFrame([("\n".join(lines),)], "text string")
    got = text.select(linededup.line_keys(text["text"]).alias("k")).first()["k"]
    second = spark.createDataFrame([(x,) for x in lines], "x string").selectExpr("xxhash64(x, 'second') as c", "xxhash64('second', x) as own").collect()
    assert [k["h2"] for k in got] == [r["own"] for r in second]
    assert not {k["h2"] for k in got} & {r["c"] for r in second}


# -- 8 licences -------------------------------------------------------------------------------------
def test_base_phrases(documents):
    found = {r["doc_id"]: r for r in licences.scan(documents).collect()}
    for r in documents.collect():
        w, places = worded(r["text"]), []
        for phrase, label in licences.BASE.items():
            p = phrase.split()
            places += [(i, label) for i in range(len(w)) if w[i : i + len(p)] == p]
        f = found[r["doc_id"]]
        assert (f["n_words"], f["n_base"], f["first_word"], f["last_word"]) == (len(w), len(places), min(places)[0] if places else None, max(places)[0] if places else None)
        assert f["base_labels"] == ",".join(sorted({x for _, x in places})) and set(f["base_labels"].split(",")) - {""} <= set(f["labels"].split(","))


def test_templates_are_found(spark):
    rows = [(i, "Zzz qqq.\n" + notice.upper() + "\nend") for i, (notice, _) in enumerate(licences.TEMPLATES.values())]
    found = {r["doc_id"]: r for r in licences.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for i, name in enumerate(licences.TEMPLATES):
        assert name in found[i]["labels"].split(",") and found[i]["score"] == 1.0
    none = licences.scan(spark.createDataFrame([(1, "license apache the version of 2 under")], "doc_id long, text string")).first()
    assert none["labels"] == ""


@pytest.mark.parametrize("rare_words", [1, licences.RARE_WORDS])
def test_all_templates_in_one_text(spark, rare_words):
    some = ["mit-grant", "bsd", "apache-2.0", "gpl-3.0", "mit"]
    notices = [[n for n, _ in licences.TEMPLATES.values()], [licences.TEMPLATES[t][0] for t in some]]
    rows = [(i, "\nzzz\n".join(x)) for i, x in enumerate(notices)]
    found = {r["doc_id"]: r for r in licences.scan(spark.createDataFrame(rows, "doc_id long, text string"), rare_words).collect()}
    assert set(licences.TEMPLATES) <= set(found[0]["labels"].split(",")) and set(some) <= set(found[1]["labels"].split(","))
    assert found[0]["score"] == found[1]["score"] == 1.0


def brute_labels(text):
    w, labels, best = worded(text), {x for p, x in licences.BASE.items() if f" {p} " in f" {' '.join(worded(text))} "}, 0.0
    for name, (notice, must) in licences.TEMPLATES.items():
        n = notice.split()
        for at in range(-len(n), len(w)):
            fits = [0 <= at + i < len(w) and w[at + i] == x for i, x in enumerate(n)]
            whole = all(all(fits[i : i + len(p)]) for p in map(str.split, must) for i in [next(i for i in range(len(n)) if n[i : i + len(p)] == p)])
            if whole and sum(fits) / len(n) >= licences.MIN_SHARE:
                labels.add(name)
                best = max(best, sum(fits) / len(n))
    return ",".join(sorted(labels)), best


def test_labels_equal_all_alignments(spark, documents):
    rng, texts = np.random.default_rng(8), [r["text"][:1500] for r in documents.limit(60).collect()]
    for notice, _ in licences.TEMPLATES.values():
        for _ in range(6):  # words lost, changed and put in, at the ends of texts too
            w = notice.split()
            for _ in range(rng.integers(0, 4)):
                k = int(rng.integers(len(w)))
                w[k : k + int(rng.integers(0, 2))] = ["zzz"] * int(rng.integers(0, 2))
                w = w or ["zzz"]
            texts.append(" ".join(["so"] * int(rng.integers(0, 3)) + w + ["by"] * int(rng.integers(0, 3))).title())
    frame = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    found = {r["doc_id"]: (r["labels"], r["score"]) for r in licences.scan(frame).collect()}
    for i, t in enumerate(texts):
        labels, best = brute_labels(t)
        assert found[i] == (labels, pytest.approx(best)), t


def test_licence_plan_has_no_python(odd):
    plan = licences.scan(odd)._jdf.queryExecution().executedPlan().toString()
    places = licences.word_places(odd)
    for p in (plan, licences.alignments(places)._jdf.queryExecution().executedPlan().toString()):
        assert "Python" not in p and "Arrow" not in p and "Pandas" not in p


# -- 9 personal data --------------------------------------------------------------------------------
NAIVE = [r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", r"[0-9]([\x20-]?[0-9])+", r"\+[0-9][\x20().0-9-]+[0-9]"]


def naive_spans(text):
    digits = lambda m: re.sub("[^0-9]", "", m[0])
    good = [lambda m: True, lambda m: all(int(p) <= 255 for p in m[0].split(".")), lambda m: 13 <= len(digits(m)) <= 19 and pii.luhn(digits(m)), lambda m: 9 <= len(digits(m)) <= 15]
    return [(k, *m.span()) for k, (p, ok) in enumerate(zip(NAIVE, good, strict=True)) for m in re.finditer(p, text) if ok(m)]


def test_patterns_equal_the_regular_expressions():
    rng = np.random.default_rng(3)
    bits = ["a", ".", "@", "1", "25", "300", "-", " ", "+", "(", ")", "é", "4111111111111111", "%", "\n", "٣", "0000001", "9" * 30]
    for _ in range(20_000):
        text = "".join(rng.choice(bits, rng.integers(0, 24)))
        assert pii.base_spans(text) == naive_spans(text)
    for text in ("a" * 300_000, "1" * 300_000 + ".", "1." * 100_000, "a@" * 100_000, "+1" + "(" * 200_000):
        pii.base_spans(text)


def test_tagger_gradients():
    t, rng = pii.Tagger(), np.random.default_rng(0)
    t.p = {k: v.astype(np.float64) for k, v in t.p.items()}
    codes, tags = rng.integers(0, pii.N_CLASSES, (7, 3)), np.array([[0, 1, 2], [1, 2, 2], [2, 2, 0], [0, 0, 3], [3, 5, 4], [4, 6, 4], [0, 6, 4]])
    _, g = t.gradients(codes, tags)
    for name in t.p:
        at = tuple(rng.integers(0, s) for s in t.p[name].shape)
        if name == "trans" and pii.RULED_OUT[at]:
            continue
        old = t.p[name][at]
        t.p[name][at] = old + 1e-4
        up = t.gradients(codes, tags)[0]
        t.p[name][at] = old - 1e-4
        down = t.gradients(codes, tags)[0]
        t.p[name][at] = old
        assert g[name][at] == pytest.approx((up - down) / 2e-4, rel=1e-2, abs=1e-4)


def test_decoding_equals_all_paths():
    t, rng = pii.Tagger(3), np.random.default_rng(1)
    free = ~pii.RULED_OUT
    t.p["trans"][free] = rng.standard_normal(free.sum())
    codes = rng.integers(0, pii.N_CLASSES, (5, 4))
    e, trans = t.emissions(codes.T), t.p["trans"]
    paths = np.array(list(product(range(pii.TAGS), repeat=4)))
    score = t.p["start"][paths[:, 0]] + trans[paths[:, 0], paths[:, 1]] + trans[paths[:, 1], paths[:, 2]] + trans[paths[:, 2], paths[:, 3]]
    tags, sure = t.decode(codes)
    for k in range(5):
        total = score + sum(e[i, k, paths[:, i]] for i in range(4))
        weight = np.exp(total - total.max())
        assert tags[k].tolist() == paths[total.argmax()].tolist()
        if tags[k].any():
            assert sure[k] == pytest.approx([weight[paths[:, i] == tags[k, i]].sum() / weight.sum() for i in range(4)], abs=1e-4)
    assert t._crf(e)[2] == pytest.approx([np.logaddexp.reduce(score + sum(e[i, k, paths[:, i]] for i in range(4))) for k in range(5)], rel=1e-4)


def test_tagger_on_held_out_passages(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    passages = pii.passages_of(docs, 500)
    assert len(passages) > pii.TRAIN_PASSAGES + 100 and all(len(p) <= pii.PASSAGE and not pii.TRIGGER.search(p) for p in passages)
    tagger, held = pii.trained(passages[: pii.TRAIN_PASSAGES]), passages[pii.TRAIN_PASSAGES :]
    plain, both = pii.evaluate(None, held, 99), pii.evaluate(tagger, held, 99)
    total = lambda r, k: sum(x[k] for x in r.values())
    assert total(plain, 1) < 0.4 * total(plain, 0)  # the patterns alone
    assert total(both, 1) > 0.85 * total(both, 0) and total(both, 1) > 0.93 * total(both, 2)  # recall and precision
    texts = [pii.Forge(5).write(p)[0] for p in held[:40]] + ["", "no digits", "12 May 2021, version 3.0.1"]
    for t, (base, every) in zip(texts, pii.all_spans(texts, tagger), strict=True):
        assert set(base) <= set(every) and base == pii.base_spans(t)
        assert all(pii.plausible(k, t[a:b]) for k, a, b in every if (k, a, b) not in base)
    assert pii.all_spans(texts[-2:], tagger) == [([], []), ([], [])]
    assert pii.redact("mail a@b.c now", [(0, 5, 10)]) == "mail [email] now"


def test_few_passages_reach_the_driver(spark):
    same = spark.range(3000).selectExpr("id as doc_id", "'a b c d e f g' as text")
    assert pii.passages_of(same) == ["a b c d e f g"]
    assert pii.passages_of(same.selectExpr("doc_id", "concat(text, ' 1') as text")) == []
    long = spark.createDataFrame([("x y " * 300_000,)], "text string")
    assert [len(p) for p in pii.passages_of(long)] == [pii.PASSAGE]


# -- 10 encoding ------------------------------------------------------------------------------------
@pytest.fixture(scope="module")
def coder():
    return bpe.coder()


def test_encoding_equals_the_library(coder, documents):
    import public_tokenizers
    import tiktoken

    own = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=coder.ranks, special_tokens={})
    texts = [r["text"] for r in documents.collect()] + ["", " \n\n  a", "a" * 3000, "日本語テスト" * 30, "I'll we've \t x", "<|endoftext|>"]
    for t in texts:
        ids = coder.encode(t)
        assert ids == own.encode_ordinary(t) and coder.decode(ids) == t.encode()
        n, digest, back = coder.digest(t)
        assert (n, digest, back) == (len(ids), sha(" ".join(map(str, ids))), sha(t))


def test_prefix_tables_grow_and_change(coder):
    rng = np.random.default_rng(1)
    bits = ["th", "er", "ing", "é", "ab", "zz", " ", "q"]
    for _ in range(150):
        text = "".join(rng.choice(bits, rng.integers(1, 60))).encode()
        t = bpe.PrefixTable(coder, text[: len(text) // 2]).append(text[len(text) // 2 :])
        assert t.last == bpe.PrefixTable(coder, text).last
        a = int(rng.integers(0, len(text) + 1))
        b = int(rng.integers(a, len(text) + 1))
        by = b"xyztheing"[: rng.integers(0, 9)]
        assert t.replace(a, b, by).last == bpe.PrefixTable(coder, text[:a] + by + text[b:]).last
