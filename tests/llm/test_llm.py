"""The corpus operators against brute force, exact round trips and edge cases."""

import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from curvebalance.llm import common as C, jaccard_join, language_id, line_dedup, mixing, packing, registry, token_store, tokens, url_filter, vector_search, warc, webp

BYTES, RANKS, WORDS = tokens.vocabulary("byte_bpe_50k.json"), tokens.vocabulary("byte_bpe_50k.tiktoken"), tokens.vocabulary("word_bpe_49k.json")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
LOWER = str.maketrans({chr(i): chr(i + 32) for i in range(65, 91)})


def docs(spark, texts, langs=None, sources=None):
    rows = [(i, t, (langs or ["en"] * len(texts))[i], (sources or ["s"] * len(texts))[i], len(t) if t is not None else None) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, SCHEMA)


def sentence(r, n):
    return " ".join("".join(r.choice("abcdefghij") for _ in range(r.randint(2, 7))) for _ in range(n))


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in any column, empty and long texts, ties and repeated rows, special strings."""
    rows = [(1, None, None, None, None), (2, "", "en", "a", 0), (3, "  \n\t ", "en", None, 5), (4, "word " * 5000, "en", "a", 25000), (5, "Same text here, twice and more.", "en", "a", 31), (5, "Same text here, twice and more.", "en", "a", 31), (6, "Same text here, twice and more.", None, "b", 31), (None, "no id at all here", "en", "a", 17), (7, "<|endoftext|> a<|startoftext|>b é́   日本語 ﬁ İ", "fr", "b", 30), (8, "12 34 ...", "en", "b", 9)]
    return spark.createDataFrame(rows, SCHEMA).withColumn("order", F.lit(1)).withColumn("epoch", F.lit("x"))


# ---- similarity join ----


def brute_components(texts, num=80, den=100):
    sets = {}
    for i, t in texts.items():
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOWER))
        sets[i] = {tuple(w[j : j + 5]) for j in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} - {()}
    up = {i: i for i in sets}

    def find(a):
        while up[a] != a:
            a = up[a]
        return a

    ids = sorted(sets)
    for x, i in enumerate(ids):
        for j in ids[x + 1 :]:
            a, b = sets[i], sets[j]
            if a and b and den * len(a & b) >= num * len(a | b):
                p, q = find(i), find(j)
                up[max(p, q)] = min(p, q)
    return {i: (len(sets[i]), find(i)) for i in sets}


def test_jaccard_join_equals_brute_force(spark):
    r = random.Random(7)
    texts = []
    for n in (3, 6, 8, 12, 20, 40, 90, 200, 400):
        base = sentence(r, n).split()
        for k in range(7):
            w = list(base)
            for _ in range(k * max(1, n // 60)):
                w[r.randrange(len(w))] = sentence(r, 1)
            texts.append(" ".join(w) if k % 2 else " ".join(w).upper())
    texts += [None, "", "a b c", "A  b\tc", "a b c d", sentence(r, 50)]
    r.shuffle(texts)
    got = {x["doc_id"]: (x["n_shingles"], x["component_id"]) for x in jaccard_join.near_duplicates(docs(spark, texts)).collect()}
    assert got == brute_components(dict(enumerate(texts)))


def test_jaccard_join_resolves_large_chains(spark, monkeypatch):
    """Copies that resemble their neighbours only: no first member reaches all, blocks are tiny, and no link may be lost."""
    monkeypatch.setattr(jaccard_join, "BLOCK_ROWS", 5)
    r = random.Random(1)
    w = sentence(r, 60).split()
    texts = []
    for k in range(30):
        texts.append(" ".join(w))
        w[(7 * k) % 60] = sentence(r, 1)
    got = {x["doc_id"]: (x["n_shingles"], x["component_id"]) for x in jaccard_join.near_duplicates(docs(spark, texts)).collect()}
    assert got == brute_components(dict(enumerate(texts)))


def test_sketch_keys_meet_whenever_sets_may_link():
    plan, r = jaccard_join.Plan(80, 100), np.random.default_rng(0)
    for n in (1, 2, 5, 9, 17, 33, 64, 65, 130, 600):
        for _ in range(20):
            a = np.unique(r.integers(0, 2**63, n).astype(np.uint64))
            d = plan.apart(len(a), len(a))
            keep = r.permutation(a)[d // 2 :]
            b = np.unique(np.concatenate((keep, r.integers(0, 2**63, d - d // 2).astype(np.uint64))))
            if plan.linked(a, b):
                assert np.intersect1d(plan.keys(a), plan.keys(b)).size
                assert plan.near(len(a), jaccard_join.folded(a), len(b), jaccard_join.folded(b))


def test_jaccard_join_edges(spark, odd):
    got = jaccard_join.near_duplicates(odd).collect()
    assert len(got) == odd.count()
    by = Counter((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got)
    assert by[1, 0, 1] == by[2, 0, 2] == by[3, 0, 3] == 1 and by[5, 2, 5] == 2 and by[6, 2, 5] == 1 and by[None, 1, None] == 1
    assert jaccard_join.near_duplicates(odd.where("doc_id < 0")).count() == 0
    kept = jaccard_join.keep_one(odd)
    assert kept.columns == odd.columns and sorted(r["doc_id"] for r in kept.where("doc_id is not null").collect()) == [1, 2, 3, 4, 5, 5, 7, 8]


def test_components_equal_union_find(spark):
    r = random.Random(3)
    e = [(r.randrange(200), r.randrange(200)) for _ in range(150)] + [(i, i + 1) for i in range(300, 340)]
    up = list(range(400))

    def find(a):
        while up[a] != a:
            a = up[a]
        return a

    for a, b in e:
        p, q = find(a), find(b)
        up[max(p, q)] = min(p, q)
    got = {x["node"]: x["comp"] for x in C.components(spark.createDataFrame(e, "a long, b long")).collect()}
    assert got == {n: find(n) for a, b in e if a != b for n in (a, b)}


# ---- packing ----


def test_packing_places_everything_once(spark, odd):
    k = tokens.library(BYTES)
    got = packing.pack_documents(odd, BYTES, RANKS, keep_ids=True).collect()
    by = Counter()
    for r in got:
        assert zlib.crc32(r["ids"]) == r["ids_crc32"] and len(r["ids"]) == 4 * r["length"] <= 4 * 2048
        by[r["doc_id"]] += r["length"]
    for r in odd.collect():
        if r["doc_id"] not in (None, 5):
            assert by[r["doc_id"]] == len(k.encode(r["text"] or "", add_special_tokens=False).ids) + 1
    seqs = {}
    for r in sorted(got, key=lambda r: r["offset"]):
        assert seqs.get(r["sequence_id"], 0) == r["offset"]
        seqs[r["sequence_id"]] = r["offset"] + r["length"]
    assert max(seqs.values()) <= 2048
    whole = packing.sequences(packing.pack_documents(odd, BYTES, RANKS, keep_ids=True)).collect()
    assert {r["sequence_id"]: len(r["ids"]) // 4 for r in whole} == seqs
    assert packing.pack_documents(odd.where("doc_id < 0"), BYTES, RANKS).count() == 0


@pytest.mark.parametrize("seed", range(6))
def test_bins_are_few(seed):
    r = np.random.default_rng(seed)
    cap = 100
    items = np.concatenate((r.integers(1, 101, 300), r.integers(30, 60, 200 * (seed % 3))))
    counts = Counter(items.tolist())
    runs, bins = packing.plan_bins(counts, cap)
    used = Counter()
    runs.sort()
    for i, (n, low, seq, off) in enumerate(runs):
        high = runs[i + 1][1] if i + 1 < len(runs) and runs[i + 1][0] == n else counts[n]
        for k in range(high - low):
            used[seq + k] += n
            assert off + n <= cap
    assert sum(used.values()) == items.sum() and max(used.values()) <= cap and len(used) == bins
    gaps: list[int] = []  # plain best-fit decreasing
    for n in sorted(items.tolist(), reverse=True):
        fit = min((g for g in gaps if g >= n), default=None)
        if fit is None:
            gaps.append(cap - n)
        else:
            gaps[gaps.index(fit)] -= n
    assert -(-items.sum() // cap) <= bins <= len(gaps)


# ---- lines ----


def brute_lines(texts, least=4, near=10):
    rows = [(d, n, line_dedup.words_of(x)) for d, t in sorted(texts.items()) for n, x in enumerate(t.split("\n"))]
    rows = [r for r in rows if len(r[2]) >= least]
    gone = set()
    for i, (d, n, w) in enumerate(rows):
        for _, _, v in rows[:i]:
            if w == v or len(w) >= near and len(v) >= near and line_dedup.within_one(w, v):
                gone.add((d, n))
                break
    return gone


def test_line_dedup_equals_brute_force(spark):
    r = random.Random(2)
    base = [sentence(r, n) for n in (3, 4, 9, 10, 11, 14, 25, 60)]
    texts = {}
    for d in range(40):
        lines = []
        for _ in range(5):
            w = r.choice(base).split()
            for _ in range(r.randrange(3)):
                k, i = r.randrange(3), r.randrange(len(w))
                w[i : i + (k != 0)] = [sentence(r, 1)] if k != 1 else []
                w = w or ["x"]
            lines.append((" " * r.randrange(3)).join([" ".join(w).upper() if r.random() < 0.2 else "  ".join(w), ""]))
        texts[d] = "\n".join(lines)
    df = docs(spark, [texts[i] for i in range(40)])
    got = {(x["doc_id"], x["line"]) for x in line_dedup.dropped_lines(df).collect()}
    assert got == brute_lines(texts) and got
    for x in line_dedup.dedup(df).collect():
        lines = texts[x["doc_id"]].split("\n")
        assert x["text"] == "\n".join(t for i, t in enumerate(lines) if (x["doc_id"], i) not in got) and x["n_lines"] == len(lines)


def test_line_dedup_edges(spark, odd):
    out = line_dedup.dedup(odd.withColumn("dropped", F.lit(0)))
    assert out.count() == odd.count() and set(odd.columns) <= set(out.columns)
    by = {r["doc_id"]: r["text"] for r in out.collect()}
    assert by[1] is None and by[5].startswith("Same") and by[6] == "" and by[None] == "no id at all here"
    assert line_dedup.dedup(odd.where("doc_id < 0")).count() == 0


def test_line_dedup_has_no_floor_in_the_queries(spark, tmp_path):
    corpus_pipeline = pytest.importorskip("corpus_pipeline")
    r = random.Random(5)
    short = ["Yes", "no more", "one two three", "a b c d", "x", "", " \t", "Über uns"]
    near = [sentence(r, n) for n in (8, 9, 10, 11)]
    texts = {d: "\n".join(r.choice(short + near + [f"only {d}"]).upper() if r.random() < 0.3 else r.choice(short + near) for _ in range(6)) for d in range(30)}
    df = docs(spark, [texts[i] for i in range(30)])
    df.write.parquet(f"{tmp_path}/documents.parquet")
    gone = brute_lines(texts, least=1)
    assert any(len(line_dedup.words_of(texts[d].split("\n")[n])) == 1 for d, n in gone)
    got = {x["doc_id"]: x["text"] for x in registry.QUERIES["op3_line_dedup"](spark, str(tmp_path)).collect()}
    want = {d: "\n".join(x for i, x in enumerate(t.split("\n")) if (d, i) not in gone) for d, t in texts.items()}
    assert got == want
    got = {x["doc_id"]: x["text"] for x in corpus_pipeline.lines(spark, df, "").collect()}
    assert got == {d: t for d, t in want.items() if t.strip() or t == texts[d]}


# ---- token store ----


def test_token_store_round_trip(spark, odd):
    r = random.Random(4)
    long_ = sentence(r, 3000)
    more = spark.createDataFrame([(20, long_, None, None, 0), (21, "start " + long_, None, None, 0), (22, long_ + " end", None, None, 0)], SCHEMA)
    df = odd.select(*more.columns).unionByName(more)
    path = C.new_path(spark, "test-store")
    token_store.write(df, path, WORDS)
    got = token_store.digests(token_store.read(spark, path)).join(spark.read.parquet(f"{path}/index").select("doc_id", "copy", "start"), ["doc_id", "copy"]).collect()
    k, start, want = tokens.library(WORDS), 0, []
    for d, t in sorted((x["doc_id"], x["text"]) for x in df.where("doc_id is not null").fillna("", ["text"]).collect()):
        a = np.array(k.encode(t, add_special_tokens=False).ids + [1], "<u4")
        want.append((d, start, len(a), zlib.crc32(a.tobytes())))
        start += len(a)
    assert sorted((x["doc_id"], x["start"], x["n_tokens"], x["ids_crc32"]) for x in got) == want
    packs = spark.read.parquet(f"{path}/packs")
    chunks = packs.select(F.explode("recipe").alias("c")).where("c.kept").select("c.digest")
    assert chunks.count() == chunks.distinct().count() and packs.where("absent > 0").count() >= 3
    token_store.write(df.where("doc_id < -5"), C.new_path(spark, "test-store"), WORDS)


def test_token_store_query_equals_the_library(spark, sf, tmp_path, odd):
    """Over a whole table, with null and repeated ids beside it: ids, places in ascending doc_id order and digests as the library gives them."""
    df = spark.read.parquet(sf.replace("0.001", "0.01") + "/documents.parquet")
    extra = odd.select(*df.columns).unionByName(odd.select(*df.columns).where("doc_id is null or doc_id = 5").withColumn("text", F.lit("another text")))
    df = df.withColumn("doc_id", F.col("doc_id") + 100).unionByName(extra)
    df.write.parquet(f"{tmp_path}/documents.parquet")
    got = sorted(registry.QUERIES["op4_token_store"](spark, str(tmp_path)).collect(), key=lambda r: r["start"])
    lib, want = tokens.library(WORDS), Counter()
    for r in df.select("doc_id", "text").collect():
        a = np.array(lib.encode(r["text"] or "", add_special_tokens=False).ids + [1], "<u4")
        want[r["doc_id"], len(a), zlib.crc32(a.tobytes())] += 1
    assert Counter((r["doc_id"], r["n_tokens"], r["ids_crc32"]) for r in got) == want
    assert [r["start"] for r in got] == np.cumsum([0] + [r["n_tokens"] for r in got])[:-1].tolist()
    ids = [r["doc_id"] for r in got]
    assert ids == sorted(ids, key=lambda i: (i is None, i))


@pytest.mark.parametrize("what", ["manifest", "index", "lost", "doubled", "bytes"])
def test_token_store_finds_what_was_altered(spark, what):
    r = random.Random(14)
    df = docs(spark, [sentence(r, 300) for _ in range(40)])
    path = C.new_path(spark, "test-store")
    token_store.write(df, path, WORDS)
    assert token_store.read(spark, path).count() == 40
    name = {"manifest": "manifest", "index": "index"}.get(what, "packs")
    rows = spark.read.parquet(f"{path}/{name}")
    if what == "manifest":
        rows = rows.withColumn("root", F.expr("unhex(md5(root))"))
    elif what == "index":
        rows = rows.withColumn("start", F.when(F.col("doc_id") == 7, F.col("start") + 1).otherwise(F.col("start")))
    elif what == "bytes":
        rows = rows.withColumn("bytes", F.when(F.col("doc_id") == 7, F.expr("reverse(bytes)")).otherwise(F.col("bytes")))
    else:
        rows = rows.where("doc_id != 7") if what == "lost" else rows.unionByName(rows.where("doc_id = 7"))
    rows.write.parquet(f"{path}/altered")
    spark.read.parquet(f"{path}/altered").write.mode("overwrite").parquet(f"{path}/{name}")
    with pytest.raises(Exception, match="differ"):
        token_store.read(spark, path).collect()


def test_token_store_fetches_chunks_by_digest(spark):
    r = random.Random(15)
    path = C.new_path(spark, "test-store")
    token_store.write(docs(spark, [sentence(r, 900) for _ in range(6)]), path, WORDS)
    names = spark.read.parquet(f"{path}/packs").select(F.explode("recipe.digest").alias("digest"))
    got = token_store.fetch(spark, path, names).collect()
    assert len(got) == names.distinct().count() and all(token_store.digest(bytes(x["bytes"])) == bytes(x["digest"]) for x in got)


def test_chunks_of_equal_passages_are_equal():
    r = np.random.default_rng(0)
    a, b = r.integers(0, 49000, 20000).astype(np.uint16), r.integers(0, 49000, 300).astype(np.uint16)
    def parts(x):
        e = token_store.cuts(x)
        assert e[-1] == len(x) and max(np.diff([0, *e])) <= token_store.MOST
        return {x[i:j].tobytes() for i, j in zip([0, *e], e)}
    assert len(parts(a) & parts(np.concatenate((b, a)))) > 0.8 * len(parts(a))


@pytest.mark.parametrize("kind", ["bytes", "words"])
def test_fast_ids_equal_the_library(kind):
    r = random.Random(5)
    letters = "ab'sStredvml .,;!?0123456789éüßñÇœ€–“”\n\t<|>Ŝĳ-_/()[]{}#$%^&* 日́İ"
    texts = ["".join(r.choice(letters) for _ in range(r.randrange(80))) for _ in range(800)] + ["<|endoftext|>", "it's don't", ""]
    lib = tokens.library(BYTES if kind == "bytes" else WORDS)
    if kind == "bytes":
        got = [a.tolist() for a in tokens.ByteBpe(BYTES, RANKS).encode(texts)]
    else:
        got = [np.frombuffer(b, "<u2").tolist() for b in tokens.WordBpe(WORDS).encode(texts)]
    assert got == [lib.encode(t, add_special_tokens=False).ids for t in texts]


# ---- WARC ----


def test_warc_round_trip(spark):
    rows = [(3, "http://a/x\r\ny", "<p>one</p>"), (1, None, "<p>one</p>"), (2, "http://b", None), (5, "http://c", ""), (4, "u", "é" * 5), (None, "http://d", "<p>one</p>"), (4, "u", "é" * 5), (9, "z", "<p>" + "x" * 3_000_000)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("refers", F.lit(1))
    folder = C.new_path(spark, "test-warc")
    index = warc.write(pages, folder)
    got = sorted(((r["page_id"], r["record_type"], r["refers_to"], r["payload_bytes"], r["payload"]) for r in warc.read(index, folder, True).collect()), key=repr)
    want = [(3, "revisit", 1, 10, None), (1, "response", None, 10, b"<p>one</p>"), (2, "response", None, 0, b""), (5, "revisit", 2, 0, None), (4, "response", None, 10, ("é" * 5).encode()), (4, "response", None, 10, ("é" * 5).encode()), (None, "response", None, 10, b"<p>one</p>"), (9, "response", None, 3_000_003, b"<p>" + b"x" * 3_000_000)]
    assert [tuple(bytes(v) if isinstance(v, bytearray) else v for v in g) for g in got] == sorted(want, key=repr)
    head, block = warc.lookup(spark, index, folder, 4)[0]
    assert head["WARC-Record-ID"] == "<urn:x-page:4>" and block.endswith(("é" * 5).encode())
    assert warc.write(pages.where("page_id < 0"), C.new_path(spark, "test-warc")).count() == 0
    small = warc.write(pages, C.new_path(spark, "test-warc"), least_bytes=11)
    assert small.count() == len(rows)


# ---- URLs ----

RULES = [url_filter.Rule.parse(x) for x in ("allow com/", "block example.com/en/", "allow www.example.com/en/", "block net/es/", "block net/fr/")]


def brute_url(u):
    host = path = ""
    if u and "://" in u:
        m = re.match(r"([^/?#]*)([^?#]*)", u.split("://", 1)[1], re.S)
        host, path = m[1].translate(LOWER), m[2]
    fits = [r for r in RULES if (host == r.host or host.endswith("." + r.host)) and path.startswith(r.path)]
    best = max(fits, key=lambda r: len(r.name), default=None)
    return host, path, best.name if best else None, best.action if best else "allow"


@pytest.mark.parametrize("limit", [1 << 20, 0])
def test_url_rules_and_cascade(spark, limit):
    r = random.Random(6)
    urls = [None, "", "no scheme", "://", "http://", "http://com", "http://COM/", "http://x.com?q=://y", "http://example.com/en/\nz", "http://notexample.com/en/1", "http://net/es/"]
    for _ in range(400):
        urls.append(f"http{r.choice(['', 's'])}://{r.choice(['', 'www.', 'a.b.', 'WWW.'])}{r.choice(['example', 'Other', 'x'])}.{r.choice(['com', 'net', 'org'])}{r.choice(['', '/'])}{r.choice(['en/', 'es/', 'fr/', 'en', ''])}{r.randrange(60)}{r.choice(['', '?p=1', '#t', '#a?b'])}")
    df = spark.createDataFrame([(i if i % 50 else None, u) for i, u in enumerate(urls)], "page_id long, url string").withColumn("host", F.lit(0))
    got = url_filter.judge(df, RULES, shard_keys=40, broadcast_bytes=limit).collect()
    want = Counter((i if i % 50 else None, *brute_url(u)) for i, u in enumerate(urls))
    assert Counter((x["page_id"], x["host"], x["path"], x["rule"], x["verdict"]) for x in got) == want
    assert all(x["listed"] == (brute_url(urls[x["page_id"]])[3] == "block") for x in got if x["page_id"] is not None)
    # the cascade gives the verdict: with nothing listed, nothing is blocked
    built = url_filter.build
    url_filter.build = lambda keys, shards: built(keys.withColumn("listed", F.lit(False)), shards)
    try:
        assert {x["verdict"] for x in url_filter.judge(df, RULES, shard_keys=40, broadcast_bytes=limit).collect()} == {"allow"}
    finally:
        url_filter.build = built
    assert url_filter.judge(df.where("page_id < 0"), RULES).count() == 0


def test_cascade_is_exact():
    r = np.random.default_rng(0)
    keys = np.unique(r.integers(0, 2**63, 20000).astype(np.uint64))
    for n in (0, 1, 300, 9000, len(keys)):
        c = url_filter.Cascade.build(keys[:n], keys[n:])
        assert (c.has(keys) == (np.arange(len(keys)) < n)).all()


# ---- WebP ----


@pytest.mark.parametrize("transforms", [(), (2,), (0,), (1,), (0, 1), (2, 0, 1), (3,), (3, 0)])
@pytest.mark.parametrize("cache,references,meta", [(0, False, 0), (5, True, 0), (11, True, 2), (1, False, 3)])
def test_webp_decodes_all_of_the_format(transforms, cache, references, meta):
    r = np.random.default_rng(len(transforms) + cache)
    for h, w, colours in ((1, 1, 1), (7, 13, 2), (13, 7, 4), (20, 9, 16), (11, 30, 200)):
        a = r.integers(0, 256, (colours, 4)).astype(np.uint8)[r.integers(0, colours, (h, w))]
        if 3 not in transforms and colours == 200:
            a = r.integers(0, 256, (h, w, 4)).astype(np.uint8)
        assert (webp.decode(webp.encode(a, transforms, cache, references, meta)) == a).all()


def test_webp_fixed_file():
    # a 1 x 1 opaque red image, every code of one symbol, written out by hand
    w = webp.Writer()
    for v, n in ((0x2F, 8), (0, 14), (0, 14), (0, 1), (0, 3), (0, 1), (0, 1), (0, 1)):
        w.put(v, n)
    for s in (0, 255, 0, 255):
        for v, n in ((1, 1), (0, 1), (1, 1), (s, 8)):
            w.put(v, n)
    for v, n in ((1, 1), (0, 1), (0, 1), (0, 1)):
        w.put(v, n)
    assert webp.decode(webp.container(w.bytes())).tolist() == [[[255, 0, 0, 255]]]
    with pytest.raises(ValueError):
        webp.decode(b"RIFF....WEBPVP8 ")


def test_webp_images_side_by_side_are_as_one_by_one():
    r = np.random.default_rng(3)
    files = []
    for h, w, colours in ((1, 1, 1), (9, 13, 2), (40, 64, 30), (64, 64, 256), (3, 200, 5)):
        grey = r.integers(0, colours, (h, w)).astype(np.uint8)
        grey[h // 2 :] = np.resize(grey.ravel()[: max(1, h * w // 7)], grey[h // 2 :].shape)
        rgba = np.stack([grey, grey, grey, np.full_like(grey, 255)], 2)
        files += [webp.encode(rgba, (2,)), webp.encode(rgba, (2,), references=False), webp.encode(rgba, (), 4), webp.encode(rgba, (2, 0), 0, True, 2)]
        if colours <= 30:
            files += [webp.encode(rgba, (3,)), webp.encode(r.integers(0, 256, (h, w, 4)).astype(np.uint8), (1,))]
    for f, (p, w, h) in zip(files, webp.decode_many(files)):
        assert (webp._samples(p, w, h) == webp.decode(f)).all()
    assert webp.decode_many([]) == []


@pytest.mark.parametrize("n", (64, 128, 4096, 4160, 12352))
def test_webp_payloads_use_references_and_codes_of_their_own(n, monkeypatch):
    monkeypatch.setattr(webp, "LANES", 3)
    r = np.random.default_rng(n)
    words = [bytes(r.integers(97, 123, k).astype(np.uint8)) for k in r.integers(1, 12, 300)]
    prose = b" ".join(words[k] for k in r.integers(0, 300, n))[:n]
    payloads = [bytes(n), prose, prose, r.integers(0, 256, n).astype(np.uint8).tobytes(), (b"abc" * n)[:n], bytes(range(256)) * (n // 256) + bytes(n % 256)]
    media = webp.store(payloads)
    assert media == [webp.store([x])[0] for x in payloads] and webp.store([]) == []
    assert [x.tobytes() for x in webp.load(media)] == payloads and media[1] == media[2]
    assert all(len(m) == -(-n // webp.SEGMENT) for m in media)
    for m, x in zip(media, payloads):
        a = np.concatenate([webp.decode(f).reshape(-1, 4) for f in m])
        assert a[:, 1].tobytes() == x and (a[:, 0] == a[:, 1]).all() and (a[:, 2] == a[:, 1]).all() and (a[:, 3] == 255).all()
    if n >= 4096:
        a = np.frombuffer(prose, np.uint8)[:4096]
        start, length, d = webp._repeats(a, np.zeros(4096, np.int64), np.zeros(1, np.int64))
        assert len(start) and (length >= webp.LEAST).all() and (start[1:] >= (start + length)[:-1]).all()
        assert all((a[p : p + k] == a[p - q : p - q + k]).all() for p, k, q in zip(start, length, d))
        assert sum(map(len, media[1])) < 0.75 * n


def test_webp_payloads_get_the_transforms_and_groups_that_suit_them():
    r = np.random.default_rng(5)
    halves = np.concatenate([r.integers(0, 16, 2048), r.integers(0, 16, 2048) * 13 + 48]).astype(np.uint8)
    walk = np.cumsum(r.integers(0, 3, 4096)).astype(np.uint8)
    down = np.cumsum(r.integers(0, 3, (64, 64)), 0).astype(np.uint8).ravel()
    few = [np.where(r.random(4096) < 0.1, 200, 3).astype(np.uint8), np.where(r.random(4096) < 0.1, r.integers(7, 11, 4096), 7).astype(np.uint8), np.where(np.arange(4096) % 2, 90, r.integers(91, 106, 4096)).astype(np.uint8)]
    prose = np.frombuffer(" ".join(sentence(random.Random(4), 900).split())[:4096].encode(), np.uint8)
    expected = {"plain": ([2], 1, prose), "left": ([2, 0], 1, walk), "top": ([2, 0], 1, down), "groups": ([2], 2, halves)} | {f"palette {k}": ([3], 1, a) for k, a in enumerate(few)}
    for (name, (kinds, groups, a)), f in zip(expected.items(), webp.encode_grey([x[2] for x in expected.values()])):
        b, width, height, todo, across = webp._open(f)
        assert [t[0] for t in todo] == kinds and len(webp._read_codes(b, across, height, True)[3]) == groups, name
        q = webp.decode(f)
        assert (q[:, :, :3].reshape(-1, 3) == a[:, None]).all() and (q[:, :, 3] == 255).all() and (webp.load([[f]])[0] == a).all(), name
        assert len(f) < 0.7 * len(a) or name == "groups", name
    some = [r.integers(0, c, 64 * h).astype(np.uint8) * s for c in (1, 2, 5, 16, 17, 256) for h in (1, 2, 15, 16, 17, 64) for s in (1, 15)]
    assert all((x == y).all() for x, y in zip(some, webp.load([[f] for f in webp.encode_grey(some)]), strict=True))


def test_webp_codes_are_as_short_as_can_be():
    r = np.random.default_rng(6)
    for most, size in ((12, 280), (12, 40), (7, 19)):
        counts = r.integers(1, 400, (60, size)) ** 2 // 99 * (r.random((60, size)) < r.random((60, 1)))
        n, codes = webp._huffman(counts, most)
        assert (np.where(n, 0.5**n, 0).sum(1) == 1).all() and n.max() <= most and ((n > 0) | (counts == 0)).all()
        for c, a, b in zip(counts, n, codes):
            if (c > 0).sum() > 1:
                assert (a * c).sum() == (np.array(webp._lengths(c.tolist(), most)) * c).sum()
                assert [(int(x), int(y)) for x, y in zip(b, a) if y] == [x for x in webp._codes(a.tolist()) if x[1]]
    assert webp._huffman(np.array([[0, 0, 0], [5, 0, 0], [0, 0, 5]]), 12)[0].tolist() == [[1, 1, 0], [1, 1, 0], [1, 0, 1]]


def test_webp_reference_before_the_image_raises():
    w = webp.Writer()
    webp._head(w, 64, 1)
    w.put(0, 3)
    codes = webp._put_code(w, [int(s in (0, 256 + 4)) for s in range(280)])
    for s in (0, 0, 255):
        w.put(0b101, 3)
        w.put(s, 8)
    webp._put_code(w, [1] + [0] * 39)
    w.put(*codes[256 + 4])
    f = webp.container(w.bytes() + bytes(8))
    with pytest.raises(ValueError):
        webp.decode(f)
    with pytest.raises(ValueError):
        webp.decode_many([f])


def test_webp_columns(spark, odd):
    import hashlib

    got = webp.decoded(C.stash(webp.media_table(odd), "media"), True).collect()
    text = Counter((r["doc_id"], r["text"] or "") for r in odd.collect())
    assert len(got) == odd.count() and sum(text.values()) == len(got)
    by = dict((d, t) for d, t in text)
    for r in got:
        p = webp.payload(by[r["doc_id"]])
        assert bytes(r["samples"]) == p and r["payload_sha256"] == hashlib.sha256(p).hexdigest() and r["tail_crc32"] == zlib.crc32(p[-64:]) and r["n_bytes"] == len(by[r["doc_id"]].encode())
    assert webp.decoded(webp.media_table(odd.where("doc_id < 0"))).count() == 0


# ---- vectors ----


def test_vector_search_finds_neighbours(spark):
    r = np.random.default_rng(1)
    x = r.normal(size=(1500, 8)).astype(np.float32)
    x[700:760] = x[0]  # a common vector
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(5000, None), (5020, [0.0] * 8), (5040, [float("nan")] + [1.0] * 7), (5060, [1.0, None] * 4), (5080, [1.0] * 3), (None, [1.0] * 8), (5100, [float("inf")] + [1.0] * 7)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("score", F.lit("x"))
    got = vector_search.search(df, "embedding", "vec_id % 20 = 0", centroids=16, candidates=700, share=0).collect()
    z = x.astype(float)
    hits = total = 0
    for q in range(0, 1500, 20):
        s = z @ z[q]
        s[q] = -np.inf
        own = sorted((t for t in got if t["query_id"] == q), key=lambda t: t["rank"])
        assert [t["rank"] for t in own] == list(range(1, 21))
        assert own == sorted(own, key=lambda t: (-t["score"], t["vec_id"])) and all(abs(t["score"] - s[t["vec_id"]]) < 1e-12 for t in own)
        hits += len({t["vec_id"] for t in own} & set(np.lexsort((np.arange(1500), -s))[:20].tolist()))
        total += 20
    assert hits / total >= 0.9 and not any(t["query_id"] >= 5000 or t["vec_id"] >= 5000 for t in got)
    few = vector_search.search(df.where("vec_id < 10"), "embedding", "vec_id % 20 = 0").collect()
    assert [t["rank"] for t in sorted(few, key=lambda t: t["rank"])] == list(range(1, 10))
    assert vector_search.search(df.where("vec_id < 0"), "embedding", "vec_id % 20 = 0").count() == 0


def test_defaults_reach_their_recall(spark, sf):
    e = spark.read.parquet(sf.replace("0.001", "0.1") + "/embeddings.parquet")
    true = {(x["query_id"], x["vec_id"]) for x in vector_search.exact(e, "embedding", "vec_id % 20 = 0").collect()}
    got = {(x["query_id"], x["vec_id"]) for x in vector_search.search(e, "embedding", "vec_id % 20 = 0").collect()}
    assert len(true & got) >= 0.9 * len(true)
    r = np.random.default_rng(4)
    centres = r.normal(size=(40, 16)) * 3
    x = centres[r.integers(0, 40, 6000)] + r.normal(size=(6000, 16))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    true = {(x["query_id"], x["vec_id"]) for x in vector_search.exact(df, "embedding", "vec_id % 20 = 0").collect()}
    got = {(x["query_id"], x["vec_id"]) for x in vector_search.search(df, "embedding", "vec_id % 20 = 0", candidates=0, share=0.15).collect()}
    assert len(true & got) >= 0.9 * len(true)


def test_equal_vectors_tie_by_id_and_ids_ask_once(spark, monkeypatch):
    monkeypatch.setattr(vector_search, "ASKING", 3)
    monkeypatch.setattr(vector_search, "BLOCK", 50)
    r = np.random.default_rng(5)
    x = r.normal(size=(10, 33))[r.integers(0, 10, 400)]
    rows = [(int(i), v.tolist()) for i, v in zip(r.permutation(400), x)] + [(0, x[3].tolist())]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = vector_search.search(df, "embedding", "vec_id % 20 = 0", share=1.0).collect()
    for q in range(0, 400, 20):
        own = sorted((t for t in got if t["query_id"] == q), key=lambda t: t["rank"])
        asks = min(v for i, v in rows if i == q)
        s = [(-float(sum(a * b for a, b in zip(asks, v))), i) for i, v in rows if i != q]
        assert [t["vec_id"] for t in own] == [i for _, i in sorted(s)[:20]]


def test_walk_goes_by_falling_sums():
    r = np.random.default_rng(2)
    a, b = r.normal(size=9), r.normal(size=7)
    cells = vector_search.walk(a, b, np.ones((9, 7), int), 30)
    sums = [a[i] + b[j] for i, j in cells]
    assert sums == sorted(sums, reverse=True) and len(cells) == 30
    assert np.allclose(sums, sorted((a[:, None] + b).ravel(), reverse=True)[:30])


# ---- mixing ----


def test_mixture_meets_its_quota(spark):
    r = random.Random(8)
    texts = [sentence(r, r.randint(1, 30)) for _ in range(400)]
    df = docs(spark, texts, sources=["big" if i % 10 < 7 else f"s{i % 3}" if i % 10 < 9 else None for i in range(400)])
    size = df.withColumn("tokens", mixing.words(F.col("text"))).cache()
    src = mixing.shares(size).cache()
    n = {x["source"]: x["tokens"] for x in src.collect()}
    p = np.array(list(n.values())) / sum(n.values())
    e = mixing.exponent(src, entropy=0.95)
    w = p**e / (p**e).sum()
    assert abs(-(w * np.log(w)).sum() - 0.95 * np.log(len(p))) < 1e-6
    limited = mixing.exponent(src, entropy=0.999, most_epochs=1.5)
    v = p**limited / (p**limited).sum() / p
    assert v.max() / v.min() <= 1.5 + 1e-6 and limited > mixing.exponent(src, entropy=0.999)
    out = mixing.mix(df, entropy=0.95, most_epochs=None).collect()
    plan = {x["source"]: x for x in mixing.weights(src, e).collect()}
    used, times = Counter(), Counter()
    for x in out:
        used[x["source"]] += x["tokens"]
        times[x["doc_id"]] += 1
    most = max(x["tokens"] for x in size.collect())
    assert len(times) == 400
    for s, x in plan.items():
        assert x["quota"] - 2 * most <= used[s] <= x["quota"]
        mine = [times[y["doc_id"]] for y in size.collect() if y["source"] == s]
        assert max(mine) - min(mine) <= 1 and min(mine) >= x["epochs"]
    assert sorted(map(tuple, (list(x.asDict().values()) for x in out)), key=repr) == sorted(map(tuple, (list(x.asDict().values()) for x in mixing.mix(df.repartition(7), entropy=0.95, most_epochs=None).collect())), key=repr)


def test_mixture_equals_brute_force(spark):
    """Rows, epochs, turns and places against plain loops; hashes alone are Spark's."""
    r = random.Random(18)
    df = docs(spark, [sentence(r, r.randint(1, 30)) for _ in range(300)], sources=[None if i % 9 == 0 else "a" if i % 3 else "b" for i in range(300)])
    mixing_rows = mixing.mix(df, entropy=0.97, most_epochs=1.8, seed=3)
    hashed = {x["doc_id"]: x for x in df.select("doc_id", "source", "text", F.xxhash64(F.lit(3), "doc_id", "text").alias("hash")).collect()}
    size = {i: len(re.findall(r"[^\x20\x09-\x0D]+", x["text"])) for i, x in hashed.items()}
    by = {}
    for i, x in hashed.items():
        by.setdefault(x["source"], []).append(i)
    n = {s: sum(size[i] for i in ids) for s, ids in by.items()}
    p = {s: v / sum(n.values()) for s, v in n.items()}

    def entropy(e):
        w = [x**e for x in p.values()]
        return -sum(x / sum(w) * np.log(x / sum(w)) for x in w)

    def bisect_(good):  # good at 0
        lo, hi = 0.0, 1.0
        for _ in range(60):
            mid = (lo + hi) / 2
            lo, hi = (mid, hi) if good(mid) else (lo, mid)
        return lo

    e = 1.0 if entropy(1.0) >= 0.97 * np.log(3) else bisect_(lambda e: entropy(e) >= 0.97 * np.log(3))
    spread = lambda e: max(x ** (e - 1) for x in p.values()) / min(x ** (e - 1) for x in p.values())
    if spread(e) > 1.8:
        e = 1 - np.log(1.8) / np.log(max(p.values()) / min(p.values()))
    budget = max(n[s] / n[s] ** e for s in n)
    quota = {s: round(n[s] ** e * budget) for s in n}
    got = {}
    for x in mixing_rows.collect():
        got.setdefault(x["source"], []).append(x)
    for s, ids in by.items():
        assert abs(sum(x["tokens"] for x in got[s]) - quota[s]) <= 2 * max(size[i] for i in ids)
        whole = quota[s] // n[s]
        times = Counter(x["doc_id"] for x in got[s])
        assert all(times[i] in (whole, whole + 1) for i in ids)
        assert Counter((x["doc_id"], x["epoch"]) for x in got[s] if x["epoch"] < whole) == Counter((i, k) for i in ids for k in range(whole))
        # one block here: of the last epoch, documents in hashed order while they fit
        last, left = [], quota[s] - whole * n[s]
        for i in sorted(ids, key=lambda i: (hashed[i]["hash"], i)):
            if size[i] > left:
                break
            left -= size[i]
            last.append(i)
        assert abs(len(last) - sum(x["epoch"] == whole for x in got[s])) <= 1  # a token of rounding in the quota may move one document
        assert len({(x["epoch"], x["turn"]) for x in got[s]}) == len({x["epoch"] for x in got[s]})


def test_mixture_blocks_take_turns(spark, monkeypatch):
    monkeypatch.setattr(mixing, "BLOCK_DOCS", 20)
    r = random.Random(19)
    df = docs(spark, [sentence(r, 10) for _ in range(600)], sources=["big" if i % 10 else "small" for i in range(600)])
    rows = [x for x in mixing.mix(df, entropy=0.97, most_epochs=None).collect() if x["source"] == "small"]
    orders = []
    for e in range(max(x["epoch"] for x in rows) + 1):
        orders.append([b for _, b in sorted({(x["turn"], x["block"]) for x in rows if x["epoch"] == e})])
    assert len(orders) > 1 and len({tuple(o) for o in orders}) > 1 and all(sorted(o) == sorted(orders[0]) for o in orders[:-1])
    plan = {x["source"]: x for x in mixing.weights(mixing.shares(df.withColumn("tokens", mixing.words(F.col("text")))), mixing.exponent(mixing.shares(df.withColumn("tokens", mixing.words(F.col("text")))), 0.97)).collect()}["small"]
    used, full = sum(x["tokens"] for x in rows), plan["epochs"] * plan["tokens"]
    assert full <= used <= plan["quota"] and plan["quota"] - used <= 20
    cut = [b for b in orders[-1]] if used > full else []
    assert all({x["doc_id"] for x in rows if x["epoch"] == len(orders) - 1 and x["block"] == b} == {x["doc_id"] for x in rows if x["epoch"] == 0 and x["block"] == b} for b in cut[:-1])


def test_mixing_edges(spark, odd):
    out = mixing.mix(odd)
    assert {r["doc_id"] for r in out.collect()} == {r["doc_id"] for r in odd.collect()} and out.where("source is null").count() >= 2
    assert mixing.mix(odd.where("doc_id < 0")).count() == 0


# ---- languages ----


def brute_path(m, s):
    best, n = None, s.shape[1]
    v = {g: (s[0, g], (g,)) for g in range(n)}
    for row in s[1:]:
        v = {g: max((v[h][0] - (h != g) * language_id.SWITCH + row[g], h == g, v[h][1] + (g,)) for h in range(n))[::2] for g in range(n)}
    return max(v.values())[0]


def test_language_accuracy_and_spans(spark, sf):
    df = spark.read.parquet(sf.replace("0.001", "0.01") + "/documents.parquet")
    got = language_id.identify(df).join(df.select("doc_id", "lang", "text"), "doc_id").where("held_out and lang is not null and lang_pred != 'und'").collect()
    assert np.mean([r["lang"] == r["lang_pred"] for r in got]) > 0.95 and len(got) > 100
    m = language_id.train(df.where(~language_id.held_out(F.col("doc_id"))))
    by = {}
    for r in got:
        if r["lang"] == r["lang_pred"] and len(r["text"].split()) > 60:
            by.setdefault(r["lang"], r["text"].split()[:60])
    assert len(by) >= 2
    (a, x), (b, y) = sorted(by.items())[:2]
    _, score, spans = m.label(" ".join(x + y))
    assert [s[2] for s in spans] == [a, b] and abs(spans[0][1] - 60) <= 4 and 0 < score < 1


def test_viterbi_is_optimal():
    r = np.random.default_rng(3)
    m = language_id.Model(["a", "b", "c"], np.ones((language_id.BUCKETS, 3)), {})
    for _ in range(60):
        s = r.normal(size=(r.integers(1, 12), 3)) * 40
        p = m.path(s)
        p = np.full(len(s), s.sum(0).argmax()) if p is None else p
        total = s[np.arange(len(s)), p].sum() - language_id.SWITCH * (np.diff(p) != 0).sum()
        assert abs(total - brute_path(m, s)) < 1e-9


def test_scripts_narrow_candidates(spark):
    df = docs(spark, ["привет мир как дела сегодня " * 5, "hello world how are you today " * 5] * 4, langs=["ru", "en"] * 4)
    m = language_id.train(df)
    assert m.scripts == {"cyrillic": [m.langs.index("ru")], "latin": [m.langs.index("en")]}
    assert m.label("мир")[0] == "ru" and m.label("world")[0] == "en" and m.label("123")[0] == "und"


def test_letters_of_unlearned_scripts_count_against_the_score(spark):
    df = docs(spark, ["hello world how are you today " * 5, "bonjour le monde comment allez vous " * 5] * 4, langs=["en", "fr"] * 4)
    m = language_id.train(df)
    assert m.label("hello world how are you")[:2] == ("en", 1.0)
    assert m.label("привет мир как дела")[1] == 0.0 and m.label("привет мир")[0] in m.langs
    assert abs(m.label("hello world приветмира")[1] - 0.5) < 1e-9 and m.label("hello world приветмира")[0] == "en"


def test_language_stage_keeps_mixtures_and_rejects_unlearned_scripts(spark):
    corpus_pipeline = pytest.importorskip("corpus_pipeline")
    said = {"en": "hello world how are you today my friend ", "fr": "bonjour le monde comment allez vous aujourd hui ", "de": "guten morgen die welt wie geht es ihnen heute "}
    other = "привет мир как дела сегодня "
    mixed = "".join(said[g] * 12 for g in said)  # no language has half of it
    mostly, partly = said["en"] * 2 + other * 20, said["en"] * 20 + other * 2
    texts = [said[g] * 5 for g in said] * 4 + [mixed, other * 9, mostly, partly, "123 456", "", None]
    df = docs(spark, texts, langs=["en", "fr", "de"] * 4 + [None] * 7)
    m = language_id.train(df)
    assert m.label(mixed)[1] < corpus_pipeline.LEAST_SHARE and m.judged([mixed])[0][3] == 1.0
    got = {r["doc_id"]: r["lang"] for r in corpus_pipeline.language(spark, df, "").collect()}
    at = {r["doc_id"]: r["text"] for r in df.collect()}
    assert {at[i] for i in got} == {*(said[g] * 5 for g in said), mixed, partly} and None not in got.values()
    p = {r["doc_id"]: r for r in language_id.predict(df.withColumn("learned", F.lit("own")), m).collect()}
    assert all(r["learned"] == "own" for r in p.values())


def test_language_edges(spark, odd):
    got = language_id.identify(odd.withColumn("score", F.lit(3))).collect()
    by = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in got}
    assert len(got) == odd.count() and by[1] == by[2] == by[3] == by[8] == ("und", 0.0)
    assert all(0 <= s <= 1 for _, s in by.values())
    assert language_id.identify(odd.where("doc_id < 0")).count() == 0
    assert {r["lang_pred"] for r in language_id.identify(odd.withColumn("lang", F.lit(None).cast("string"))).collect()} == {"und"}


# ---- shared parts ----


def test_exclusive_prefix(spark):
    df = spark.range(1000).select((F.col("id") * 7).alias("k"), (F.col("id") % 13).alias("v"))
    got = [r["p"] for r in C.exclusive_prefix(df, "k", "v", "p", 9).orderBy("k").collect()]
    assert got == np.concatenate(([0], np.cumsum(np.arange(1000) % 13)[:-1])).tolist()


def test_word_hashes_follow_the_rule():
    import pyarrow as pa

    texts = ["Aa  b\tc\x0bd", None, "", " x ", "é ü z"]
    data, off = C.utf8(pa.array(texts))
    h, at, _, _ = C.word_hashes(data, off)
    assert np.diff(at).tolist() == [4, 0, 0, 1, 2]
    d2, o2 = C.utf8(pa.array(["aA b c d"]))
    assert C.word_hashes(d2, o2)[0].tolist() == h[:4].tolist()


def test_pipeline_stages(spark, sf):
    corpus_pipeline = pytest.importorskip("corpus_pipeline")
    df = spark.read.parquet(f"{sf}/documents.parquet")
    names = df.columns
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = C.stash(stage(spark, df, sf), "stage")
        if i < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == names, name
            assert {r["doc_id"] for r in out.select("doc_id").collect()} <= {r["doc_id"] for r in df.select("doc_id").collect()}
        if name == "mixing":
            assert out.select("doc_id").distinct().count() == df.select("doc_id").distinct().count()
        if name == "n-gram jaccard join":
            texts = {r["doc_id"]: r["text"] for r in df.collect()}
            assert {r["doc_id"] for r in out.collect()} == {i for i, (_, c) in brute_components(texts).items() if i == c}
        if name == "line dedup":
            texts = {r["doc_id"]: r["text"] for r in df.collect()}
            gone = brute_lines({k: v or "" for k, v in texts.items()}, least=1)
            left = {d: "\n".join(x for i, x in enumerate(t.split("\n")) if (d, i) not in gone) for d, t in texts.items() if t is not None}
            want = {d: t for d, t in left.items() if t.strip() or t == texts[d]}
            assert {r["doc_id"]: r["text"] for r in out.collect()} == want
        df = out
    clash = spark.read.parquet(f"{sf}/documents.parquet").limit(40)
    for c in ("score", "lang_pred", "spans", "dropped", "n_lines", "tokens", "epoch", "block", "order", "Turn", "hash", "s0", "n", "component_id", "n_shingles"):
        clash = clash.withColumn(c, F.lit(f"own {c}"))
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, clash, sf)
        assert out.columns == clash.columns
        assert all(x[c] == f"own {c}" for x in out.collect() for c in clash.columns[5:])
    empty = spark.read.parquet(f"{sf}/documents.parquet").where("doc_id < 0")
    for _, stage in corpus_pipeline.STAGES:
        empty = stage(spark, empty, sf)
    assert empty.count() == 0
