"""Training-data operators against brute force, on small tables with every odd case."""

import hashlib
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from equiscale.llm import chat, exact_dedup, golay, graph, language, packing, passages, quality, sentencepieces, simhash, sketches, suffixes, toxicity
from equiscale.llm.queries import tokenizer_file

SF = "/root/testdata/sf0.001"
LOREM = "the quick brown fox jumps over the lazy dog while seven wizards brew very strong coffee near an old stone bridge at dawn"


def odd_texts():
    rng = random.Random(5)
    words = LOREM.split()
    long = " ".join(rng.choice(words) for _ in range(4000))
    return [None, "", " ", "a", "A", "a", LOREM, LOREM.upper(), LOREM + " again", LOREM + "\n" + LOREM, long, long + " end", "é" * 60 + "ß中😀 \x00 ▁x", "x" * 3000, "  two  spaces ", "<|endoftext|> <s>", "\n\n\n", "12 + 34!"]


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty, long and repeated texts, repeated rows, extra columns with clashing names."""
    rows = [(i, t, "en" if i % 2 else None, None, 0, i, "z") for i, t in enumerate(odd_texts())]
    rows += [rows[6], (None, LOREM, None, "s", 1, 0, None)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, __shard long, word string").repartition(3)


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def empty(df):
    return df.limit(0)


def local(df):
    return [(r["doc_id"], r["text"] or "") for r in df.select("doc_id", "text").collect()]


def test_sentencepiece_is_the_library(spark, docs, odd):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=tokenizer_file("piece_bpe_32k.model"))
    for df in (docs, odd):
        got = sentencepieces.encode_digests(df, tokenizer_file("piece_bpe_32k.model")).collect()
        want = []
        for d, t in local(df):
            ids = [1, *sp.encode(t), 2]
            want.append((d, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(sp.decode(ids).encode()).hexdigest()))
        assert sorted(map(str, [tuple(r)[:4] for r in got])) == sorted(map(str, want))
    full = sentencepieces.encode_documents(odd, tokenizer_file("piece_bpe_32k.model")).filter("doc_id = 6").first()
    assert full["decoded"] == LOREM and full["ids"][0] == 1
    assert sentencepieces.encode_digests(empty(odd), tokenizer_file("piece_bpe_32k.model")).count() == 0


def test_agenda_forms_agree():
    codec = sentencepieces.codec(tokenizer_file("piece_bpe_32k.model"))
    from equiscale.llm.merges import agenda

    for word in ("▁wizards", "▁bridge", "▁unbelievable", "▁a"):
        symbols = [int(codec.symbol_of[ord(c)]) for c in word]
        assert agenda(symbols, codec.table) == codec.library.encode(word[1:])


def test_unit_cache_keeps_what_is_used():
    from equiscale.llm.merges import UnitCache

    filled = []

    def fill(units):
        filled.append(len(units))
        return np.concatenate([np.full(len(u), len(u), np.int32) for u in units]), np.array([len(u) for u in units])

    cache, rng = UnitCache(fill, limit=50), random.Random(3)
    hot = ["x" * k for k in range(1, 11)]
    for step in range(60):
        units = [rng.choice(hot) for _ in range(80)] + [f"{step}-{k}" for k in range(20)]
        flat, lens = cache.ids(units)
        assert lens.tolist() == [len(u) for u in units] and flat.tolist() == [len(u) for u in units for _ in u]
        assert len(cache._at) <= 50 + 30 and (step < 10 or set(hot) <= set(cache._at))
    assert sum(filled) <= 10 + 60 * 20 + 10


def brute_passages(rows, length=50):
    out, seen = {}, {}
    for d, t in sorted(rows, key=lambda r: (r[0] is not None, r[0])):
        x = t.encode()
        m = bytearray(len(x))
        key = -(2**63) if d is None else d
        for i in range(len(x) - length + 1):
            if seen.get(x[i : i + length], key) < key:
                m[i : i + length] = b"\1" * length
        for i in range(len(x) - length + 1):
            seen.setdefault(x[i : i + length], key)
        out[d] = (len(x), sum(m), sum(1 for i in range(len(m)) if m[i] and (i == 0 or not m[i - 1])), hashlib.sha256(bytes(c for c, k in zip(x, m) if not k)).hexdigest())
    return out


def passages_of(df, **options):
    return sorted(tuple(r) if r["doc_id"] is not None else (-(2**63), *tuple(r)[1:]) for r in passages.repeated_passages(df, **options).collect())


def brute_rows(rows, length=50):
    """Like brute_passages, row by row: rows of one id never remove from each other."""
    first, out = {}, []
    for d, t in sorted((-(2**63) if d is None else d, t) for d, t in rows):
        x = t.encode()
        for i in range(len(x) - length + 1):
            first.setdefault(x[i : i + length], d)
    for d, t in rows:
        d, x = -(2**63) if d is None else d, t.encode()
        m = bytearray(len(x))
        for i in range(len(x) - length + 1):
            if first[x[i : i + length]] < d:
                m[i : i + length] = b"\1" * length
        out.append((d, len(x), sum(m), sum(1 for i in range(len(m)) if m[i] and (i == 0 or not m[i - 1])), hashlib.sha256(bytes(c for c, k in zip(x, m) if not k)).hexdigest()))
    return sorted(out)


@pytest.mark.parametrize("shard,suffix,hot", [(8_000_000, 4_000_000, 1000), (3000, 1500, 1000), (3000, 600, 1)])
def test_passages(spark, odd, shard, suffix, hot):
    assert passages_of(odd, shard_bytes=shard, suffix_bytes=suffix, hot_contexts=hot) == brute_rows(local(odd))


def header_rows(n=60):
    """A header in every text between texts of their own, texts cut out of others at every offset, and one id with two texts."""
    rng = random.Random(9)
    words = LOREM.split()
    some = lambda k: " ".join(rng.choice(words) + str(rng.randrange(10)) for _ in range(k))
    header = " licensed for every use under the terms of the open stone bridge accord, without any warranty, "
    rows = [(i, some(rng.randrange(12)) + header + some(rng.randrange(12))) for i in range(n)]
    rows += [(n + i, rows[i][1][i : i + 60 + i]) for i in range(n)]
    return rows + [(7, some(30)), (7, rows[3][1]), (None, rows[9][1]), (None, "short")]


@pytest.mark.parametrize("hot", [4000, 1])
def test_frequent_headers_are_split_and_stay_exact(spark, hot):
    rows = header_rows()
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert passages_of(df, shard_bytes=1500, suffix_bytes=2000, hot_contexts=hot) == brute_rows(rows)


def test_contexts_of_hot_anchors_cover_the_same_windows():
    raw = [t.encode() for _, t in header_rows()]
    t, a, b, h, _ = passages.contexts(raw)
    hot = np.unique(h >> passages._TOP)
    cut = passages.contexts(raw, hot=hot)
    windows = lambda x: sorted((k, w) for k, p, q in zip(*(v.tolist() for v in x[:3])) for w in range(p, q + 1))
    assert windows((t, a, b)) == windows(cut)
    key = {}
    for k, p, q, own in zip(*(v.tolist() for v in cut[:4])):
        for w in range(p, q + 1):
            assert key.setdefault(raw[k][w : w + 50], own) == own, "equal windows have equal keys"


def test_strings_of_one_hash_are_told_apart_by_their_bytes():
    raw = [b"aaaabbbbaaaacccc"]
    t, a = np.zeros(4, np.int64), np.array([0, 4, 8, 12])
    group, bodies = passages.collapse(raw, t, a, a + 4, np.zeros(4, np.uint64))
    assert [bodies[g] for g in group] == [b"aaaa", b"bbbb", b"aaaa", b"cccc"] and len(bodies) == 3


def test_cuts_of_hot_anchors_are_made_from_their_own_bytes(monkeypatch):
    rng = random.Random(12)
    words = LOREM.split()
    raw = [" ".join(rng.choice(words) for _ in range(300)).encode() for _ in range(30)]
    plain = passages.contexts(raw)
    hot = np.unique(plain[3] >> passages._TOP)[::40]
    among = passages._among(plain[3] >> passages._TOP, hot)
    every = [x for x in zip(*(v.tolist() for v in passages.contexts(raw, hot=hot)))]
    asked, real = [], passages.contexts
    monkeypatch.setattr(passages, "contexts", lambda texts, *a, **k: asked.append(sum(map(len, texts))) or real(texts, *a, **k))
    cut = passages._with_cuts(raw, passages.LENGTH, passages.GRAM, hot, plain, np.ones(len(plain[0]), bool))
    assert sorted(zip(*(v.tolist() for v in cut[:5]))) == sorted(every)
    assert 0 < asked[0] < sum(map(len, raw)) / 4 and among.any() and cut[5].all()


def test_passages_on_documents_and_filter_form(spark, docs, odd):
    rows = local(docs)
    got = {r["doc_id"]: tuple(r)[1:] for r in passages.repeated_passages(docs, shard_bytes=40_000).collect()}
    assert got == brute_passages(rows)
    out = passages.remove_passages(odd)
    assert out.columns == odd.columns and out.count() == odd.count()
    assert out.filter("doc_id = 0").first()["text"] is None
    rows = [(d, t) for d, t in header_rows() if d != 7]
    df = spark.createDataFrame([(t, d, len(t)) for d, t in rows], "text string, doc_id long, n_chars int")
    want = {(d, h) for d, _, _, _, h in brute_rows(rows)}
    kept = passages.remove_passages(df, shard_bytes=3000).collect()
    assert {(-(2**63) if r["doc_id"] is None else r["doc_id"], hashlib.sha256(r["text"].encode()).hexdigest()) for r in kept} == want
    assert all(r["n_chars"] == len(r["text"]) for r in kept)
    assert passages.repeated_passages(empty(odd)).count() == 0


def test_suffix_arrays():
    rng = random.Random(1)
    for n in [*range(20), 300]:
        for letters in (b"a", b"ab", b"\0a", b"abcdefgh"):
            t = bytes(rng.choice(letters) for _ in range(n))
            x = np.frombuffer(t, np.uint8)
            sa = suffixes.suffix_array(x)
            assert sa.tolist() == sorted(range(n), key=lambda i: t[i:])
            lcp = suffixes.common_prefixes(x, sa, 64, 7)
            for i in range(1, n):
                a, b = t[sa[i - 1] :], t[sa[i] :]
                k = next((k for k in range(min(len(a), len(b), 64)) if a[k] != b[k]), min(len(a), len(b), 64))
                assert lcp[i] == k
    words = np.sort(np.unique(np.random.default_rng(0).integers(0, 50, (40, 1)), axis=0), axis=0).astype(np.uint64)
    a, b = ((np.array([[1], [4], [9]], np.uint64), np.array([5, 6, 7])), (np.array([[0], [4], [12], [13]], np.uint64), np.array([3, 2, 9, 8])))
    for x, y in ((a, b), (b, a)):
        words_, least = suffixes.merge_windows(*x, *y)
        assert words_[:, 0].tolist() == [0, 1, 4, 9, 12, 13] and least.tolist() == [3, 5, 2, 7, 9, 8]
    assert all(suffixes.locate(words, np.array([[v]], np.uint64))[0] == (words[:, 0].tolist().index(v) if v in words else -1) for v in range(50))


def test_golay_covers_two_errors():
    rng = np.random.default_rng(2)
    x = rng.integers(0, 1 << 23, 3000)
    flip = (1 << rng.integers(0, 23, 3000)) | (1 << rng.integers(0, 23, 3000))
    a, b = golay.indices(x), golay.indices(x ^ flip)
    assert all(set(p[p >= 0]) & set(q[q >= 0]) for p, q in zip(a, b))
    assert set((a >= 0).sum(1)) <= {1, 6}


def test_fuzzy_keys_cover_four_errors():
    rng = np.random.default_rng(3)
    for errors in range(5):
        x = rng.integers(0, 2**63, 300, dtype=np.uint64)
        y = x.copy()
        for k in range(300):
            for b in rng.choice(64, errors, replace=False):
                y[k] ^= np.uint64(1) << np.uint64(b)
        (ka, ra), (kb, rb) = simhash.fuzzy_keys(x), simhash.fuzzy_keys(y)
        for k in range(300):
            assert set(ka[ra == k]) & set(kb[rb == k])


def brute_simhash(text, words=4):
    import xxhash

    low = re.sub("[A-Z]", lambda m: m.group().lower(), text)
    own = re.findall(r"[^\x20\x09-\x0D]+", low)
    shingles = [" ".join(own[i : i + words]) for i in range(max(1, len(own) - words + 1))] if own else []
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(rows, words=4):
    fp = [(d, brute_simhash(t, words)) for d, t in rows]
    label = list(range(len(fp)))

    def root(i):
        while label[i] != i:
            i = label[i]
        return i

    for i in range(len(fp)):
        for j in range(i):
            if (fp[i][1] ^ fp[j][1]).bit_count() <= 4:
                label[root(i)] = root(j)
    least = {}
    for i, (d, _) in enumerate(fp):
        least[root(i)] = min(least.get(root(i), 2**63), -(2**63) if d is None else d)
    return sorted((str(d), f"{f:016x}", str(None if least[root(i)] == -(2**63) else least[root(i)])) for i, (d, f) in enumerate(fp))


@pytest.mark.parametrize("bucket", [48_000_000, 3000])
def test_simhash_components(spark, odd, bucket):
    base = LOREM.split()
    near = spark.createDataFrame([(100 + k, " ".join(base[:k] + ["new"] + base[k + 1 :]) + " " + LOREM) for k in range(12)], "doc_id long, text string")
    df = odd.select("doc_id", "text").unionByName(near)
    got = sorted((str(r["doc_id"]), r["fingerprint"], str(r["component_id"])) for r in simhash.near_components(df, bucket_bytes=bucket).collect())
    assert got == brute_components(local(df))


def test_simhash_on_documents(spark, docs):
    got = sorted((str(r["doc_id"]), r["fingerprint"], str(r["component_id"])) for r in simhash.near_components(docs).collect())
    assert got == brute_components(local(docs))
    assert simhash.near_components(empty(docs)).count() == 0


def test_near_groups_verify_five_word_shingles(spark):
    rng = random.Random(9)
    words = [f"w{k}" for k in range(4000)]
    rows, near = [], []
    for g in range(60):
        own = [rng.choice(words) for _ in range(120)]
        rows.append((10 * g, " ".join(own)))
        copy = list(own)
        copy[rng.randrange(120)] = "changed"
        rows.append((10 * g + 1, " ".join(copy)))
        near.append(10 * g + 1)
        rows.append((10 * g + 2, " ".join(rng.choice(words) for _ in range(120))))
    got = {r["doc_id"] for r in simhash.near_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert not got - set(near) and len(got) >= 0.95 * len(near)


def brute_groups(rows, similarity=0.8):
    """{doc_id: smallest id of its component} of the documents that go, over all pairs."""
    low = lambda t: re.sub("[A-Z]", lambda m: m.group().lower(), t)
    ids, sets, holders = [], [], {}
    for d, t in sorted(rows):
        w = low(t).split()
        own = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
        for x in own or {()}:
            holders.setdefault(x, []).append(len(ids))
        ids.append(d)
        sets.append(own)
    root = list(range(len(ids)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    met = {(a, b) for own in holders.values() for k, b in enumerate(own) for a in own[:k]}
    for a, b in met:
        both, union = len(sets[a] & sets[b]), len(sets[a] | sets[b])
        if (both / union if union else 1.0) >= similarity:
            a, b = sorted((find(a), find(b)))
            root[b] = a
    return {ids[x]: ids[find(x)] for x in range(len(ids)) if find(x) != x}


def edited(own, words, n, rng):
    own = list(own)
    for k in rng.sample(range(len(own)), n):
        own[k] = rng.choice(words)
    return own


def test_near_groups_follow_chains(spark):
    rng = random.Random(10)
    words = [f"w{k}" for k in range(4000)]
    rows = []
    for g in range(30):  # neighbours agree to about 0.9, the ends of a chain do not agree to 0.8
        own = [rng.choice(words) for _ in range(200)]
        for k in range(4):
            rows.append((10 * g + k, " ".join(own)))
            own = edited(own, words, 2, rng)
    got = {r["doc_id"]: r["keep_id"] for r in simhash.near_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    want = brute_groups(rows)
    assert not set(got) - set(want) and len(got) >= 0.85 * len(want)


def test_near_groups_compare_long_texts_in_full(spark):
    rng = random.Random(11)
    words = [f"w{k}" for k in range(4000)]
    rows = []
    for g in range(60):  # just under 0.8
        own = [rng.choice(words) for _ in range(1200)]
        rows += [(2 * g, " ".join(own)), (2 * g + 1, " ".join(edited(own, words, 29, rng)))]
    want = brute_groups(rows)
    assert len(want) < 20
    got = {r["doc_id"] for r in simhash.near_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert not got - set(want)


def near_rows():
    """Groups of ten copies edited independently of an original of a larger id, chains, pairs around 0.8 and texts of 20 to 2000 words with one line in common."""
    rng = random.Random(19)
    words = [f"w{k}" for k in range(4000)]
    line = [f"common{k}" for k in range(12)]
    texts = []
    for g, size in enumerate([60, 120, 250, 450, 900, 2000] * 5):
        own = [rng.choice(words) for _ in range(size)] + line
        texts.append(own)
        texts += [edited(own, words, max(1, size // rng.choice([45, 55, 70])), rng) for _ in range(9)] if g % 3 == 0 else []
        for _ in range(8):  # each link about 0.83, the ends far below 0.8
            own = edited(own, words, max(1, size // 52), rng)
            texts.append(own)
    texts += [edited([f"s{g}x{k}" for k in range(20)], words, n, rng) + line for g in range(10) for n in (0, 0, 1)]
    ids = rng.sample(range(1, 10 * len(texts)), len(texts))
    return [(d, " ".join(t)) for d, t in zip(ids, texts)] + [(5 * 10**6, ""), (5 * 10**6 + 1, " ")]


def test_near_groups_are_the_components_of_all_pairs(spark, docs):
    rows = near_rows()
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute_groups(rows)
    assert {r["doc_id"]: r["keep_id"] for r in simhash.near_groups(frame).collect()} == want
    for distance in (20, 0):  # with hardly a link of fingerprints the prefixes find the rest
        assert {r["doc_id"]: r["keep_id"] for r in simhash.near_groups(frame, distance=distance, bucket_bytes=20_000).collect()} == want
    assert {r["doc_id"]: r["keep_id"] for r in simhash.near_groups(docs).collect()} == brute_groups(local(docs))
    kept = {r["doc_id"]: r["text"] for r in simhash.drop_near(frame).collect()}
    assert kept == {d: t for d, t in rows if d not in want}
    assert simhash.near_groups(frame.limit(0)).count() == 0


def test_prefix_and_parity_are_bounds():
    rng = np.random.default_rng(3)
    for _ in range(300):
        n = int(rng.integers(1, 1500))
        a = np.unique(rng.integers(0, 2**63, n, dtype=np.uint64))
        b = np.unique(np.concatenate([a[rng.random(len(a)) < 0.95], rng.integers(0, 2**63, int(n * rng.random() / 6), dtype=np.uint64)]))
        both = len(np.intersect1d(a, b))
        common = np.sort(a[rng.random(len(a)) < 0.5])
        if both >= 0.8 * (len(a) + len(b) - both):
            assert len(np.intersect1d(simhash.prefix(a, 0.8, common), simhash.prefix(b, 0.8, common)))
        bits = np.bitwise_count(np.frombuffer(simhash.parity(a), np.uint8) ^ np.frombuffer(simhash.parity(b), np.uint8)).sum()
        assert bits <= len(a) + len(b) - 2 * both


def test_components(spark):
    edges = [(k, k + 1) for k in range(30)] + [(100, k) for k in range(101, 160)] + [(5, 5)]
    got = {r["node"]: r["root"] for r in graph.components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == {k: 0 for k in range(1, 31)} | {k: 100 for k in range(101, 160)}


def test_exact_groups(spark, odd, docs):
    low = lambda t: re.sub("[A-Z]", lambda m: m.group().lower(), t)
    for df in (odd, docs):
        for options in ({}, {"bits_per_row": 1}, {"max_blocks": 2}):  # a crowded filter sends more rows on, with the same result
            rows, groups = local(df), {}
            for d, t in rows:
                groups.setdefault(low(t), []).append(d)
            want = []
            for d, t in rows:
                own = groups[low(t)]
                keep = max((x for x in own if x is not None), default=None)
                want.append((str(d), str(keep), len(own), d == keep, hashlib.sha256(low(t).encode()).hexdigest()))
            got = [(str(r["doc_id"]), str(r["keep_id"]), r["group_size"], r["kept"], r["text_sha256"]) for r in exact_dedup.exact_groups(df, **options).collect()]
            assert sorted(got) == sorted(want)
    kept = exact_dedup.drop_exact(odd)
    assert kept.columns == odd.columns
    last = {}
    for r in odd.collect():
        own = low(r["text"] or "")
        last[own] = max(last.get(own, -1), -1 if r["doc_id"] is None else r["doc_id"])
    want = [r for r in odd.collect() if (-1 if r["doc_id"] is None else r["doc_id"]) == last[low(r["text"] or "")]]
    assert sorted(map(str, kept.collect())) == sorted(map(str, want))
    assert exact_dedup.exact_groups(empty(odd)).count() == 0


def test_filter_passes_single_rows_through(spark):
    rows = exact_dedup.hashed(spark.range(2000).select(F.col("id").alias("doc_id"), F.col("id").cast("string").alias("text")))
    blocks = exact_dedup.filter_blocks(2000)
    assert exact_dedup.probe(rows, exact_dedup.repeated_blocks(rows, blocks), blocks).filter("maybe").count() < 0.06 * 2000
    twice = rows.unionByName(rows.filter("doc_id < 100"))
    maybe = exact_dedup.probe(twice, exact_dedup.repeated_blocks(twice, blocks), blocks).filter("maybe")
    assert maybe.filter("doc_id < 100").count() == 200 and maybe.count() < 200 + 0.15 * 2000
    assert exact_dedup.filter_blocks(10**12) == exact_dedup.MAX_BLOCKS


def test_sketches(spark, odd):
    import itertools

    got = {str(r["doc_id"]) + str(i): r for i, r in enumerate(sketches.fingerprints(odd.filter("doc_id is not null").dropDuplicates(["doc_id"]).withColumn("text", F.col("text"))).orderBy("doc_id").collect())}
    rows = sorted(dict((d, t) for d, t in local(odd) if d is not None).items())
    whole = spark.createDataFrame(rows, "doc_id long, text string").select("doc_id", sketches.sketch(F.col("text"), 5, 1).alias("s")).collect()
    assert len(got) == len(rows)
    for i, (d, t) in enumerate(rows):
        r = got[str(d) + str(i)]
        other = rows[(i + 1) % len(rows)][1]
        n = len(t) // 2
        edited = t[: len(t) - n] + other[:n]
        assert r["n_chars"] == len(t) and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        words = t.split()
        shingles = {tuple(words[k : k + 5]) for k in range(max(1, len(words) - 4))} if words else set()
        full = next(x["s"] for x in whole if x["doc_id"] == d)
        assert len(full) == len(shingles)
        assert r["fingerprint"] == "".join(f"{h & (2**64 - 1):016x}" for h in full if h < -(2**62))
        assert 0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1
    fps = [(t, got[str(d) + str(i)]["fingerprint"]) for i, (d, t) in enumerate(rows)]
    assert all(a[1] == b[1] for a, b in itertools.combinations(fps, 2) if a[0] == b[0])
    assert sketches.fingerprints(empty(odd)).count() == 0


def brute_sketch(text):
    """Hashes of the words' hashes by Spark's own function are taken as given; sets are made here."""
    words = text.split()
    return {tuple(words[k : k + 5]) for k in range(len(words) - 4)} or ({tuple(words)} if words else set())


def test_likeness_is_that_of_the_retained_shingles(spark, odd, docs):
    """Both likenesses against sets made in Python, null and repeated ids included."""
    for df in (odd.filter("length(text) < 5000 or text is null"), docs):
        rows = sorted(((d is not None, d, t) for d, t in local(df)), key=lambda r: (r[0], r[1] if r[0] else 0, r[2]))
        rows = [(d, t) for _, d, t in rows]
        texts = []
        for i, (_, t) in enumerate(rows):
            nxt = rows[(i + 1) % len(rows)][1]
            n = len(t) // 2
            texts.append((t, t[: len(t) - n] + nxt[:n], nxt))
        shingles = sorted({s for own in texts for t in own for s in brute_sketch(t)})
        flat = spark.createDataFrame([(k, list(s)) for k, s in enumerate(shingles)], "k long, w array<string>").repartition(8)
        hashed = flat.select("k", F.when(F.size("w") < 5, F.xxhash64(F.transform("w", lambda w: F.xxhash64(w)))).otherwise(F.xxhash64(*[F.xxhash64(F.get("w", F.lit(j))) for j in range(5)])).alias("h"))
        h = {shingles[r["k"]]: r["h"] for r in hashed.collect()}
        low = {k for k, v in h.items() if v < -(2**62)}

        def like(a, b):
            x, y = ({h[s] for s in brute_sketch(t) if s in low} for t in (a, b))
            return len(x & y) / len(x | y) if x and y else float(a == b)

        want = sorted((str(d), len(t), hashlib.sha256(e.encode()).hexdigest(), round(like(t, e), 9), round(like(t, nxt), 9)) for (d, _), (t, e, nxt) in zip(rows, texts))
        got = sorted((str(r["doc_id"]), r["n_chars"], r["edited_sha256"], round(r["near_edited"], 9), round(r["near_next"], 9)) for r in sketches.fingerprints(df).collect())
        assert got == want


def test_ranges_are_even_whatever_the_ids(spark):
    ids = [*range(3000), 10**16, -(2**63), 2**63 - 1, *(10**12 + 7 * k for k in range(500))]
    df = spark.createDataFrame([(d, "t") for d in ids] + [(None, "t")] * 3, "doc_id long, text string")
    got = sketches._ranges(df, 100).groupBy("__b").agg(F.min(F.coalesce("doc_id", F.lit(-(2**63)))).alias("lo"), F.max(F.coalesce("doc_id", F.lit(-(2**63)))).alias("hi"), F.count("*").alias("n")).orderBy("__b").collect()
    assert sum(r["n"] for r in got) == len(ids) + 3 and max(r["n"] for r in got) <= 400
    assert all(a["hi"] <= b["lo"] for a, b in zip(got, got[1:]))


def test_sketch_merge_and_containment(spark):
    df = spark.createDataFrame([("g", LOREM), ("g", "other words make another short text here")], "g string, text string").withColumn("s", sketches.sketch(F.col("text"), 5, 1))
    merged = sketches.merge(df, ["g"], "s").select(F.col("g").alias("k"), F.col("s").alias("m"))
    assert {r[0] for r in df.join(merged, F.col("g") == F.col("k")).select(sketches.containment(F.col("s"), F.col("m"))).collect()} == {1.0}


def test_next_document_over_ranges(spark):
    ids = random.Random(4).sample(range(-(10**12), 10**12), 300)
    df = spark.createDataFrame([(d, str(d)) for d in ids], "doc_id long, text string")
    ids.sort()
    got = {r["doc_id"]: r["next_text"] for r in sketches.with_next(df, rows_per_range=7).collect()}
    assert got == {d: str(ids[(i + 1) % 300]) for i, d in enumerate(ids)}


def test_packing_is_whole_and_tight(spark, docs, odd):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(tokenizer_file("word_bpe_49k.json"))
    for df, capacity, block in ((docs, 4096, 4000), (docs, 512, 60), (odd, 64, 10)):
        got = packing.pack_documents(df, tokenizer_file("word_bpe_49k.json"), capacity=capacity, block=block).collect()
        want = []
        for d, t in local(df):
            ids = np.array([*tok.encode(t, add_special_tokens=False).ids, 1], "<u4")
            want += [(str(d), k, a, len(ids[a : a + capacity]), zlib.crc32(ids[a : a + capacity].tobytes())) for k, a in enumerate(range(0, len(ids), capacity))]
        assert sorted((str(r["doc_id"]), r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got) == sorted(want)
        bins = {}
        for r in got:
            bins.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
        for own in bins.values():
            at = 0
            for o, n in sorted(own):
                assert o == at
                at += n
            assert at <= capacity
        bound = -(-sum(w[3] for w in want) // capacity)
        assert len(bins) <= 1.03 * bound + 2
    assert packing.pack_documents(empty(odd), tokenizer_file("word_bpe_49k.json")).count() == 0


def test_chunks_of_known_words_need_no_merges(monkeypatch):
    import pyarrow as pa

    codec, merged = packing.WordCodec(tokenizer_file("word_bpe_49k.json")), []
    plain = packing.merge_words
    monkeypatch.setattr(packing, "merge_words", lambda flat, size, table: merged.append(len(size)) or plain(flat, size, table))
    rows = ["", "other", "alpha beta, (gamma) don't", "Alpha, (BETA) Gamma don'T alpha(beta)\nGamma,alpha", "\n ", "naïve <|endoftext|> alpha\tbeta 12 日本 ÉÉ!", "alpha  beta, "]
    assert codec.encode([]) == []
    column = pa.array(rows, pa.string())
    for at, n, new in ((2, 1, 8), (3, 1, 0), (4, 3, 5)):  # alpha beta , ( gamma ) don 't; nothing; naïve 1 2 éé !
        merged.clear()
        got = codec.encode(column.slice(at, n))
        assert [x.tolist() for x in got] == [codec.library.encode(t, add_special_tokens=False).ids for t in rows[at : at + n]]
        assert sum(merged) == new


def hard_sizes(n=1200, seed=3):
    """Pieces of a fifth to a half of a sequence: best fit leaves much room."""
    rng = random.Random(seed)
    return [rng.randint(820, 2048) for _ in range(n)]


def test_evolution_gains_where_best_fit_misses_the_bound(spark):
    sizes = hard_sizes()
    best, generations = packing.evolve(sizes, 4096, [], 5)
    assert sorted(i for b in best for i in b) == list(range(len(sizes))) and max(sum(sizes[i] for i in b) for b in best) <= 4096
    plain = len(packing.best_fit(sizes, 4096))
    assert generations > 0 and len(best) <= plain - 10
    sizes = hard_sizes(300)
    easy = [1024] * 400
    assert packing.evolve(easy, 4096, [], 5)[1] == 0  # best fit meets the bound: nothing to gain
    pieces = spark.createDataFrame([(i, 0, 0, s, 0) for i, s in enumerate(sizes)], packing.PIECE_SCHEMA)
    rows = packing.evolution(pieces, block=150, islands=2).collect()
    assert sum(r["pieces"] for r in rows) == len(sizes)
    assert all(r["bound"] <= r["evolved"] < r["best_fit"] and r["generations"] > 0 for r in rows)
    packed = packing.pack(pieces, block=300, islands=2).select("sequence_id").distinct().count()
    assert packed < len(packing.best_fit(sizes, 4096))


def test_crossover_keeps_every_piece():
    rng = random.Random(0)
    sizes = [rng.randint(100, 2500) for _ in range(300)]
    a, b = packing.best_fit(sizes, 4096), packing.best_fit(sizes, 4096, noise=rng)
    child = packing.mutate(packing.crossover(a, b, sizes, 4096, rng), sizes, 4096, rng)
    assert sorted(i for x in child for i in x) == list(range(300)) and all(sum(sizes[i] for i in x) <= 4096 for x in child)
    best, _ = packing.evolve(sizes, 4096, [], 3)
    assert len(best) <= len(a)


def test_chat(spark):
    rows = [(1, 0, "system", "rules", 0), (1, 1, "user", "hi", 0), (1, 2, "bob", "yo", 0), (1, 2, "bob", "yo", 0), (1, 3, "user", None, 0), (2, 0, "system", "alone", 0), (None, None, None, "x", 0), (3, 700, "user", "late", 0), (3, 1, "user", "early", 0)]
    got = {(r["conv_id"], r["part"], r["perspective"]): r for r in chat.rotate_perspectives(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, own long")).collect()}
    assert set(got) == {(1, 0, "user"), (1, 0, "bob"), (None, -1, "unknown"), (3, 0, "user"), (3, 2, "user")}
    r = got[(1, 0, "bob")]
    assert r["rendered"] == "<|im_start|>system\nrules<|im_end|>\n<|im_start|>user name=user\nhi<|im_end|>\n<|im_start|>assistant\nyo<|im_end|>\n<|im_start|>user name=user\n<|im_end|>\n"
    a, b = map(int, r["mask"].split(":"))
    assert r["rendered"][a:b] == "yo<|im_end|>\n" and r["n_turns"] == 4 and r["n_own"] == 1


def test_chat_parts_make_the_whole(spark):
    rng = random.Random(4)
    rows = [(c, t, rng.choice(["system", "user", "bob", None]), rng.choice([None, "", LOREM, "ok"])) for c in (1, 2, None) for t in [*range(40), None]]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")

    def whole(segment):
        out = {}
        for r in sorted(chat.rotate_perspectives(df, segment=segment).collect(), key=lambda r: r["part"]):
            text, spans, n = out.get((r["conv_id"], r["perspective"]), ("", [], 0))
            own = [tuple(map(int, x.split(":"))) for x in r["mask"].split(",") if x]
            out[r["conv_id"], r["perspective"]] = (text + r["rendered"], spans + [(len(text) + a, len(text) + b) for a, b in own], n + r["n_turns"])
        return out

    assert whole(7) == whole(10**9) and len(whole(7)) == 9
    assert chat.rotate_perspectives(empty(df)).count() == 0


def test_near_groups_on_odd_rows(spark, odd):
    got = {r["doc_id"]: r["keep_id"] for r in simhash.near_groups(odd).collect()}
    rows = [(-(2**63) if d is None else d, t) for d, t in local(odd)]
    want = {d: (None if k == -(2**63) else k) for d, k in brute_groups(list(dict(rows).items())).items()}
    assert got == want
    kept = simhash.drop_near(odd)
    assert kept.columns == odd.columns
    assert sorted(map(str, kept.collect())) == sorted(str(r) for r in odd.collect() if (-(2**63) if r["doc_id"] is None else r["doc_id"]) not in want)
    assert simhash.near_groups(empty(odd)).count() == 0 and simhash.drop_near(empty(odd)).count() == 0


def test_language_scores_are_those_of_a_plain_mean(spark, docs, odd):
    model = language.learn(docs)

    def plain(text):
        code = [b if b >= 128 or chr(b).isalpha() else 32 for b in b" " + text.lower().encode() + b" "]
        rows = []
        for size in (3, 4):
            for i in range(len(code) - size + 1):
                own = code[i : i + size]
                if 32 not in own[1:-1]:
                    value = int.from_bytes(bytes(own), "little")
                    rows.append(model.table[(value * (2654435761 + 2 * size) % 2**32) >> 17].astype(float))
        if not any(map(str.isalpha, text)):
            return "und", 0.0
        z = (np.mean(rows, axis=0) if rows else np.zeros(len(model.languages))) / model.temperature
        e = np.exp(z - z.max())
        return model.languages[int(z.argmax())], float((e / e.sum()).max())

    for df in (docs.limit(60), odd.filter("length(text) < 3000 or text is null")):
        want = {str(d): plain(t) for d, t in local(df)}
        for r in language.identify(df, model).collect():
            lang, score = want[str(r["doc_id"])]
            assert r["lang_pred"] == lang and r["score"] == pytest.approx(score, abs=1e-5)


def test_quality_scores_are_those_of_plain_sums(spark, docs):
    train, labels = labelled(spark)
    model = quality.learn(train, labels)
    texts = [t for _, t in local(docs)][:40] + ["", "\n\n", LOREM]

    def plain(text):
        x, size, _ = quality.line_features([text])
        e = x @ model.field.w
        t = model.field.t
        n = len(e)
        # sums over all paths, state by state
        f, b = [[1.0, float(np.exp(e[0]))]], [[1.0, 1.0]]
        for k in range(1, n):
            row = [sum(f[-1][a] * np.exp(t[a, s]) for a in range(2)) * (np.exp(e[k]) if s else 1.0) for s in range(2)]
            f.append([v / sum(row) for v in row])
        for k in range(n - 2, -1, -1):
            row = [sum(np.exp(t[a, s]) * (np.exp(e[k + 1]) if s else 1.0) * b[0][s] for s in range(2)) for a in range(2)]
            b.insert(0, [v / sum(row) for v in row])
        p = [f[k][1] * b[k][1] / sum(f[k][s] * b[k][s] for s in range(2)) for k in range(n)]
        w = [z + 1.0 for z in size]
        mean = sum(a * c for a, c in zip(p, w)) / sum(w)
        low = min([v for v, z in zip(p, size) if z >= 20] + [1.0])
        c = min(max(mean, 1e-4), 1 - 1e-4)
        return 1 / (1 + np.exp(-np.clip(np.dot([np.log(c / (1 - c)), mean, low, 1.0], model.weights), -30, 30)))

    assert np.allclose(model.score(texts), [plain(t) for t in texts], atol=1e-6)


def edit_distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a):
        row, old = [i + 1], row
        for j, y in enumerate(b):
            row.append(min(old[j] + (x != y), old[j + 1] + 1, row[j] + 1))
    return row[-1]


def test_levenshtein_automata():
    rng = random.Random(6)
    terms = ["idiot", "worthless", "scum", "moron", "abcabc"]
    lexicon = toxicity.FuzzyLexicon(terms)
    tokens = list(terms)
    for t in terms:
        for _ in range(300):
            x = list(t)
            for _ in range(rng.randint(0, 3)):
                k = rng.randrange(len(x) + 1)
                x[k : k + rng.randint(0, 1)] = rng.choice(["", "a", "o", "z"])
            tokens.append("".join(x))
    for w in tokens:
        want = min(((edit_distance(w, t), i) for i, t in enumerate(terms) if edit_distance(w, t) <= lexicon.allowed(t)), default=None)
        assert lexicon.search(w) == want, w
    small = toxicity.FuzzyLexicon(terms, keep=5)  # tables that start anew all the time give the same
    assert [small.search(w) for w in tokens] == [lexicon.search(w) for w in tokens] and len(small._sets) <= 5
    stem = toxicity.FuzzyLexicon(["lowei*"])
    assert stem.search("loweichen") == (0, 0) and stem.search("lowe") is None
    assert lexicon.match("1d10t") is not None


def test_quotation_is_not_abuse():
    scan = toxicity.Scanner(toxicity.FuzzyLexicon(["idiot"]))
    abuse, quoted = scan.features("you idiot"), scan.features('they said "idiot" to us')
    assert abuse[0] > quoted[0] and quoted[3] > abuse[3]


def plain_features(text, terms, clean, window=6):
    """The features of a text term by term, without trie or automaton."""
    low = text.lower()
    places = list(toxicity.TOKEN.finditer(low))

    def find(word):
        best = None
        for i, term in enumerate(terms):
            allowed = toxicity.FuzzyLexicon.allowed(term)
            if term.endswith("*"):
                d = min(edit_distance(word[:k], term[:-1]) for k in range(len(word) + 1))
            else:
                d = edit_distance(word, term)
            if d <= allowed and (best is None or (d, i) < best):
                best = (d, i)
        return best

    exact = fuzzy = stem = quoted = 0.0
    for k, m in enumerate(places):
        word = m.group()
        hit = find(word)
        if (hit is None or hit[0]) and not word.isalpha():
            plain = find(word.translate(toxicity.LEET))
            if plain is not None and (hit is None or plain[0] < hit[0]):
                hit = (max(1, plain[0]), plain[1])
        if hit is None or (hit[0] and word in clean):
            continue
        start, end = m.span()
        before = low[max(low.rfind("\n", 0, start) + 1, start - 200) : start]
        marks = sum(c in "\"“”«»„‘’" for c in before) % 2 == 1 and any(c in "\"“”«»„‘’" for c in low[end : end + 200])
        near = {p.group() for p in places[max(0, k - window) : k + window + 1]}
        abuse = min(1.0, max(0.05, 1.0 - 0.6 * marks - 0.25 * bool(near & toxicity.REPORT) + 0.25 * bool(near & toxicity.ADDRESS)))
        quoted += 1 - abuse
        if hit[0]:
            fuzzy += abuse
        elif terms[hit[1]].endswith("*"):
            stem += abuse
        else:
            exact += abuse
    total = exact + fuzzy + stem
    return [np.log1p(exact), np.log1p(fuzzy), np.log1p(stem), np.log1p(quoted), float(exact + stem >= 0.5), 100 * total / (len(places) + 1), float(total >= 1.5), 1.0]


def test_toxicity_scores_are_those_of_plain_search(spark, odd):
    docs, labels = labelled(spark)
    more = spark.createDataFrame([(900 + i, t, "xx") for i, t in enumerate(['they said "grumpix" and left', "you gr4mpix", "snarvels snarvle blortn grumpixes", "she wrote: blorten"])], docs.schema)
    docs = docs.unionByName(more).unionByName(odd.filter("length(text) < 500 or text is null").select("doc_id", "text", "lang"))
    terms, clean, weights = model = toxicity.learn(docs, labels)
    assert terms
    got = sorted((str(r["doc_id"]), r["__score"]) for r in toxicity.score(docs, model).collect())
    want = sorted((str(r["doc_id"]), 1 / (1 + np.exp(-np.clip(np.dot(plain_features(r["text"] or "", terms, clean), weights), -30, 30)))) for r in docs.collect())
    assert [d for d, _ in got] == [d for d, _ in want] and np.allclose([p for _, p in got], [p for _, p in want], atol=1e-9)


def labelled(spark, n=400):
    rng = random.Random(8)
    words = [a + b for a in ("ka", "lo", "mi", "ter", "sun") for b in ("ra", "den", "pol", "ti", "mon")]
    bad = ["grumpix", "snarvel", "blorten"]
    docs, labels = [], []
    for d in range(n):
        text = [rng.choice(words) for _ in range(60)]
        toxic, good = int(d % 4 == 0), int(d % 3 != 0)
        if toxic:
            for _ in range(3):
                text.insert(rng.randrange(50), rng.choice(bad))
        lines = [" ".join(text[k : k + 10]) for k in range(0, len(text), 10)]
        if not good:
            lines = [x.upper().replace(" ", "!! ") for x in lines[:-1]] + lines[-1:]
        docs.append((d, "\n".join(lines), "xx" if d % 2 else "yy"))
        labels.append((d, good, toxic))
    return spark.createDataFrame(docs, "doc_id long, text string, lang string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def test_toxicity_and_quality_on_held_out(spark, odd):
    docs, labels = labelled(spark)
    want = {r["doc_id"]: r for r in labels.collect()}
    for run, column in ((toxicity.judge, "toxic"), (quality.score_documents, "quality")):
        rows = run(docs, labels).collect()
        assert {r["held_out"] for r in rows} == {True, False}
        assert np.mean([r["predicted"] == want[r["doc_id"]][column] for r in rows if r["held_out"]]) > 0.95
        assert run(odd, labels).count() == odd.count()
        assert run(odd, labels.limit(0)).count() == odd.count()
        assert run(empty(odd), labels).count() == 0
    kept = toxicity.drop_toxic(docs, labels)
    assert kept.columns == docs.columns and {want[r["doc_id"]]["toxic"] for r in kept.collect()} == {0}


def test_line_field_marginals():
    rng = np.random.default_rng(1)
    x, start = rng.normal(size=(9, 3)), np.array([0, 4, 5, 9])
    field = quality.LineField(rng.normal(size=3), rng.normal(size=(2, 2)))
    p, pair = field.marginals(x, start, pairs=True)
    total = np.zeros((2, 2))
    for a, b in zip(start[:-1], start[1:]):
        z, good = 0.0, np.zeros(b - a)
        own = np.zeros((2, 2))
        for code in range(2 ** (b - a)):
            y = [(code >> k) & 1 for k in range(b - a)]
            w = np.exp(sum(v * (x[a + k] @ field.w) for k, v in enumerate(y)) + sum(field.t[u, v] for u, v in zip(y, y[1:])))
            z += w
            good += w * np.array(y)
            for u, v in zip(y, y[1:]):
                own[u, v] += w
        assert np.allclose(p[a:b], good / z)
        total += own / z
    assert np.allclose(pair, total)


def test_language(spark, docs, odd):
    rows = language.predict_languages(docs).collect()
    lang = {r["doc_id"]: r["lang"] for r in docs.select("doc_id", "lang").collect()}
    assert np.mean([r["lang_pred"] == lang[r["doc_id"]] for r in rows if r["held_out"]]) > 0.9
    got = {r["doc_id"]: r for r in language.predict_languages(odd).collect()}
    assert got[0]["lang_pred"] == got[1]["lang_pred"] == got[17]["lang_pred"] == "und"
    assert got[6]["lang_pred"] == "en" and 0 <= got[6]["score"] <= 1
    assert language.predict_languages(empty(odd)).count() == 0


def test_pipeline(spark):
    import corpus_pipeline

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES[:-1]):
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns, name
        docs = spark.createDataFrame(out.collect(), out.schema)
    assert 0 < docs.count() < 200
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, SF)
    assert {r[0] for r in packed.select("doc_id").distinct().collect()} == {r[0] for r in docs.select("doc_id").collect()}
    assert corpus_pipeline.ORACLE_SQL is None and len(corpus_pipeline.STAGES) == 5


def test_pipeline_runs_on_odd_tables(spark, odd, tmp_path):
    """Nulls, repeated rows and extra columns from end to end; and an empty table."""
    import corpus_pipeline

    labels = spark.createDataFrame([(1, None, 0), (None, 1, 1)], "doc_id long, quality int, toxic int")
    labels.write.parquet(str(tmp_path / "labels.parquet"))
    odd.write.parquet(str(tmp_path / "documents.parquet"))
    rows = corpus_pipeline.run(spark, str(tmp_path)).collect()
    full = {}
    for r in odd.collect():  # without labels of both kinds nothing is toxic
        d, t = -(2**63) if r["doc_id"] is None else r["doc_id"], r["text"] or ""
        key = re.sub("[A-Z]", lambda m: m.group().lower(), t)
        full[key] = max(full.get(key, (-(2**63), "")), (d, t))
    gone = brute_groups(list(full.values()))
    assert {-(2**63) if r["doc_id"] is None else r["doc_id"] for r in rows} == {d for d, _ in full.values() if d not in gone}
    odd.limit(0).write.mode("overwrite").parquet(str(tmp_path / "documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_pipeline_stages_against_brute_force(spark):
    """Exact, near and passage stage on groups of more than two, pairs at 0.80-0.85 and long texts; the packing keeps every id."""
    import corpus_pipeline

    stage = dict(corpus_pipeline.STAGES)
    rows = near_rows()
    rows += [(10**6 + d, t.upper()) for d, t in rows[::7]]
    last = {t.lower(): d for d, t in sorted(rows)}
    out = stage["exact dedup"](spark, spark.createDataFrame(rows, "doc_id long, text string"), SF)
    exact = {r["doc_id"]: r["text"] for r in out.collect()}
    assert exact == {d: t for d, t in rows if last[t.lower()] == d}

    docs = spark.createDataFrame(list(exact.items()), "doc_id long, text string")
    near = {r["doc_id"]: r["text"] for r in stage["SimHash near-dedup"](spark, docs, SF).collect()}
    gone = brute_groups(list(exact.items()))
    assert near == {d: t for d, t in exact.items() if d not in gone}

    out = stage["suffix-array dedup"](spark, spark.createDataFrame(list(near.items()), "doc_id long, text string"), SF)
    got = {r["doc_id"]: hashlib.sha256(r["text"].encode()).hexdigest() for r in out.collect()}
    assert got == {d: r[3] for d, r in brute_passages(list(near.items())).items()}
    assert {r[0] for r in stage["best-fit packing"](spark, out, SF).select("doc_id").distinct().collect()} == set(got)


def test_blocks_evolve_on_every_level(spark):
    """Several blocks whose bins all stay on the first level are packed as well as one block."""
    sizes = hard_sizes(300)
    pieces = spark.createDataFrame([(i, 0, 0, s, 0) for i, s in enumerate(sizes)], packing.PIECE_SCHEMA)
    packed = packing.pack(pieces, block=150, islands=2, epochs=1, levels=2, keep_above=0.0).select("sequence_id").distinct().count()
    assert packed < len(packing.best_fit(sizes, 4096))
