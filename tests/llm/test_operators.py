"""The ten operators against brute force, and their defined results for odd input."""

from __future__ import annotations

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict
from fractions import Fraction

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from stepsql.llm import bpe, exact, html, langid, license, packing, quality, shard, simhash, topk
from stepsql.llm.common import pick

from ..oracle import duck_rows, spark_rows

DOCS = "doc_id bigint, text string"
ODD = [(1, None), (2, ""), (3, "Abc abc"), (4, "aBC ABC"), (4, "aBC ABC"), (None, "abc abc"), (5, "x " * 60_000), (6, "É é"), (7, "é é"), (None, None), (8, "123 !?"), (9, "\n\t ")]
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def odd(spark):
    """Nulls, empty and long texts, repeated rows, and extra columns whose names clash."""
    df = spark.createDataFrame(ODD, DOCS)
    return df.select("doc_id", "text", F.lit(1).alias("size"), F.lit("z").alias("print"), F.lit(2).alias("TEXT"), F.lit("w").alias("cut"))


def none(spark):
    return spark.createDataFrame([], DOCS)


def documents(spark, data):
    return spark.read.parquet(f"{data}/documents.parquet")


# --- shared helpers ---------------------------------------------------------------------------


def test_pick_takes_the_exact_name(spark):
    got = pick(odd(spark), "doc_id", "text")
    assert got.columns == ["doc_id", "text"] and got.schema["text"].dataType.simpleString() == "string"


@pytest.mark.parametrize("name", ["op1_license_scan", "op2_exact_dedup", "op8_exact_topk"])
def test_matches_sql(spark, data, name):
    from stepsql.llm import queries

    assert spark_rows(queries.QUERIES[name](spark, data)) == duck_rows(queries.ORACLE_SQL[name], data)


# --- 1 licences -------------------------------------------------------------------------------


def test_license_places(spark):
    rows = [
        (1, "CC-BY, cc by; all rights reserved. All Rights reserve"), (2, "general public general public license"), (3, None), (4, ""), (5, "ccKby cc é by"),
        (6, "Permission is hereby granted, free of charge, to any person obtaining one copy of this software and its associated documentation files"),
        (7, "cc by " * 3000), (7, "cc by " * 3000), (8, "kK all rights reserved"), (9, "allrights reserved ccby"),
    ]
    got = defaultdict(list)
    for r in license.scan(spark.createDataFrame(rows, DOCS).withColumn("Row", F.lit(1)).withColumn("w", F.lit(2))).collect():
        got[r.doc_id].append(r)
    assert (got[1][0].n_base, got[1][0].first_word, got[1][0].last_word, got[1][0].base_labels) == (3, 0, 4, "cc-by,reserved")
    assert (got[2][0].n_base, got[2][0].first_word, got[2][0].labels, got[2][0].score) == (1, 2, "gpl", 1.0)
    for k in (3, 4):
        assert (got[k][0].n_words, got[k][0].n_base, got[k][0].first_word, got[k][0].labels, got[k][0].score) == (0, 0, None, "", 0.0)
    assert got[5][0].n_base == 0 and got[9][0].n_base == 0
    assert got[6][0].labels == "mit" and 0.6 <= got[6][0].score < 1 and got[6][0].n_base == 0
    assert [r.n_base for r in got[7]] == [3000, 3000] and got[7][0].last_word == 5998
    assert (got[8][0].n_words, got[8][0].first_word) == (4, 1)
    assert license.scan(none(spark)).count() == 0
    assert license.scan(odd(spark)).count() == len(ODD)


def test_license_plan_is_native(spark, data):
    from stepsql.plans.inspect import plan_text

    assert not re.search("Python|Arrow|Pandas", plan_text(license.scan(documents(spark, data)), "simple"))


# --- 2 exact dedup ----------------------------------------------------------------------------


@pytest.mark.parametrize("block_bits", [1, 3, 8])
def test_quotient_filters_merge_without_loss(block_bits):
    r = np.random.default_rng(1)
    parts = [r.integers(0, 2**64, n, np.uint64) for n in (500, 3, 1, 2000)]
    parts.append(np.concatenate([parts[0][:50], parts[3][:20], parts[0][:10], np.full(100_000, 7, np.uint64), np.array([0, 0, 2**64 - 1, 2**64 - 1], np.uint64)]))
    parts.append(np.uint64(5 << 56) + r.integers(0, 40, 3000, np.uint64))  # one home, a long run
    runs = defaultdict(list)
    for p in parts:
        for block, f in exact.filters_of(p, block_bits).items():
            row = exact.to_row(block, f)
            runs[block].append(exact.from_row(*row[1:]))
            assert f.occupied.sum() == f.last.sum() and len(f.slots) >= len(f.occupied)
    got = Counter()
    for block, held in runs.items():
        value, count = exact.merge(held)
        assert (value[1:] > value[:-1]).all() and ((value >> np.uint64(64 - block_bits)) == block).all()
        got.update(dict(zip(value.tolist(), count.tolist())))
    assert got == Counter(int(v) for p in parts for v in p)


def test_dedup_of_odd_rows(spark):
    got = exact.dedup(odd(spark)).collect()
    assert len(got) == len(ODD)
    abc = [r for r in got if r.text_sha256 == hashlib.sha256(b"abc abc").hexdigest()]
    # one row of a group stays, also where its doc_id repeats
    assert Counter((r.doc_id, r.keep_id, r.group_size, r.kept) for r in abc) == Counter([(3, 4, 4, False), (4, 4, 4, True), (4, 4, 4, False), (None, 4, 4, False)])
    empty = [r for r in got if r.text_sha256 == hashlib.sha256(b"").hexdigest()]
    assert {(r.doc_id, r.keep_id, r.group_size, r.kept) for r in empty} == {(1, 2, 3, False), (2, 2, 3, True), (None, 2, 3, False)}
    assert all(r.kept and r.group_size == 1 for r in got if r.doc_id in (5, 6, 7))
    assert exact.dedup(none(spark)).count() == 0


def test_dedup_and_keep_have_one_law(spark):
    rows = [(None, "a b"), (None, "A b"), (None, "a B"), (7, "same"), (7, "same"), (7, "Same"), (None, "alone"), (3, "x"), (5, "X")]
    df = spark.createDataFrame(rows, DOCS)
    got = exact.dedup(df).collect()
    by = defaultdict(list)
    for r in got:
        by[r.text_sha256].append(r)
    assert all(sum(r.kept for r in held) == 1 and len(held) == held[0].group_size for held in by.values())
    assert {r.keep_id for r in got} == {None, 7, 5}
    kept = exact.keep(df).collect()
    assert sorted((r.doc_id or 0, r.text.lower()) for r in kept) == [(0, "a b"), (0, "alone"), (5, "x"), (7, "same")]


def test_colliding_prints_are_told_apart_by_bytes(spark, monkeypatch):
    monkeypatch.setattr(exact, "fingerprint", lambda digest: 7)
    rows = [(k, f"text {k % 3}") for k in range(9)]
    prints = spark.createDataFrame([(7,)] * 9, "print bigint")
    assert [(r.print, r.n) for r in exact.repeated_prints(prints).collect()] == [(7, 9)]
    got = exact.dedup(spark.createDataFrame(rows, DOCS)).collect()
    assert all(r.keep_id == 6 + r.doc_id % 3 and r.group_size == 3 for r in got)


def test_keep_one_row_of_each_text(spark):
    df = spark.createDataFrame(ODD, DOCS)
    got = exact.keep(df).collect()
    want = {(t or "").translate(LOWER) for _, t in ODD}
    assert len(got) == len(want) and {(r.text or "").translate(LOWER) for r in got} == want
    assert [r.doc_id for r in got if (r.text or "").lower() == "abc abc"] == [4]
    assert exact.keep(none(spark)).count() == 0


# --- 3 quality, 5 language ------------------------------------------------------------------------


def fold_of(i, k):
    return zlib.crc32(str(i).encode()) % k


def test_quality_is_accurate_on_held_out_rows(spark):
    top = "/root/testdata/sf0.1"
    docs, labels = documents(spark, top), spark.read.parquet(f"{top}/labels.parquet")
    got = quality.predict(docs, quality.fit(docs, labels)).join(labels.select("doc_id", "quality"), "doc_id").where("held_out").collect()
    assert len(got) > 500 and all(fold_of(r.doc_id, 3) == 1 and 0 <= r.score <= 1 for r in got)
    assert np.mean([r.predicted == r.quality for r in got]) > 0.97


def test_quality_tables_and_pairs():
    r = np.random.default_rng(3)
    x = r.random((3000, 4))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.5)).astype(float)  # nothing but an interaction
    m = quality.train(x, y)
    assert (0, 1) in m.double and np.mean((quality.score_features(x, m) > 0.5) == y) > 0.9


def test_quality_of_odd_rows(spark):
    labels = spark.createDataFrame([(1, 0), (3, 1), (None, 1), (5, None)], "doc_id bigint, quality int")
    got = quality.predict(odd(spark), quality.fit(odd(spark), labels)).collect()
    assert len(got) == len(ODD) and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in got)
    assert quality.fit(none(spark), labels) is None and quality.predict(none(spark), None).count() == 0
    assert {r.score for r in quality.predict(odd(spark), None).collect()} == {0.5}
    assert quality.keep(spark.createDataFrame(ODD, DOCS), None).count() == len(ODD)


def test_language_is_accurate_on_held_out_rows(spark):
    docs = documents(spark, "/root/testdata/sf0.1")
    model = langid.fit(docs)
    got = langid.predict(docs, model).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert all(fold_of(r.doc_id, 4) == 2 and 0 <= r.score <= 1 for r in got)
    assert np.mean([r.lang_pred == r.lang for r in got]) > 0.98
    assert langid.keep(docs, model).count() > 0.99 * docs.count()


def test_language_of_odd_rows(spark):
    docs = odd(spark).withColumn("lang", F.when(F.col("doc_id") > 2, F.lit("en")))
    got = langid.predict(docs, langid.fit(docs)).collect()
    assert len(got) == len(ODD)
    for r in got:
        text = dict((k, t) for k, t in ODD).get(r.doc_id)
        if r.doc_id in (1, 2, 8, 9):
            assert (r.lang_pred, r.score, r.rejected) == ("und", 0.0, True), text
        elif r.doc_id:
            assert r.lang_pred == "en"
    assert langid.fit(none(spark).withColumn("lang", F.lit(None).cast("string"))) is None
    assert langid.predict(none(spark), None).count() == 0


# --- 4 near duplicates ----------------------------------------------------------------------------


def slow_simhash(text):
    words = re.findall(rb"[^\x20\x09-\x0D]+", (text or "").translate(LOWER).encode())
    if not words:
        return 0
    parts = [b" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [b" ".join(words)]
    h = [xxhash.xxh64_intdigest(p, 42) for p in parts]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def slow_components(prints, ids):
    root = list(range(len(prints)))

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    p = np.array(prints, np.uint64)
    for i in range(len(p)):
        for j in np.flatnonzero(np.bitwise_count(p[i + 1 :] ^ p[i]) <= 2) + i + 1:
            root[find(int(j))] = find(i)
    low = {}
    for i, d in enumerate(ids):
        if d is not None:
            low[find(i)] = min(low.get(find(i), d), d)
    return [low.get(find(i)) for i in range(len(p))]


def test_simhash_of_odd_rows(spark):
    got = simhash.components(odd(spark)).collect()
    prints = [slow_simhash(t) for _, t in ODD]
    want = sorted(map(repr, zip([d for d, _ in ODD], [f"{p:016x}" for p in prints], slow_components(prints, [d for d, _ in ODD]))))
    assert sorted(repr((r.doc_id, r.fingerprint, r.component_id)) for r in got) == want
    assert simhash.components(none(spark)).count() == 0


@pytest.mark.parametrize("bucket", [64, 3])
def test_links_of_crowded_prints(spark, bucket):
    """Clusters of prints a few bits apart, with common halves; small buckets force the linear way."""
    r = random.Random(2)
    prints = set()
    for _ in range(12):
        base = r.getrandbits(64)
        for _ in range(25):
            p = base
            for _ in range(r.randint(0, 5)):
                p ^= 1 << r.randrange(64)
            prints.add(p)
        prints |= {base ^ 3 << 40 | r.getrandbits(16) for _ in range(15)}
    chain = r.getrandbits(64)
    for k in range(0, 40, 2):
        prints.add(chain)
        chain ^= 3 << k
    prints = sorted(prints)
    signed = [int(np.uint64(p).astype(np.int64)) for p in prints]
    edges = simhash.links(spark.createDataFrame([(p,) for p in signed], "print bigint"), simhash.Config(bucket=bucket, sample=200))
    assert all((a ^ b).bit_count() <= 2 for a, b in ((int(np.int64(e.a).astype(np.uint64)), int(np.int64(e.b).astype(np.uint64))) for e in edges.collect()))
    star = {e.a: e.b for e in simhash.connect(edges).collect()}
    got = [star.get(p, p) for p in signed]
    want = slow_components(prints, list(range(len(prints))))
    assert len(set(zip(got, want))) == len(set(got)) == len(set(want))


def test_thresholds_spend_the_budget():
    r = np.random.default_rng(4)
    known = r.integers(0, 2**64, 300, np.uint64)
    order, widths = simhash.bit_order(known, 3)
    assert sorted(order) == list(range(64)) and sum(widths) == 64
    parts = simhash._partition_values(simhash.reorder(known, order), widths)
    t = simhash.thresholds(parts, parts, widths, 1e6, simhash.Config())
    assert ((t + 1).sum(1) == 3).all() and (t >= -1).all()


def test_connect_joins_long_paths(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(60)] + [(100, 101), (103, 101)], "a bigint, b bigint")
    star = {e.a: e.b for e in simhash.connect(edges).collect()}
    assert star == {k: 0 for k in range(1, 61)} | {101: 100, 103: 100}


# --- 6 shards ---------------------------------------------------------------------------------


def check_shards(rows, texts, shards=8):
    assert Counter(r.doc_id for r in rows) == Counter(d for d, _ in texts)
    size = {d: len((t or "").encode()) + 1 for d, t in texts}
    by = defaultdict(list)
    for r in rows:
        assert r["size"] == size[r.doc_id] and r.text_crc32 == zlib.crc32((dict(texts)[r.doc_id] or "").encode()) and r.law == "bytes" and r.grown_shard is None
        by[r.shard].append(r)
    assert all(0 <= s < shards for s in by) and all(sorted(r.slot for r in v) == list(range(len(v))) for v in by.values())
    where = defaultdict(set)
    for r in rows:
        where[dict(texts)[r.doc_id] or ""].add(r.shard)
    assert all(len(v) == 1 for v in where.values())
    return {s: sum(r["size"] for r in v) for s, v in by.items()}


def test_shards(spark, data):
    docs = documents(spark, data)
    texts = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    totals = check_shards(shard.shard(docs, shard.Config(unit=10, parcels=64)).collect(), texts)
    assert len(totals) == 8 and max(totals.values()) - min(totals.values()) < 0.05 * sum(totals.values())
    hot = [(k, "same text " * 9) for k in range(300)] + [(k, f"other {k}") for k in range(300, 600)]
    check_shards(shard.shard(spark.createDataFrame(hot, DOCS), shard.Config(unit=20)).collect(), hot)
    assert shard.shard(none(spark)).count() == 0 and shard.shard(odd(spark)).count() == len(ODD)


def test_best_fit_takes_the_tightest_bin():
    assert shard.best_fit_decreasing([7, 6, 3, 4], 10) == [0, 1, 0, 1]
    r = random.Random(1)
    for _ in range(20):
        sizes, cap = [r.randint(1, 60) for _ in range(80)], 100
        bins, want = [], []
        for i in sorted(range(80), key=lambda i: -sizes[i]):
            fits = [(left, k) for k, left in enumerate(bins) if left >= sizes[i]]
            k = min(fits)[1] if fits else len(bins)
            bins += [cap] if k == len(bins) else []
            bins[k] -= sizes[i]
            want.append((i, k))
        assert shard.best_fit_decreasing(sizes, cap) == [k for _, k in sorted(want)]
    assert max(shard.best_fit_decreasing([50, 5, 5], 10)) == 1


def test_shards_of_a_capacity(spark):
    rows = [(k, "x" * (k % 50)) for k in range(200)]
    got = shard.shard(spark.createDataFrame([(k, f"{k} {t}") for k, t in rows], DOCS), capacity=500).groupBy("shard").agg(F.sum("size").alias("s")).collect()
    assert all(r.s <= 500 for r in got) and len(got) <= -(-sum(r.s for r in got) // 500) + 1


# --- 7 BPE ------------------------------------------------------------------------------------


def test_bpe_equals_the_library(spark, data):
    import public_tokenizers
    import tiktoken

    ranks = bpe.read_ranks(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
    library = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    r = random.Random(5)
    texts = [t for _, t in ODD if t] + ["日本語テキスト😀́" * 30, "a" * 3000, "<|endoftext|>", "\x00\x01", " \n\n  x"] + ["".join(chr(r.choice((r.randint(32, 126), r.randint(160, 1000), 0x4E00 + r.randint(0, 99)))) for _ in range(r.randint(1, 200))) for _ in range(200)]
    own = bpe.SegmentBpe(ranks, public_tokenizers.PATTERN)
    for t, ids in zip(texts, own.encode_all(texts)):
        assert np.frombuffer(ids, "<u4").tolist() == library.encode_ordinary(t)
        assert own.decode(ids) == t.encode()
    docs = documents(spark, data)
    for r in bpe.encode_documents(docs).join(docs.select("doc_id", "text"), "doc_id").limit(50).collect():
        ids = np.array(library.encode_ordinary(r.text), "<u4").tobytes()
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(r.text.encode()).hexdigest())


def test_bpe_of_odd_rows(spark):
    got = bpe.encode_documents(odd(spark)).collect()
    assert len(got) == len(ODD) and {r.n_tokens for r in got if r.doc_id in (1, 2)} == {0}
    assert {r.decoded_sha256 for r in got if r.doc_id == 1} == {hashlib.sha256(b"").hexdigest()}
    back = {r.doc_id: r.text for r in bpe.decode_ids(bpe.encode_documents(odd(spark))).collect()}
    assert back[5] == "x " * 60_000 and back[6] == "É é"
    assert bpe.encode_documents(none(spark)).count() == 0


# --- 8 top-k ----------------------------------------------------------------------------------


def slow_top(rows, k=5):
    q = {}
    for i, v in rows:
        if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v):
            q.setdefault(i, []).append([int(256 * Fraction(x) // 1) for x in v])
    out = []
    for i, own in q.items():
        if i % 50 == 0:
            scores = sorted((-sum(a * b for a, b in zip(min(own), v)), j) for j, vs in q.items() if j != i for v in vs)
            scores = [x for x in scores if -(2**63) <= -x[0] < 2**63]
            out += [(i, n + 1, j, -s) for n, (s, j) in enumerate(scores[:k])]
    return sorted(out)


@pytest.mark.parametrize("spread", [0.1, 3.0])
def test_top_k_equals_brute_force(spark, spread):
    r = np.random.default_rng(6)
    rows = [(k, [float(x) for x in r.normal(0, spread, 16)]) for k in range(400)]
    rows += [(k, rows[7][1]) for k in range(400, 460)]  # ties
    rows += [(500, None), (501, [float("nan")] * 16), (502, [None] + [0.1] * 15), (503, [float("inf")] * 16), (None, [1.0] * 16), (504, [0.5] * 9), (505, []), (550, [0.0] * 16), (600, [1e30] * 16), (601, [600_000.0] + [0.1] * 15), (650, [5e6, -3.5] + [0.2] * 14), (50, [None] + [0.5] * 15), (700, [float("nan")]), (700, [0.25] * 16)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>").withColumn("rank", F.lit(1)).withColumn("Score", F.lit(2))
    got = topk.top_k(df, df.where("vec_id % 50 = 0"), topk.Config(queries=4, rows=100))
    assert sorted(map(tuple, got.select("query_id", "rank", "vec_id", "score").collect())) == slow_top(rows)


def test_top_k_of_few_rows(spark):
    df = spark.createDataFrame([(0, [0.5]), (1, [0.25]), (3, [0.5])], "vec_id bigint, embedding array<float>")
    assert sorted(map(tuple, topk.top_k(df, df.where("vec_id = 0")).collect())) == [(0, 1, 3, 16384), (0, 2, 1, 8192)]
    assert topk.top_k(df.limit(0), df.limit(0)).count() == 0
    assert topk.top_k(df, df.where("vec_id = 99")).count() == 0


# --- 9 HTML -----------------------------------------------------------------------------------


def test_main_text():
    page = (
        '<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var t="</p>";</script></head><body><header><h1>Site</h1></header><nav><ul><li>Menu</ul></nav><!-- ad --><div class="ad">Buy</div>'
        '<div class="cookie-notice">We use</div><article><h1>Ti&amp;tle\xa0 x</h1><p><b>One<br>two <p>Three &lt;b&gt;&#233;</p><aside>s</aside><form><input value=1>f</form><ul><li>a<li>b</ul>tail<div class="share">s</div></article>'
        '<div id="comments"><p>Reader</p></div><aside>Side</aside><footer>&copy; F</footer></body></html>'
    )
    assert html.main_text(page) == "Ti&tle x\nOne two\nThree <b>é\na\nb\ntail"
    assert html.main_text(None) == "" and html.main_text("") == "" and html.main_text("<p>") == ""
    assert html.main_text("plain &amp; text") == "plain & text"
    assert html.main_text("<body><p>a<article class='comment'><p>no</article><p>b") == "a\nb"
    assert html.main_text("<body><p data-state='hidden' title=\"id\">a<p hidden>b<div class='x article-body'>c<div class=ad>d</div></div>") == "c"
    assert html.main_text("<article><p>" + "word " * 50_000 + "</article>") == ("word " * 50_000).strip()


def test_style_tree_cuts_what_a_host_repeats(spark):
    """Pages without an article element: the repeated strap goes, by entropy; the varying text stays."""
    rows = [(k, f"http://h.example/{k}", f'<body><div class="strap">Welcome to us</div><div class="c"><p>Text number {k} of many</p></div></body>') for k in range(20)]
    rows += [(k, f"http://copies.example/{k}", "<body><div><p>All the same</p></div></body>") for k in range(30, 40)]
    rows += [(100, "http://one.example/", '<body><div class="strap">Welcome to us</div><p>Only</p></body>'), (101, None, "<p>no host"), (102, "x", None), (103, "http://h.example/z", "")]
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string").withColumn("host", F.lit("clash")).withColumn("cut", F.lit(1))
    got = {r.page_id: r.text for r in html.extract(df).collect()}
    assert all(got[k] == f"Text number {k} of many" for k in range(20))
    assert all(got[k] == "All the same" for k in range(30, 40))
    assert got[100] == "Welcome to us\nOnly" and got[101] == "no host" and got[102] == "" and got[103] == ""
    nodes = html.importance(df.drop("host").withColumn("host", F.lit("h")))
    assert nodes.where("presentation < -1e-9 or presentation > 1 + 1e-9 or content < -1e-9 or content > 1 + 1e-9").count() == 0
    assert html.extract(df.limit(0)).count() == 0


def test_copied_articles_stay_whole(spark):
    page = "<body><nav>m</nav><article><p>Shared passage</p></article></body>"
    df = spark.createDataFrame([(k, f"http://h.example/{k}", page) for k in range(30)], "page_id bigint, url string, html string")
    assert {r.text for r in html.extract(df).collect()} == {"Shared passage"}


# --- 10 packing -------------------------------------------------------------------------------


def check_packing(rows, capacity=2048):
    by = defaultdict(list)
    for r in rows:
        by[r.sequence_id].append((r.offset, r.length))
    for v in by.values():
        at = 0
        for offset, length in sorted(v):
            assert offset == at
            at += length
        assert at <= capacity
    return len(by)


def test_packing_of_documents(spark, data):
    from tokenizers import Tokenizer

    import public_tokenizers

    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    docs = documents(spark, data).limit(60).unionByName(spark.createDataFrame([(9001, "日本 text <|endoftext|> end", "x", "y", 1), (9002, None, None, None, None), (9003, "", "x", "y", 0)], documents(spark, data).schema))
    rows = packing.pack(docs).collect()
    check_packing(rows)
    pieces = defaultdict(list)
    for r in rows:
        pieces[r.doc_id].append(r)
    for d in docs.collect():
        ids = np.array(library.encode(d.text or "", add_special_tokens=False).ids + [0], "<u4")
        own = sorted(pieces[d.doc_id], key=lambda r: r.piece)
        assert [r.piece for r in own] == list(range(len(own))) and sum(r.length for r in own) == len(ids)
        assert all(r.ids_crc32 == zlib.crc32(ids[r.start : r.start + r.length].tobytes()) for r in own)
        assert len(own) == -(-len(ids) // 2048)


def test_usual_texts_split_alike_in_both_libraries():
    import public_tokenizers

    vocabulary, ranks = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken")
    whole, fast = packing._encoders(vocabulary, ranks)
    for c in [*range(0x250), *range(0x2010, 0x2028), 0x20AC]:
        for t in (f"a{chr(c)}b {chr(c)}1 {chr(c)}{chr(c)}\n", f"{chr(c)} {chr(c)}s"):
            assert fast(t) == whole.encode(t, add_special_tokens=False).ids, hex(c)


def test_local_search_empties_bins():
    # best-fit-decreasing needs four bins where three do
    lengths = [6, 6, 5, 5, 4, 2, 2]
    start = packing.best_fit(lengths, 10)
    end = packing.improve(start, lengths, 10)
    assert sorted(i for b in end for i in b) == list(range(7)) and all(sum(lengths[i] for i in b) <= 10 for b in end)
    assert len(end) == 3
    gained = 0
    r = random.Random(4)
    for _ in range(30):
        lengths = [r.randint(500, 1000) for _ in range(120)]
        start = packing.best_fit(lengths, 2048)
        end = packing.improve(start, lengths, 2048)
        assert sorted(i for b in end for i in b) == list(range(120)) and all(sum(lengths[i] for i in b) <= 2048 for b in end)
        gained += len(start) - len(end)
    assert gained > 0


def test_packing_of_odd_rows(spark):
    rows = packing.pack(odd(spark), packing.Config(cell=4)).collect()
    check_packing(rows)
    assert Counter(r.doc_id for r in rows if r.piece == 0) == Counter(d for d, _ in ODD)
    assert packing.pack(none(spark)).count() == 0


def test_packing_spreads_rows_that_are_all_alike(spark):
    docs = spark.range(400).selectExpr("cast(null as bigint) doc_id", "'same text' text").repartition(4)
    rows = packing.pack(docs, packing.Config(cell=40)).collect()
    assert len(rows) == 400 and len({r.sequence_id >> 32 for r in rows}) > 3
    used = {}
    for r in rows:
        used.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in used.values():
        parts.sort()
        assert all(o == sum(n for _, n in parts[:k]) for k, (o, _) in enumerate(parts)) and sum(n for _, n in parts) <= 2048
