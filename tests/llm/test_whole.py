"""The whole job where parts of it were once left out."""

from __future__ import annotations

import random
from itertools import combinations

from pyspark.sql import functions as F

from stepsql.llm import html, license, packing, shard


def texts_of(spark, pages, config=html.Config()):
    df = spark.createDataFrame([(k, f"http://h.example/{k}", p) for k, p in enumerate(pages)], "page_id bigint, url string, html string")
    return {r.page_id: r.text for r in html.extract(df, config).collect()}


def test_style_tree_judges_around_and_in_articles(spark):
    """Body text beside a small or empty article stays, what the site repeats goes, also from inside an article."""
    got = texts_of(spark, [f'<body><div class="strap">Welcome</div><div class="article-meta">By writer {k}</div><div class="c"><p>Body {k}</p></div></body>' for k in range(20)])
    assert all(got[k] == f"By writer {k}\nBody {k}" for k in range(20))
    got = texts_of(spark, [f"<body><p>Body {k}</p><article></article></body>" for k in range(20)])
    assert all(got[k] == f"Body {k}" for k in range(20))
    got = texts_of(spark, [f'<body><article><h1>Title {k}</h1><p>A long enough text, number {k}</p><div class="strap">Read on</div></article></body>' for k in range(20)])
    assert all(got[k] == f"Title {k}\nA long enough text, number {k}" for k in range(20))
    got = texts_of(spark, [f'<body><div class="strap">Welcome</div><article><h1>Title {k}</h1><p>A passage that is copied to every page</p></article></body>' for k in range(20)])
    assert all(got[k] == f"Title {k}\nA passage that is copied to every page" for k in range(20))


def test_parcels_beyond_a_capacity(spark):
    """Small groups whose parcels would pass the capacity: every shard keeps to it, and few are part empty."""
    docs = spark.range(3000).selectExpr("id doc_id", "concat(id, repeat(' x', int(id % 40))) text")
    docs = docs.unionByName(docs.where("doc_id < 50"))
    for capacity in (2000, 4000):
        rows = shard.shard(docs, shard.Config(parcels=8, large=16), capacity)
        got = rows.groupBy("shard").agg(F.sum("size").alias("s"), F.count("*").alias("n"), F.max("slot").alias("last")).collect()
        assert sum(r.n for r in got) == 3050 and all(r.last == r.n - 1 for r in got)
        assert all(r.s <= capacity for r in got) and len(got) <= 1.05 * sum(r.s for r in got) / capacity + 1
    assert rows.groupBy("doc_id").agg(F.countDistinct("shard").alias("n")).where("n > 1").count() == 0


def exchanges(bins, lengths, capacity):
    """How many exchanges between underfull bins would still raise the sum of squared fills, by brute force."""
    fill = [sum(lengths[i] for i in b) for b in bins]
    found = 0
    for a, b in ((a, b) for a in range(len(bins)) for b in range(len(bins)) if a != b and fill[b] <= fill[a] < capacity):
        got = {lengths[i] for i in bins[b]}
        mine = [(), *((lengths[i],) for i in bins[a]), *((lengths[i], lengths[j]) for i, j in combinations(bins[a], 2))]
        found += any(0 < n - sum(m) <= capacity - fill[a] for n in got for m in mine)
        two = {lengths[i] + lengths[j] for i, j in combinations(bins[b], 2)}
        found += any(0 < t - lengths[i] <= capacity - fill[a] for t in two for i in bins[a])
    return found


def test_local_search_leaves_no_exchange():
    """The 49th piece of a length, and the pieces of a bin after the 24th, take part."""
    # 60 fuller bins hold pieces as long as the only one that fits
    lengths = [36, 14, 55, 35] + [59, 36] * 60
    start = [[2 * k, 2 * k + 1] for k in range(62)]
    end = packing.improve(start, lengths, 100)
    assert sorted(i for b in end for i in b) == list(range(len(lengths))) and exchanges(start, lengths, 100) > 0 and exchanges(end, lengths, 100) == 0
    # a bin of short pieces, whose 31st is the one to give
    lengths = [2] * 30 + [9, 10, 25, 30]
    assert max(sum(lengths[i] for i in b) for b in packing.improve([list(range(31)), [31, 32], [33]], lengths, 70)) == 70
    r = random.Random(7)
    for _ in range(20):
        lengths = [r.choice((3, 5, 8, 13, 13, 13, 21, 34)) for _ in range(150)]
        start = [[i, i + 50, i + 100] for i in range(50)]
        end = packing.improve(start, lengths, 102)
        assert sorted(i for b in end for i in b) == list(range(150)) and all(sum(lengths[i] for i in b) <= 102 for b in end)
        assert len(end) == -(-sum(lengths) // 102) or exchanges(end, lengths, 102) == 0


def test_notices_close_together_keep_their_label(spark):
    line, broken = "released under the mit license", "released under the new mit license"
    texts = ["; ".join([line] * 3), "; ".join([line, "licensed under the mit license x"] * 900), f"{line} mit license mit license mit license mit license", ". ".join([broken] * 4), "mit license " * 9]
    got = {r.doc_id: r for r in license.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")).collect()}
    assert [got[k].labels for k in range(5)] == ["mit", "mit", "mit", "mit", ""] and got[4].score == 0
    assert [got[k].score for k in range(3)] == [1.0, 1.0, 1.0] and got[3].labels == "mit" and got[3].score >= 0.6
    assert [(x["first"], x["grams"], x["share"]) for x in got[0].spans if x["share"] == 1 and x["grams"] == 4][:3] == [(0, 4, 1.0), (5, 4, 1.0), (10, 4, 1.0)]


def test_straps_of_a_small_section_are_cut_on_a_large_host(spark):
    """Three pages of 400, also where the cut branches are too many to broadcast."""
    pages = [f'<body><div class="rare">Section strap</div><div class="c"><p>Text {k}</p></div></body>' if k < 3 else f'<body><div class="c"><p>Text {k}</p></div></body>' for k in range(400)]
    for config in (html.Config(), html.Config(broadcast_rows=0)):
        assert texts_of(spark, [*pages, None], config) == {k: f"Text {k}" for k in range(400)} | {400: ""}
