"""Cases at the edges of the training-data operators' methods, each against a plain form of its own."""

from __future__ import annotations

import math
import time
from collections import Counter, defaultdict

import pytest

from stepsql.llm import html, langid, license, packing, quality, shard

DOCS = "doc_id long, text string"


@pytest.mark.parametrize(
    ("text", "labels"),
    [
        ("licensed under licensed under licensed under", ""),
        ("licensed under the gpl, licensed under the bsd", ""),
        ("licensed under the eclipse license version 2 0", ""),
        ("This work is licensed under a Creative Commons Attribution 4.0 International License.", "cc-by"),
        ("This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.", "cc-by-nc"),
        ("This work is licensed under the GNU General Public License version 3", "gpl"),
        ("under the terms of the gnu general public license", "gpl"),
        ("this work is licensed under the gnu affero general public license version 3", "agpl,gpl"),
        ("license mit the under licensed", ""),
        ("it is licensed under the the mit license", "mit"),
        ("released under the mit license " * 3000, "mit"),
        ("released under a mit license. licensed under this the mit license, " * 500, "mit"),
    ],
)
def test_license_spans_are_verified(spark, text, labels):
    row = license.scan(spark.createDataFrame([(1, text)], DOCS)).first()
    assert row.labels == labels
    assert 0 <= row.score <= 1 and (row.score > 0) == bool(labels)


def _plain_labels(text: str) -> set[str]:
    """Labels by trying every template at every place and width, word by word."""
    config, words = license.Config(), text.split()
    grams = list(zip(words, words[1:]))
    spans = []
    for number, (template, label, need) in enumerate(config.templates):
        own = list(zip(template, template[1:]))
        if number < len(config.base):
            spans += [(label, None, 1.0, len(own)) for i in range(len(grams)) if grams[i : i + len(own)] == own]
            continue
        for first in sorted({i - p for i, g in enumerate(grams) for p, o in enumerate(own) if g == o}):
            by = {d: [p for p, o in enumerate(own) if 0 <= p + d < len(grams) and grams[p + d] == o] for d in range(first, first + config.slack + 1)}
            held, top = {}, -1
            for p in range(len(own)):
                at = next((p + d for d in sorted(by, key=lambda d: (-len(by[d]), d)) if p in by[d]), None)
                if at is not None and at > top:
                    held[p], top = at, at
            if len(held) >= config.least * len(own) and all(set(n) & set(held) for n in need):
                spans.append((label, set(held.values()), len(held) / len(own), len(own)))
    best = {}
    for label, places, share, n in spans:
        for at in places or ():
            best[at] = max(best.get(at, (0, 0, "")), (share, n, label))
    return {label for label, places, _, n in spans if places is None or sum(best[at][2] == label for at in places) >= config.least * n}


def test_license_labels_equal_a_plain_search(spark):
    import random

    draw = random.Random(4)
    notices = [words for words, _, _ in license.Config().templates]
    rows = []
    for i in range(120):
        words = []
        for _ in range(draw.randrange(1, 5)):
            part = list(draw.choice(notices))
            for _ in range(draw.randrange(0, 4)):
                k = draw.randrange(len(part))
                part[k : k + 1] = draw.choice([[], ["extra"], [part[k], "more"], [draw.choice(draw.choice(notices))]]) or part[k : k + 1][:0]
                if not part:
                    part = ["x"]
            words += part
        rows.append((i, " ".join(words)))
    got = {r.doc_id: set(r.labels.split(",")) - {""} for r in license.scan(spark.createDataFrame(rows, DOCS)).collect()}
    assert got == {i: _plain_labels(text) for i, text in rows}


@pytest.mark.parametrize("ids", ["cast(5 as bigint)", "cast(null as bigint)", "id % 3"])
def test_packing_deals_out_rows_whose_ids_repeat(spark, ids):
    docs = spark.range(400).selectExpr(f"{ids} doc_id", "'same text' text").repartition(4)
    rows = packing.pack(docs, packing.Config(cell=40)).collect()
    assert len(rows) == 400 and max(Counter(r.sequence_id >> 32 for r in rows).values()) < 120
    used = defaultdict(list)
    for r in rows:
        used[r.sequence_id].append((r.offset, r.length))
    for parts in used.values():
        parts.sort()
        assert all(o == sum(n for _, n in parts[:k]) for k, (o, _) in enumerate(parts)) and sum(n for _, n in parts) <= 2048


@pytest.mark.parametrize("ids", ["cast(5 as bigint)", "cast(null as bigint)", "id"])
def test_shards_number_rows_whose_ids_repeat(spark, ids):
    docs = spark.range(3000).selectExpr(f"{ids} doc_id", "if(id % 2 = 0, '', concat('text ', id % 7)) text").repartition(4)
    got = shard.shard(docs, shard.Config(unit=16))
    slots = defaultdict(list)
    for r in got.select("shard", "slot").collect():
        slots[r.shard].append(r.slot)
    assert sum(map(len, slots.values())) == 3000 and all(sorted(s) == list(range(len(s))) for s in slots.values())


def test_samples_are_bounded_where_ids_repeat(spark):
    # 0: an id in neither held-out fold
    docs = spark.range(2000).selectExpr("cast(0 as bigint) doc_id", "concat('some words here ', id % 900) text", "'en' lang")
    assert len(langid.sample(docs, langid.Config(sample=50))) < 200
    copies = spark.range(5000).selectExpr("cast(0 as bigint) doc_id", "'one text' text", "'en' lang")
    assert len(langid.sample(copies, langid.Config(sample=10_000))) == 1
    marks = spark.createDataFrame([(0, 1), (8, 0)], "doc_id long, quality int")
    assert quality.fit(docs.select("doc_id", "text"), marks) is None  # one row to learn from, one class


PAGES = "page_id long, url string, html string"


@pytest.mark.parametrize(
    "page",
    ["<a " * 350_000, "<div>" * 100_000 + "x" + "</i>" * 100_000 + "</div>" * 100_000, "<p><tr>" + "<b>" * 50_000 + "<hr>" * 50_000, "<!" * 300_000, "<a '" * 250_000, '<a "' * 250_001, "<script>" * 100_000, "<ul>" + "<li>a" * 100_000],
    ids=["tags without end", "nested", "rules in deep text", "declarations", "odd quotes", "even quotes", "raw", "list"],
)
def test_long_pages_take_linear_time(page):
    began = time.perf_counter()
    html.main_text(page, frozenset({3}))
    html.style_nodes(page)
    assert time.perf_counter() - began < 20


def test_deep_pages_are_read_through_spark(spark):
    deep = ["<div>" * 20_000 + f"deep text {i}" + "</div>" * 20_000 for i in range(4)]
    rows = [(i, "http://h.example/", f"<body><div class=strap>all alike</div>{deep[i]}{i}</body>") for i in range(4)]
    assert {r.text for r in html.extract(spark.createDataFrame(rows, PAGES)).collect()} == {f"deep text {i}\n{i}" for i in range(4)}


def test_the_tree_overrules_names(spark):
    """Large branches stay though their class names a role; small ones of the same name go."""
    story = " ".join(f"word{k}" for k in range(60))
    rows = [
        (i, "http://h.example/", f'<body><nav><a href=x>menu {i}</a></nav><div class="top-story"><p>{story} {i}</div><div class="side-content"><p>{story} b{i}</div><div class="alert-text"><p>{story} c{i}</div>'
         f'<div class="ad">Buy number {i}</div><footer>Foot {i}</footer></body>')
        for i in range(12)
    ]
    got = {r.page_id: r.text for r in html.extract(spark.createDataFrame(rows, PAGES)).collect()}
    assert got == {i: f"{story} {i}\n{story} b{i}\n{story} c{i}" for i in range(12)}


def test_straps_inside_articles_go(spark):
    rows = [(i, f"http://{h}.example/", f"<body><article><div class=strap>Read more from us</div><h1>Title {i}{h}</h1><p>Body {i} of {h} in words</p></article></body>") for h in "ab" for i in range(6)]
    got = {r.text for r in html.extract(spark.createDataFrame(rows, PAGES)).collect()}
    assert got == {f"Title {i}{h}\nBody {i} of {h} in words" for h in "ab" for i in range(6)}


def test_comments_go_however_long(spark):
    rows = [(i, "http://h.example/", f"<body><article><p>Short text {i}</p></article><div id=comments>{' '.join(f'remark{k}' for k in range(300))} {i}</div></body>") for i in range(5)]
    assert {r.text for r in html.extract(spark.createDataFrame(rows, PAGES)).collect()} == {f"Short text {i}" for i in range(5)}


def _plain_importance(pages: list[tuple[str, str]]) -> dict:
    """Entropies and shares of the style tree, node by node."""
    config = html.Config()
    seen = defaultdict(list)
    for host, page in pages:
        for path, role, _, shape, mark, words, around in html.style_nodes(page):
            seen[host, path].append((role, shape, mark, words, around))

    def entropy(values):
        values = [v for v in values if v is not None]
        m = len(values)
        return None if not m else 1.0 if m == 1 else -sum(c / m * math.log(c / m) for c in Counter(values).values()) / math.log(m)

    every = defaultdict(list)
    for (_, path), rows in seen.items():
        if max(r[0] for r in rows):
            every[path] += rows
    out = {}
    for (host, path), rows in seen.items():
        role, look, content = max(r[0] for r in rows), entropy([r[1] for r in rows]), entropy([r[2] for r in rows])
        if not role:
            out[host, path] = max(1.0 if content is None else content, look)
            continue
        mean = lambda k: sum(r[k] for r in every[path]) / len(every[path])  # noqa: B023, E731
        around = sum(r[4] for r in rows) + config.pages * mean(4)
        share = (sum(r[3] for r in rows) + config.pages * mean(3)) / around if around else 0.0
        known = 1.0 if len(rows) < config.support or content is None else content
        out[host, path] = known * (config.prior + (config.comment_weight if role == 2 else config.weight) * share)
    return out


def test_importance_equals_a_plain_tree(spark, data):
    pages = spark.read.parquet(f"{data}/pages.parquet").selectExpr("parse_url(url, 'HOST') host", "html")
    want = _plain_importance([tuple(r) for r in pages.collect()])
    got = {(r.host, r.path): r.importance for r in html.importance(pages).collect()}
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-9 for k in want)


def test_the_tree_decides_on_the_given_pages(spark, data):
    pages = spark.read.parquet(f"{data}/pages.parquet")
    cut = {r.page_id: r.text for r in html.extract(pages).collect()}
    uncut = {r.page_id: r.text for r in html.extract(pages, html.Config(least=0.0)).collect()}
    assert all(len(cut[k]) < len(uncut[k]) for k in cut)
