from __future__ import annotations

import hashlib
import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from pathloom.llm import fingerprints, html_extraction, licenses, near_dedup, pieces, quality, suffix_dedup, token_counts
from pathloom.llm.common import CLEANUP, pick, shuffles_dropped, stored
from pathloom.llm.components import components
from pathloom.llm.decontamination import leaked_items
from pathloom.llm.fingerprints import containment, edited, likeness, merged, neighbour_fingerprints, read, sketch, written
from pathloom.llm.licenses import canonical, known_licenses, license_scan
from pathloom.llm.sharding import interleaved_shards

from .helpers import empty, hostile, hostile_rows, near_components, prose, repeated_bytes, small_documents

PIECES = public_tokenizers.path("piece_bpe_32k.model")
BYTES = public_tokenizers.path("byte_bpe_50k.json")


def by_id(df, key="doc_id"):
    return {r[key]: r for r in df.collect()}


def test_pick_ignores_clashing_columns(spark):
    assert pick(hostile(spark), "text").columns == ["text"]


# 1


def test_near_duplicates_against_brute_force(spark):
    docs = small_documents(spark)
    want = near_components({r["doc_id"]: r["text"] for r in docs.collect()})
    got = by_id(near_dedup.near_duplicates(docs))
    assert {i: (r["n_shingles"], r["component_id"]) for i, r in got.items()} == want
    assert all(r["kept"] == (i == r["component_id"]) for i, r in got.items())


def test_near_duplicates_of_hard_documents(spark):
    rows = near_dedup.near_duplicates(hostile(spark)).collect()
    assert len(rows) == len(hostile_rows())
    want = near_components({r[0]: r[1] for r in hostile_rows() if r[0] is not None})
    for r in rows:
        if r["doc_id"] is None:
            assert r["component_id"] is None and r["kept"]
        else:
            assert (r["n_shingles"], r["component_id"]) == want[r["doc_id"]]
    assert near_dedup.near_duplicates(empty(spark)).count() == 0


def test_loosely_alike_texts_are_joined_in_blocks(spark, monkeypatch):
    rng = random.Random(5)
    base = prose(77, 150).split()
    rows = []
    for i in range(150):
        w = list(base)
        for _ in range(rng.choice((2, 5, 6, 7))):
            w[rng.randrange(len(w))] = f"x{rng.random()}"
        rows.append((i, " ".join(w)))
    monkeypatch.setattr(near_dedup, "BLOCK", 40)
    got = by_id(near_dedup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")))
    assert {i: (r["n_shingles"], r["component_id"]) for i, r in got.items()} == near_components(dict(rows))


def test_false_block_links_are_not_taken(spark, monkeypatch):
    """Hashes that collide in the first round of blocks: full sets decide, and a second round finds the true links."""
    real = near_dedup._sets
    monkeypatch.setattr(near_dedup, "_sets", lambda seed: _colliding_sets if seed == near_dedup.SEED else real(seed))
    rows = [(i, f"{prose(31, 60)} {prose(100 + i // 2, 14 + i % 2)}") for i in range(16)]
    got = by_id(near_dedup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")))
    assert {i: (r["n_shingles"], r["component_id"]) for i, r in got.items()} == near_components(dict(rows))


def _colliding_sets(batches):
    """All texts have the same hashes."""
    import pyarrow as pa

    for batch in batches:
        same = np.arange(1, 40, dtype=np.uint64).tobytes()
        yield pa.RecordBatch.from_arrays([batch.column("key"), pa.array([same] * batch.num_rows, pa.binary())], names=["key", "hashes"])


def test_circulant_signature_estimates_similarity():
    a = np.arange(1, 2001, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    x, y = near_dedup.signature(np.sort(a[:1500]), 512), near_dedup.signature(np.sort(a[500:]), 512)
    assert abs((x == y).mean() - 0.5) < 0.1


def test_components_of_a_chain(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(100)] + [(200, 201), (7, 7), (201, 200)], "a long, b long")
    got = {r["node"]: r["component"] for r in components(edges).collect()}
    assert got == {i: 0 for i in range(101)} | {200: 200, 201: 200}


# 2


def test_sampled_pieces_are_lossless_and_reproducible(spark):
    docs = hostile(spark)
    out = pieces.sampled_pieces(docs, PIECES)
    rows = out.collect()
    texts = sorted((r[1] or "" for r in hostile_rows()))
    back = sorted(r["text"] for r in pieces.decoded(out, PIECES).collect())
    assert back == texts
    again = pieces.sampled_pieces(docs.repartition(3), PIECES).collect()
    assert sorted((str(r["doc_id"]), r["pieces"]) for r in rows) == sorted((str(r["doc_id"]), r["pieces"]) for r in again)
    assert all(r["n_pieces"] == len(r["pieces"]) for r in rows)
    assert pieces.sampled_pieces(empty(spark), PIECES).count() == 0
    digests = pieces.sampled_pieces(docs, PIECES, ids=False).collect()
    assert all(r["lossless"] for r in digests)


def test_draws_do_not_depend_on_what_was_seen_before():
    """Other texts before, and tables that start anew after every text, change nothing."""
    texts = [prose(i, 60) for i in range(12)]
    fresh, used = pieces.PieceSampler(PIECES, most_nodes=1), pieces.PieceSampler(PIECES)
    used.sample([prose(900 + i, 300) for i in range(40)], list(range(40)))
    for i, t in enumerate(texts):
        assert list(fresh.sample([t], [i])[0]) == list(used.sample([t], [i])[0])


def test_sampling_follows_the_lattice():
    model = pieces.PieceSampler(PIECES)
    word, n = "than", 20000
    found = {}
    for ids in model.sample([word] * n, list(range(n))):
        found[tuple(ids)] = found.get(tuple(ids), 0) + 1
    text = pieces.MARK + word
    ways = {(): 1.0}
    paths = {0: {(): 1.0}}
    for e in range(1, len(text) + 1):
        paths[e] = {}
        for s in range(e):
            if hit := model.ends.get(text[s:e]):
                for p, w in paths[s].items():
                    paths[e][(*p, hit[0])] = w * hit[1]
    ways = paths[len(text)]
    total = sum(ways.values())
    for p, w in ways.items():
        assert abs(found.get(p, 0) / n - w / total) < 0.02


def test_seeds_differ_by_row():
    model = pieces.PieceSampler(PIECES)
    text = prose(3, 200)
    a, b = model.sample([text, text], [1, 2])
    assert list(a) != list(b) and model.decode(a) == model.decode(b) == text


# 3


def test_leaks_and_reparameterised_questions(spark):
    item = "A train leaves Paris at 9 and drives 240 km in 3 hours while, says Anna, another train drives 100 km in 2 hours. How far are they?"
    other = "A train leaves Paris at 7 and drives 810 km in 5 hours while, says Boris, another train drives 320 km in 6 hours. How far are they?"
    mixed = "A train leaves Paris at 9 and drives 240 km in 3 hours while, says Anna, another train drives 100 km in 2 hours"
    benchmark = spark.createDataFrame([(1, item), (2, None), (3, "too short"), (None, item)], "item_id long, text string")
    docs = spark.createDataFrame(
        [(1, prose(1, 50) + " " + item + " " + prose(2, 50)), (2, prose(3, 30) + ". " + other), (3, prose(4, 80)), (4, None), (5, ""), (6, mixed), (None, item), (7, item.upper())],
        "doc_id long, text string",
    )
    got = {(r["doc_id"], r["item_id"]): r["kind"] for r in leaked_items(docs, benchmark).collect()}
    assert got[1, 1] == "verbatim" and got[2, 1] == "reparameterised" and got[6, 1] == "verbatim"
    assert not {3, 4, 5} & {d for d, _ in got}
    assert leaked_items(empty(spark), benchmark).count() == 0
    assert leaked_items(hostile(spark), benchmark.limit(0)).count() == 0
    assert leaked_items(hostile(spark), benchmark).count() == 0


@pytest.mark.parametrize(
    "item,leak,clean",
    [
        ("Tom has 3 apples. Tom buys 5 more. Tom eats 2. How many are left?", "Anna has 4 apples. Anna buys 6 more. Anna eats 1. How many are left?", "Anna sold all her pears. How many friends came by is not known."),
        ("McDonald sells three hats to O'Neil for twelve dollars each day", "Baker sells four hats to D'Arcy for thirty dollars each day", "Baker sells shoes"),
        ("what is love", "he asked: What is love? Nobody knew.", "what love is"),
        ("Kyoto", "They went to Kyoto in May.", "they went home"),
    ],
)
def test_short_items_names_and_numbers(spark, item, leak, clean):
    docs = spark.createDataFrame([(1, prose(1, 40) + " " + leak + " " + prose(2, 40)), (2, prose(3, 40) + " " + clean), (3, "1 2 3 4 5 6 7 8 9"), (4, item)], "doc_id long, text string")
    got = {r["doc_id"]: r["kind"] for r in leaked_items(docs, spark.createDataFrame([(1, item), (2, "")], "item_id long, text string")).collect()}
    assert 1 in got and got[4] == "verbatim" and 3 not in got
    assert 2 not in got


def test_tables_of_figures_find_only_items_of_figures(spark):
    docs = spark.createDataFrame([(1, " ".join(map(str, range(2000)))), (2, "sum 1 2 3 4 5 6 7 up")], "doc_id long, text string")
    items = spark.createDataFrame([(1, "sum 1 2 3 4 5 6 7 up"), (2, "900 901 902 903 904 905")], "item_id long, text string")
    assert {(r["doc_id"], r["item_id"]) for r in leaked_items(docs, items).collect()} >= {(2, 1), (1, 2)}
    assert (1, 1) not in {(r["doc_id"], r["item_id"]) for r in leaked_items(docs, items).collect()}


def test_reparameterised_leaks_are_recalled(spark):
    """Questions from one template with other names, numbers and units, hidden in prose, against plain items."""
    rng = random.Random(8)
    names, units = ["Ada", "Boris", "Carla", "Dmitri", "Elena", "Farid"], ["km", "kg", "hours", "dollars"]
    forms = [
        "{a} walks {x} {u} to the old mill and {b} walks {y} {u} to the new mill before {a} rests for {z} {u} near {b}",
        "If {a} gives {x} {u} of grain to {b} and keeps {y} {u} then how much grain did {a} have before {b} came with {z} {u}",
        "A shop of {a} sells {x} {u} on Monday while the shop of {b} sells {y} {u} so that {a} and {b} sell {z} {u} together",
    ]
    fill = lambda f: f.format(a=(p := rng.sample(names, 2))[0], b=p[1], u=rng.choice(units), **dict(zip("xyz", rng.sample(range(2, 900), 3))))
    items = [(i, fill(f)) for i, f in enumerate(forms)]
    docs = [(i * 100 + k, f"{prose(k, 30)} {fill(f)} {prose(k + 50, 30)}") for i, f in enumerate(forms) for k in range(12)] + [(1000 + k, prose(k, 80)) for k in range(30)]
    got = {(r["doc_id"], r["item_id"]) for r in leaked_items(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()}
    want = {(i * 100 + k, i) for i in range(3) for k in range(12)}
    assert len(want & got) >= 0.9 * len(want) and not got - want


def test_inconsistent_slots_are_no_leak(spark):
    item = "Take 5 red and 5 blue and 5 green balls then draw 5 of them at 5 o'clock for 5 days"
    wrong = "Take 1 red and 2 blue and 3 green balls then draw 4 of them at 6 o'clock for 7 days"
    rows = leaked_items(spark.createDataFrame([(1, wrong)], "doc_id long, text string"), spark.createDataFrame([(1, item)], "item_id long, text string"))
    assert rows.count() == 0


def test_leaks_on_small_tables(spark):
    docs = small_documents(spark)
    items = spark.read.parquet("/root/testdata/sf0.001/benchmark.parquet")
    plain = lambda t: " ".join((t or "").lower().split())
    want = {(d["doc_id"], i["item_id"]) for d in docs.collect() for i in items.collect() if plain(i["text"]) in plain(d["text"])}
    assert {(r["doc_id"], r["item_id"]) for r in leaked_items(docs, items).collect()} == want


# 4


def test_quality_held_out_accuracy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    score = quality.quality_scorer(docs, labels)
    rows = docs.join(labels, "doc_id").filter(quality.is_held_out(F.col("doc_id"))).select("quality", score("text").alias("score")).collect()
    assert rows and np.mean([(r["score"] >= quality.THRESHOLD) == bool(r["quality"]) for r in rows]) > 0.97


def test_quality_of_hard_documents(spark):
    labels = spark.createDataFrame([(0, 1), (12, 0), (None, 1), (5, None), (99, 0)], "doc_id long, quality int")
    docs = hostile(spark)
    score = quality.quality_scorer(docs, labels)
    rows = pick(docs, "text").select("text", score("text").alias("s")).collect()
    assert len(rows) == len(hostile_rows()) and all(0 <= r["s"] <= 1 for r in rows)
    score = quality.quality_scorer(empty(spark), labels.limit(0))
    assert {r["s"] for r in pick(docs, "text").select(score("text").alias("s")).collect()} == {0.5}


def test_neighbours_vote_as_by_brute_force():
    """Scores against plain loops over all labelled vectors."""
    texts = [prose(i, 40) if i % 2 else prose(i, 40).replace(" ", " !! ") for i in range(60)]
    x = quality._frequencies(texts)
    rows = [(np.flatnonzero(r), r[np.flatnonzero(r)]) for r in x]
    labels = np.array([float(i % 2) for i in range(60)])
    voter = quality.fit_voter(rows, labels)
    dense = x * 1.0
    having = (dense > 0).sum(axis=0)
    weighted = dense * (np.log(61 / (1 + having)) + 1)
    left, size, _ = np.linalg.svd(weighted, full_matrices=False)
    want = left[:, : quality.DIMENSIONS] * size[: quality.DIMENSIONS]
    want /= np.linalg.norm(want, axis=1, keepdims=True)
    assert np.allclose(want @ want.T, voter.vectors @ voter.vectors.T, atol=0.02)
    for text in [prose(100, 30), prose(101, 30).replace(" ", " !! "), ""]:
        z = voter.project(quality._frequencies([text]))[0]
        near = sorted(((float(z @ v), y) for v, y in zip(voter.vectors, voter.labels)), reverse=True)[: quality.NEIGHBOURS]
        votes = sum(max(c, 0) * y for c, y in near) + quality.PRIOR_VOTES * voter.prior
        score = votes / (sum(max(c, 0) for c, _ in near) + quality.PRIOR_VOTES)
        assert abs(voter.scores([text])[0] - score) < 1e-4


def test_texts_that_differ_in_words_only_differ(spark):
    a, b = quality._frequencies(["the red house stands here", "der neue Motor lief lange"])
    assert float(a @ b) / float(np.linalg.norm(a) * np.linalg.norm(b)) < 0.8


def test_scored_documents_of_hard_tables(spark):
    labels = spark.createDataFrame([(0, 1, 9), (0, 0, 9), (12, 0, 9), (None, 1, 9), (5, None, 9), (18, 1, 9)], "doc_id long, quality int, DOC_ID int")
    rows = quality.scored_documents(hostile(spark), labels).collect()
    assert len(rows) == len(hostile_rows()) and all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= quality.THRESHOLD) for r in rows)
    assert quality.scored_documents(empty(spark), labels).count() == 0


def test_held_out_rows(spark):
    got = by_id(spark.range(50).select(F.col("id").alias("doc_id"), quality.is_held_out(F.col("id")).alias("h")))
    assert {i for i, r in got.items() if r["h"]} == {i for i in range(50) if zlib.crc32(str(i).encode()) % 4 == 2}


# 5


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(BYTES)


def test_token_counts_are_the_librarys(spark, library):
    docs = hostile(spark)
    got = token_counts.token_counts(docs, BYTES).collect()
    want = sorted(((r[0] if r[0] is not None else -1), len((r[1] or "").encode()), len(library.encode(r[1] or "", add_special_tokens=False).ids)) for r in hostile_rows())
    assert sorted(((r["doc_id"] if r["doc_id"] is not None else -1), r["n_bytes"], r["n_tokens"]) for r in got) == want
    assert all(r["over_limit"] == (r["n_tokens"] > 1024) for r in got)
    assert token_counts.token_counts(empty(spark), BYTES).count() == 0


def test_long_texts_are_counted_by_chunks(spark, library):
    """Texts without white space, runs longer than a chunk, special strings over seams; several rounds of composition."""
    texts = ["w" * 700, "日本語、" * 200, "ab12-" * 300 + "<|endoftext|>" * 40 + prose(3, 200), prose(4, 400), "a" * 31, "\n \n" * 200 + "x"]
    docs = spark.createDataFrame([(i % 4, t) for i, t in enumerate(texts + texts)], "doc_id long, text string")
    for chunk in (3, 31):
        got = sorted((r["n_bytes"], r["n_tokens"]) for r in token_counts.token_counts(docs, BYTES, chunk=chunk).collect())
        assert got == sorted((len(t.encode()), len(library.encode(t, add_special_tokens=False).ids)) for t in texts + texts)


def test_chunk_maps_compose_anywhere(library):
    t = token_counts.transducer(BYTES)
    rng = random.Random(1)
    letters = "ab'sT tré \n\t  1²½٣_-.,!日本ñ\U0001f600\u0085"
    for _ in range(600):
        text = "".join(rng.choice(letters) if rng.random() < 0.9 else "<|endoftext|>" for _ in range(rng.randint(0, 60)))
        want = len(library.encode(text, add_special_tokens=False).ids)
        assert t.count(text) == want == t.count_by_chunks(text, rng.choice((1, 2, 3, 7, 20, 1000))), repr(text)


# 6


PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var t="</p><article>no</article>";</script></head><body>
<header><h1>Site</h1></header><nav><ul><li><a href="/a">A</a><li>B</ul></nav><div class="cookie-notice">We use cookies</div><div class="ad">Buy</div>
<article><header><h1>Title &amp; more</h1></header><p>First   <b>bold</b>
line.<br>Second&nbsp;line<p>Unclosed &lt;para&gt; <i>it<p>Third<aside>side</aside><form>mail</form><ul><li>one<li>two</ul><div id="comments"><p>reader</p></div></article>
<footer>&copy; x</footer></body></html>"""


def test_main_text_of_a_page():
    want = "Title & more\nFirst bold line. Second line\nUnclosed <para> it\nThird\none\ntwo"
    assert html_extraction.main_text(PAGE) == want
    cut = PAGE[: PAGE.index("Third") + 3] + "<foo"
    assert html_extraction.main_text(cut).endswith("it\nThi")
    assert html_extraction.main_text(None) == html_extraction.main_text("") == ""
    assert html_extraction.main_text("plain & simple\n text") == "plain & simple text"
    assert html_extraction.main_text("<div>" * 3000 + "deep") == "deep"


@pytest.mark.parametrize("attrs", ['style="overflow:hidden"', 'title="hidden gems"', 'href="/hidden/x"', 'href="/x?id=search"', "href=/x?id=search", 'data-id="search"', 'data-class="ad"'])
def test_attributes_that_only_look_like_names_drop_nothing(attrs):
    assert html_extraction.main_text(f"<body><div {attrs}>kept</div></body>") == "kept"


def test_names_inside_content_must_be_whole():
    page = '<article><h2 id="search-and-rescue">Rescue</h2><section id="related-work">Others</section><div class="x share">Share</div><p id=search>Find</p><p HIDDEN>no</p></article>'
    assert html_extraction.main_text(page) == "Rescue\nOthers"
    assert html_extraction.main_text('<div class="site-search">no</div><div role="alert x">no</div><div aria-hidden=true>no</div>yes') == "yes"


def test_wrappers_find_the_content_region(spark):
    page = lambda i: f"<html><body><div><p>Our site</p><p>Since 1999</p></div><div><div><h2>{prose(i, 5)}</h2><p>{prose(i + 50, 30)}</p></div><p>All rights</p></div></body></html>"
    rows = [(i, f"http://h.example/{i}", page(i)) for i in range(8)] + [(50, "http://lone.example/", page(50)), (51, None, None), (None, "x", ""), (52, "http://h.example/52", None)]
    pages = spark.createDataFrame([(*r, "clash") for r in rows], "page_id long, url string, html string, HTML string")
    got = by_id(html_extraction.extracted_pages(pages), "page_id")
    assert len(got) == len(rows)
    for i in range(8):
        assert got[i]["text"] == f"{prose(i, 5)}\n{prose(i + 50, 30)}"
        assert got[i]["n_chars"] == len(got[i]["text"])
    # the lone page is judged by itself: its text's place is found, what is constant elsewhere cannot be known
    assert f"{prose(50, 5)}\n{prose(100, 30)}" in got[50]["text"] and got[51]["text"] == "" == got[52]["text"]
    assert html_extraction.extracted_pages(pages.limit(0)).count() == 0


def test_a_deeply_nested_seed_keeps_its_hosts_wrapper(spark):
    deep = "<div>" * 600
    page = lambda i: f"<html><body><div><p>Our site</p></div><div>{deep if i == 0 else ''}<h2>{prose(i, 5)}</h2><p>{prose(i + 50, 30)}</p></div></body></html>"
    pages = spark.createDataFrame([(i, f"http://h.example/{i}", page(i)) for i in range(8)], "page_id long, url string, html string")
    got = by_id(html_extraction.extracted_pages(pages), "page_id")
    assert all("Our site" not in got[i]["text"] and prose(i + 50, 30) in got[i]["text"] for i in range(8))


def _largest(a, b):
    """Size of the largest mapping, by plain recursion."""
    x, y = html_extraction._elements(a), html_extraction._elements(b)
    best = [[0] * (len(y) + 1) for _ in range(len(x) + 1)]
    for i, c in enumerate(x, 1):
        for j, d in enumerate(y, 1):
            best[i][j] = max(best[i - 1][j], best[i][j - 1], best[i - 1][j - 1] + (_largest(c, d) if c.tag == d.tag else 0))
    return 1 + best[-1][-1]


def test_alignment_is_a_largest_mapping():
    rng = random.Random(3)

    def tree(depth):
        return "".join(f"<{t}>{tree(depth - 1) if depth else ''}</{t}>" for t in (rng.choice(("x", "y", "z")) for _ in range(rng.randint(0, 4))))

    for _ in range(150):
        a, b = html_extraction.parse(tree(3)), html_extraction.parse(tree(3))
        html_extraction.numbered(a), html_extraction.numbered(b)
        pairs = html_extraction.aligned(a, b)
        assert len(pairs) == _largest(a, b) and all(p.tag == q.tag for p, q in pairs)
        ahead = sorted((p.number, q.number) for p, q in pairs)
        assert [q for _, q in ahead] == sorted(q for _, q in ahead)


def test_long_lists_of_unlike_siblings_are_aligned():
    a = html_extraction.parse("".join(f"<div>{'<b></b>' * (i % 7)}</div>" for i in range(1500)))
    b = html_extraction.parse("".join(f"<div>{'<b></b>' * (i % 5)}</div>" for i in range(1600)))
    html_extraction.numbered(a), html_extraction.numbered(b)
    assert len(html_extraction.aligned(a, b)) > 1500


def _article_of(source):
    """The expected text of a table's page: its article's blocks, by a plain reading of these tables' markup."""
    import html
    import re

    body = re.search(r"<article>(.*)</article>", source, re.S)[1]
    body = re.sub(r"<!--.*?-->|<(script|style|form|aside|nav|footer)\b.*?</\1>", "", body, flags=re.S)
    body = re.sub(r"<br */?>", " ", body)
    lines = re.split(r"</?(?:p|h[1-6]|div|ul|ol|li|table|tr|td|th|tbody|thead|blockquote|pre|section|header|figure|figcaption|dl|dt|dd|hr)\b[^>]*>", body)
    found = (" ".join(html.unescape(re.sub(r"<[^>]*>", "", x)).split()) for x in lines)
    return "\n".join(x for x in found if x)


@pytest.mark.parametrize("renamed", [False, True])
def test_wrappers_find_the_articles_of_the_tables(spark, renamed):
    """With sectioning elements as plain ones no landmark and no layout helps: slots and constants decide."""
    pages = spark.read.parquet("/root/testdata/sf0.001/pages.parquet")
    want = {r["page_id"]: _article_of(r["html"]) for r in pages.collect()}
    if renamed:
        pages = pages.withColumn("html", F.regexp_replace("html", r"<(/?)(article|main|nav|header|footer)\b", "<$1div"))
    got = by_id(html_extraction.extracted_pages(pages), "page_id")
    assert {i: r["text"] for i, r in got.items()} == want


def test_a_second_layout_and_an_odd_seed_do_not_break_a_host(spark):
    page = lambda i: f"<html><body><div><p>Our site</p></div><article><h2>{prose(i, 5)}</h2><p>{prose(i + 50, 30)}</p></article><div><p>Imprint</p></div></body></html>"
    other = lambda i: f"<html><body><header>Shop</header><main><p>{prose(i, 40)}</p></main><aside>x</aside></body></html>"
    rows = [(0, "http://h.example/0", "<p>odd")] + [(i, f"http://h.example/{i}", page(i)) for i in range(1, 8)] + [(i, f"http://h.example/{i}", other(i)) for i in range(8, 15)]
    rows += [(i, f"http://h.example/{i}", page(3)) for i in range(20, 60)]  # copies count once
    got = by_id(html_extraction.extracted_pages(spark.createDataFrame(rows, "page_id long, url string, html string")), "page_id")
    assert got[0]["text"] == "odd"
    for i in range(1, 8):
        assert got[i]["text"] == f"{prose(i, 5)}\n{prose(i + 50, 30)}"
    assert all(got[i]["text"] == got[3]["text"] for i in range(20, 60)) and all(got[i]["text"] == prose(i, 40) for i in range(8, 15))


def test_names_of_a_sites_own_are_no_names(spark):
    page = lambda i: f"<html><body><div class='menu'><a href=x>{prose(i, 3)}</a></div><div class='related-widget'><p>{prose(i + 9, 60)}</p></div></body></html>"
    pages = spark.createDataFrame([(i, f"http://h.example/{i}", page(i)) for i in range(6)], "page_id long, url string, html string")
    got = by_id(html_extraction.extracted_pages(pages), "page_id")
    assert all(got[i]["text"] == prose(i + 9, 60) for i in range(6))


# 7


def _spans_result(df):
    kept = suffix_dedup.kept_bytes(F.col("text"), F.col("starts"), F.col("sizes"))
    return df.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2(kept, 256).alias("sha"))


@pytest.mark.parametrize("slice_bytes", [4 << 20, 2000])
def test_repeated_spans_against_brute_force(spark, monkeypatch, slice_bytes):
    monkeypatch.setattr(suffix_dedup, "SLICE_BYTES", slice_bytes)
    docs = small_documents(spark)
    want = repeated_bytes(sorted((r["doc_id"], r["text"]) for r in docs.collect()))
    got = {r[0]: tuple(r)[1:] for r in _spans_result(suffix_dedup.repeated_spans(docs)).collect()}
    assert got == want


def test_repeated_spans_of_hard_documents(spark):
    rows = {}
    for r in hostile_rows():
        rows.setdefault((r[0] if r[0] is not None else -1, r[1] or ""), None)
    ordered = sorted(rows)
    want = {}
    for k, v in repeated_bytes([((i, t), t) for i, t in ordered]).items():
        want[k] = v
    got = suffix_dedup.repeated_spans(hostile(spark))
    assert got.count() == len(hostile_rows())
    for r in _spans_result(got).join(pick(hostile(spark), "doc_id", "text"), "doc_id").collect():
        assert tuple(r)[1:5] == want[r["doc_id"], r["text"] or ""]
    assert suffix_dedup.repeated_spans(empty(spark)).count() == 0


def _colliding_texts():
    """Two different ASCII texts of 100 bytes whose first 64-bit fingerprints are equal."""
    odd, mask = [int(x) for x in suffix_dedup._ODD], (1 << 64) - 1
    mix = lambda x, i: (x ^ x >> 29) * odd[i] & mask
    turn = lambda s: s * odd[15] & mask ^ (s * odd[15] & mask) >> 32

    def unmix(y: int, i: int) -> int:
        y = y * pow(odd[i], -1, 1 << 64) & mask
        return y ^ y >> 29 ^ y >> 58

    a = prose(1, 60).encode()[:100]
    word = lambda at: int.from_bytes(a[at : at + 8], "little")
    state = 100
    for i in range(9):
        state = turn(state ^ mix(word(8 * i), i))
    goal = turn(state ^ mix(word(72), 9)) ^ mix(word(80), 10)
    for k in range(1 << 16):
        other = f"{k:08d}".encode()
        rest = unmix(goal ^ turn(state ^ mix(int.from_bytes(other, "little"), 9)), 10).to_bytes(8, "little")
        if max(rest) < 128:
            return a.decode(), (a[:72] + other + rest + a[88:]).decode()
    raise AssertionError("none found")


def test_windows_with_one_equal_fingerprint_are_no_repeats(spark, monkeypatch):
    one, two = _colliding_texts()
    print_of = lambda t: suffix_dedup._fingerprints(np.frombuffer(t.encode() + bytes(16), np.uint8), np.array([0]), 100)[0]
    assert one != two and len(two) == 100 and print_of(one) == print_of(two)
    for slice_bytes in (4 << 20, 100):  # within a slice and across slices
        monkeypatch.setattr(suffix_dedup, "SLICE_BYTES", slice_bytes)
        docs = spark.createDataFrame([(1, one), (2, two), (3, two + "!")], "doc_id long, text string").coalesce(1)
        got = {r["doc_id"]: r["n_removed"] for r in suffix_dedup.repeated_spans(docs).collect()}
        assert got == {1: 0, 2: 0, 3: 100}


def test_kept_text_keeps_whole_characters(spark):
    rows = {r["doc_id"]: r for r in suffix_dedup.repeated_spans(hostile(spark)).select("doc_id", "text", "n_removed", suffix_dedup.kept_text(F.col("text"), F.col("starts"), F.col("sizes")).alias("new")).collect()}
    assert rows[15]["n_removed"] > 0 and "�" not in rows[15]["new"] and rows[15]["new"].endswith(prose(7, 30)[-20:])


# 8


def test_neighbour_fingerprints(spark):
    docs = small_documents(spark)
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    got = by_id(neighbour_fingerprints(docs))
    order = sorted(texts, reverse=True)
    prints = {}
    for i, j in zip(order, order[1:] + order[:1]):
        assert got[i]["n_chars"] == len(texts[i])
        assert got[i]["edited_sha256"] == hashlib.sha256(edited(texts[i], texts[j]).encode()).hexdigest()
        assert prints.setdefault(texts[i], got[i]["fingerprint"]) == got[i]["fingerprint"]
        assert got[i]["near_next"] == likeness(read(got[i]["fingerprint"]), read(got[j]["fingerprint"]))
        assert got[i]["near_edited"] == likeness(read(got[i]["fingerprint"]), read(got[i]["edited_fingerprint"]))
    assert np.mean([r["near_edited"] > r["near_next"] for r in got.values()]) > 0.9


def test_likeness_estimates_exact_similarity(spark):
    """Against exact Jaccard similarities of plain shingle sets."""
    docs = small_documents(spark)
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}

    def exact(a, b):
        x, y = near_dedup.shingle_set(a), near_dedup.shingle_set(b)
        return len(x & y) / len(x | y) if x | y else 1.0, len(x | y)

    order, got, errors = sorted(texts, reverse=True), by_id(neighbour_fingerprints(docs)), []
    for i, j in zip(order, order[1:] + order[:1]):
        for near, other in ((got[i]["near_next"], texts[j]), (got[i]["near_edited"], edited(texts[i], texts[j]))):
            want, n = exact(texts[i], other)
            if n >= 200:
                errors.append(abs(near - want))
    assert len(errors) > 100 and max(errors) < 0.25 and np.mean(errors) < 0.03


def test_ranges_by_bytes_and_digest(spark, monkeypatch):
    """Many ranges, one key with half of the rows, rows without a key: neighbours are those of the plain order."""
    monkeypatch.setattr(fingerprints, "RANGE_BYTES", 300)
    rows = [(7 if i % 2 else i, prose(i, 20)) for i in range(120)] + [(None, prose(500 + i, 10)) for i in range(20)]
    got = neighbour_fingerprints(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()
    order = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, hashlib.md5(r[1].encode()).hexdigest()), reverse=True)
    want = sorted((len(t), hashlib.sha256(edited(t, n).encode()).hexdigest()) for (_, t), (_, n) in zip(order, order[1:] + order[:1]))
    assert sorted((r["n_chars"], r["edited_sha256"]) for r in got) == want


def test_fingerprints_of_hard_documents(spark):
    rows = neighbour_fingerprints(hostile(spark)).collect()
    assert len(rows) == len(hostile_rows())
    assert all(0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1 for r in rows)
    assert {r["fingerprint"] for r in rows if r["doc_id"] in (4, 5, 6)} == {""}
    assert neighbour_fingerprints(empty(spark)).count() == 0
    assert neighbour_fingerprints(spark.createDataFrame([(1, "a b")], "doc_id long, text string")).count() == 1


def test_sketches_merge_and_estimate_containment():
    memo = near_dedup.WordHashes()
    long, part = prose(1, 4000), " ".join(prose(1, 4000).split()[:1000])
    a, b = sketch(long, memo), sketch(part, memo)
    assert containment(b, a) == 1.0 and abs(containment(a, b) - 0.25) < 0.05
    assert abs(likeness(a, b) - 0.25) < 0.05
    assert list(merged(a, b)) == list(a) and list(read(written(a))) == list(a)
    lone = sketch("just two", memo)
    assert len(lone) == 1 and list(read(written(lone))) == list(lone)


# 9


def test_shards_follow_the_mixture(spark):
    docs = small_documents(spark)
    rows = interleaved_shards(docs, 8).collect()
    assert len(rows) == docs.count()
    shards = {}
    for r in rows:
        shards.setdefault(r["shard"], []).append(r)
    counts = [len(v) for v in shards.values()]
    assert len(shards) == 8 and max(counts) - min(counts) <= 1
    sources = {}
    for r in rows:
        sources[r["source"]] = sources.get(r["source"], 0) + 1
    for v in shards.values():
        assert sorted(r["slot"] for r in v) == list(range(len(v)))
        for s, n in sources.items():
            assert abs(sum(r["source"] == s for r in v) - n / 8) <= 2
    text = {r["doc_id"]: r["text"] for r in docs.collect()}
    for r in rows:
        assert r["size"] == len(text[r["doc_id"]].encode()) + 16 and r["text_crc32"] == zlib.crc32(text[r["doc_id"]].encode())
    again = {r["doc_id"]: (r["shard"], r["slot"]) for r in interleaved_shards(docs.repartition(5), 8).collect()}
    assert again == {r["doc_id"]: (r["shard"], r["slot"]) for r in rows}


def test_shards_of_hard_documents(spark):
    rows = interleaved_shards(hostile(spark), 40).collect()
    assert len(rows) == len(hostile_rows()) and len({(r["shard"], r["slot"]) for r in rows}) == len(rows)
    assert {r["size"] for r in rows if r["doc_id"] == 4} == {16}
    assert interleaved_shards(empty(spark)).count() == 0


# 10


def test_license_digests(spark):
    known = known_licenses(spark)
    mit = next(text for i, _, text in licenses.TEXTS if i == "MIT")
    changed = ("MIT License\nCopyright (c) 2024 Somebody\n\n" + mit).replace(",", " ,").upper().replace("LICENSE", "LICENCE")
    docs = spark.createDataFrame(
        [(1, changed), (2, "released under the mit licence\n" + prose(1, 20)), (3, prose(2, 20)), (4, None), (5, ""), (None, "..."), (6, mit + " And more."), (7, "x\nSPDX-License-Identifier: AGPL-3.0")], "doc_id long, text string"
    )
    got = by_id(license_scan(docs, known))
    assert got[1]["license_id"] == "MIT" and got[2]["license_id"] is None and got[2]["notices"] == ["MIT"]
    assert got[3]["notices"] == [] and got[4]["text_digest"] is None and got[6]["license_id"] is None and got[7]["notices"] == ["AGPL-3.0"]
    assert license_scan(hostile(spark), known).count() == len(hostile_rows())
    assert license_scan(empty(spark), known).count() == 0
    assert docs.select(canonical(F.col("text")).alias("c")).filter("c like '%2024%'").count() == 0


def test_planted_licences_are_found_as_whole_texts(spark):
    """Every built-in text, wrapped, numbered otherwise and under another copyright line, among the tables' documents."""
    docs = small_documents(spark).select("doc_id", "text")
    planted = [(10_000 + k, i, f"Copyright {2000 + k} Someone\nAll rights reserved.\n\n" + text.replace(". ", ".\n   ").replace('"', "''")) for k, (i, _, text) in enumerate(licenses.TEXTS)]
    rows = docs.union(spark.createDataFrame([(k, t) for k, _, t in planted], "doc_id long, text string"))
    got = by_id(license_scan(rows, known_licenses(spark)))
    assert all(got[k]["license_id"] == i for k, i, _ in planted)
    assert all(r["license_id"] is None for k, r in got.items() if k < 10_000)


def test_licences_of_a_folder_and_another_language(spark, tmp_path):
    (tmp_path / "EUPL-de.txt").write_text("Lizenziert unter der EUPL, nicht früher als Version 1.2.")
    known = known_licenses(spark, licenses.licenses_in(spark, str(tmp_path)))
    docs = spark.createDataFrame([(1, "a\nLIZENZIERT unter der EUPL -- nicht früher als Version 1.2"), (2, "lizenziert unter der EUPL nicht früher als version 1 2!")], "doc_id long, text string")
    got = by_id(license_scan(docs, known))
    assert got[1]["notices"] == ["EUPL-de"] and got[2]["license_id"] == "EUPL-de"


def test_digests_of_long_licences(spark):
    """Held against the system's own copies, where it has them."""
    import os

    folder = "/usr/share/common-licenses"
    if not os.path.isdir(folder):
        pytest.skip("no licence texts here")
    texts = [(n, open(f"{folder}/{n}", encoding="utf-8").read()) for n in ("Apache-2.0", "GPL-3", "MPL-2.0")]
    got = license_scan(spark.createDataFrame([(i, t) for i, (_, t) in enumerate(texts)], "doc_id long, text string"), known_licenses(spark))
    assert {r["doc_id"]: r["license_id"] for r in got.collect()} == {0: "Apache-2.0", 1: "GPL-3.0", 2: "MPL-2.0"}


def test_operators_need_a_shared_folder_on_a_cluster():
    from types import SimpleNamespace

    from pathloom.llm.common import shared_dir

    def session(master, folder=None):
        context = SimpleNamespace(master=master, folder=folder)
        context.getCheckpointDir, context.setCheckpointDir = lambda: context.folder, lambda f: setattr(context, "folder", f)
        return SimpleNamespace(sparkContext=context, conf={})

    assert shared_dir(session("yarn", "/shared")) == "/shared"
    with pytest.raises(ValueError):
        shared_dir(session("local-cluster[3,1,1024]"))
    alone = session("local[2]")
    assert shared_dir(alone) == shared_dir(alone)


def test_page_features_are_found_once_for_equal_tags():
    from pathloom.llm import html_extraction as H

    H._features.cache_clear()
    page = '<div class="story lead">a</div>' * 40 + '<div data-x="' + "y" * 2000 + '" class="menu">b</div>'
    kinds = [(n.out, n.named) for n in H.numbered(H.parse(page))[1:]]
    assert kinds == [(False, False)] * 40 + [(False, True)]
    assert H._features.cache_info().misses == 1  # long attributes are not remembered


def test_repeats_are_the_same_in_several_rounds(spark, monkeypatch):
    docs = small_documents(spark).filter("doc_id < 100").select("doc_id", "text")
    columns = ["doc_id", "text", "n_removed", "n_spans", "starts", "sizes"]
    want = sorted(map(str, suffix_dedup.repeated_spans(docs).select(columns).collect()))
    monkeypatch.setattr(suffix_dedup, "ROUND_BYTES", 0)
    monkeypatch.setattr(suffix_dedup, "ROUNDS", 3)
    monkeypatch.setattr(suffix_dedup, "SLICE_BYTES", 3000)
    tables = []
    monkeypatch.setattr(suffix_dedup, "stored", lambda df, label, real=suffix_dedup.stored: tables.append(label) or real(df, label))
    assert sorted(map(str, suffix_dedup.repeated_spans(docs).select(columns).collect())) == want
    assert tables.count("later") == 3


def test_fitting_holds_one_matrix_of_all_pairs():
    import tracemalloc

    n, rng = 2048, np.random.default_rng(5)
    rows = [(np.sort(rng.choice(quality.TERMS, 20, replace=False)).astype("<u2"), rng.random(20).astype("<f4")) for _ in range(n)]
    labels = rng.integers(0, 2, n).astype(float)
    tracemalloc.start()
    quality.fit_voter(rows, labels)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 2.2 * 4 * n * n


def test_shuffled_files_go_with_their_execution(spark):
    """Within shuffles_dropped a stored table leaves no shuffled files behind, without waiting for a garbage collection."""
    disk = spark._jsc.sc().env().blockManager().diskBlockManager()

    def left(store):
        before = {f.getName() for f in files()}
        store()
        return sum(f.length() for f in files() if f.getName() not in before)

    def files():
        found = disk.getAllFiles().iterator()
        out = []
        while found.hasNext():
            out.append(found.next())
        return [f for f in out if f.getName().startswith("shuffle_") and f.getName().endswith(".data")]

    docs = spark.range(100_000).repartition(3, "id")
    assert left(lambda: stored(docs, "kept")) > 100_000
    with shuffles_dropped(spark):
        assert left(lambda: stored(docs, "dropped")) == 0
    assert spark.conf.get(CLEANUP) == "false"


def test_wrappers_are_made_once_for_each_pool_however_rows_alternate(monkeypatch):
    import pyarrow as pa

    from pathloom.llm import html_extraction as H

    page = lambda site, i: f"<body><div>menu of {site}</div><div><p>text {i} of the page</p><p>more {i * i}</p></div></body>"
    rows = [(site, page(site, i)) for i in range(20) for site in ("a", "b")]
    pools, html = ([r[k] for r in rows] for k in (0, 1))
    seeds = [page(site, 0) for site in pools]
    counted = next(H._counted(iter([pa.RecordBatch.from_arrays([pa.array(pools), pa.array(html), pa.array(seeds)], names=["pool", "html", "seed"])]))).to_pylist()
    stats = pa.array([[r for r in counted if r["pool"] == site] for site in pools])
    calls = []
    monkeypatch.setattr(H, "wrapper", lambda *a, f=H.wrapper: calls.append(1) or f(*a))
    batch = pa.RecordBatch.from_arrays([pa.array(range(40)), pa.array(pools), pa.array(pools), pa.array(html), pa.array(seeds), stats], names=["key", "url", "pool", "html", "seed", "stats"])
    texts = next(H._extracted(iter([batch]))).column("text").to_pylist()
    assert texts == [f"text {i} of the page\nmore {i * i}" for i in range(20) for _ in "ab"] and len(calls) == 2
