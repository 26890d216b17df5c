"""WARC, embeddings, packing, HTML, sharding and the pipeline on small fixtures."""

import base64
import hashlib
import importlib
import json
import random
import sys
import time
import zlib
from math import sqrt

import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from simweave.llm import embedding_dedup as E
from simweave.llm import html_text as H
from simweave.llm import packing as K
from simweave.llm import sharding as D
from simweave.llm import warc as W
from simweave.plans.staging import shared_dir

BPE = public_tokenizers.path("byte_bpe_50k.json")


def words(n, seed=0):
    r = random.Random(seed)
    return " ".join(f"w{r.randrange(900)}" for _ in range(n))


def test_warc_round_trip(spark, request):
    tricky = "a\r\n\r\nWARC/1.1\r\nContent-Length: 3\r\n\r\nb é"
    pages = [(1, "http://a/x", "one"), (2, None, "one"), (3, "http://a/\r\ny", None), (4, "u", ""), (5, "u", tricky), (9, "u", "one"), (6, "u", "x" * 300_000)]
    df = spark.createDataFrame([(*p, 7, "z") for p in pages], "page_id long, url string, html string, payload int, record_type string")
    got = {r["page_id"]: r for r in W.archive_round_trip(df, f"{shared_dir(spark)}/t-{request.node.name}", with_payload=True).collect()}
    assert set(got) == {p[0] for p in pages}
    for i, _, h in pages:
        body = (h or "").encode()
        twins = [j for j, _, x in pages if (x or "") == (h or "")]
        r = got[i]
        assert r["payload_bytes"] == len(body) and r["payload_digest"] == base64.b32encode(hashlib.sha1(body).digest()).decode()
        assert (r["record_type"], r["refers_to"]) == (("response", None) if i == max(twins) else ("revisit", max(twins)))
        if r["record_type"] == "response":
            assert bytes(r["payload"]) == body
    sizes = {r["page_id"]: r["record_type"] for r in W.page_records(df, least_bytes=4).collect()}
    assert all(sizes[i] == "response" for i in (1, 2, 3, 4, 9))
    assert W.archive_round_trip(df.limit(0), f"{shared_dir(spark)}/t-empty").count() == 0


def test_warc_repeated_rows_and_sizes(spark, request, monkeypatch):
    """Every row is a capture; files hold a bounded number of bytes."""
    monkeypatch.setattr(W, "FILE_BYTES", 6000)
    monkeypatch.setattr(W, "SIZES", (100, 1000, 5000))
    pages = [(1, "a", "one"), (1, "b", "one"), (1, "a", "one"), (2, "c", "one"), (None, "d", "two"), (None, "d", "two"), (3, "e", "two"), (4, "f", "one more")]
    pages += [(10 + k, "g", "x" * (17 * k * k % 9000)) for k in range(60)] + [(None, None, None)]
    df = spark.createDataFrame([(*p, "q", 2) for p in pages], "page_id long, url string, html string, uri string, copy int")
    path = f"{shared_dir(spark)}/t-{request.node.name}"
    got = sorted(((r["page_id"], r["uri"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in W.archive_round_trip(df, path).collect()), key=repr)
    want = []
    for i, u, h in pages:
        body = (h or "").encode()
        most = max((j for j, _, x in pages if (x or "") == (h or "") and j is not None), default=None)
        twins = {j for j, _, x in pages if (x or "") == (h or "")}
        revisit = len(twins) > 1 and i != most
        want.append((i, u or "", len(body), base64.b32encode(hashlib.sha1(body).digest()).decode(), "revisit" if revisit else "response", most if revisit else None))
    assert got == sorted(want, key=repr)
    sizes = [r["length"] for r in spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("length").collect()]
    assert len(sizes) > 10 and max(sizes) < 12_000 + 60 * 1500


def test_captures_join_over_a_record_between(spark):
    rows = [("r1", "response", None), ("q1", "request", "r1"), ("m1", "metadata", "q1"), ("q2", "request", "gone")]
    out = W.assemble_captures(spark.createDataFrame(rows, "record_id string, record_type string, concurrent_to string")).collect()
    by = {r["capture_id"]: r for r in out}
    assert by["r1"]["request"]["record_id"] == "q1" and by["r1"]["metadata"]["record_id"] == "m1" and by["gone"]["response"] is None


def brute_links(rows):
    n, comp = {}, {}
    unit = {}
    for i, v, label in rows:
        n[i], comp[i] = 0, i
        if v is not None and label is not None and v and None not in v and np.isfinite(v).all() and np.any(v):
            unit[i] = (np.array(v, float) / np.linalg.norm(np.array(v, float)), label)
    ids = sorted(unit)
    for a in ids:
        for b in ids:
            if a < b and unit[a][1] == unit[b][1] and len(unit[a][0]) == len(unit[b][0]) and unit[a][0] @ unit[b][0] >= 0.93:
                n[a] += 1
                n[b] += 1
                x, y = comp[a], comp[b]
                comp = {k: min(x, y) if c in (x, y) else c for k, c in comp.items()}
    return {i: (n[i], comp[i]) for i in n}


@pytest.mark.parametrize("block,bucket", [(4096, 2048), (8, 3)])
def test_embedding_links(spark, monkeypatch, block, bucket):
    monkeypatch.setattr(E, "BLOCK", block)
    monkeypatch.setattr(E, "BUCKET", bucket)
    r = np.random.default_rng(4)
    rows = []
    for c in range(6):
        centre = r.standard_normal(64)
        for k in range(12):
            rows.append((len(rows), [float(np.float32(x)) for x in centre + r.standard_normal(64) * 0.05 * (k % 6)], c % 2))
    rows += [(500 + k, rows[3][1], rows[3][2]) for k in range(5)]
    rows += [(600, None, 1), (601, [0.0] * 64, 1), (602, [1.0, None], 1), (603, [float("nan")] * 64, 0), (604, rows[0][1], None), (605, [2 * x for x in rows[0][1]], 0), (606, [1.0, 0.0], 0), (607, [1.0, 0.01], 0), (608, [], 0)]
    df = spark.createDataFrame([(i, v, c, "z", 9) for i, v, c in rows], "vec_id long, embedding array<float>, label int, key string, unit int")
    got = {x["vec_id"]: (x["n_links"], x["component_id"]) for x in E.link_embeddings(df).collect()}
    assert got == brute_links(rows)
    assert E.link_embeddings(df.limit(0)).count() == 0


def test_one_id_with_two_vectors(spark):
    rows = [(1, [1.0, 0.0], 0), (1, [0.0, 1.0], 0), (2, [0.0, 1.0], 0), (3, [1.0, 0.01], 0), (3, [1.0, 0.01], 0), (None, [1.0, 0.0], 0), (0, [-1.0, 0.0], 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").repartition(3)
    got = sorted((r["vec_id"], r["n_links"], r["component_id"], r["kept"]) for r in E.link_embeddings(df).collect())
    assert got == [(0, 0, 0, True), (1, 1, 1, True), (1, 2, 1, True), (2, 1, 1, False), (3, 2, 1, False), (3, 2, 1, False)]


def test_no_link_near_the_threshold_is_lost(spark):
    """Pairs with cosines from 0.93 to 0.95 and from 0.91 to 0.93, each apart from all others."""
    r = np.random.default_rng(6)
    rows, want = [], {}
    for k in range(1500):
        a, b = r.standard_normal((2, 64))
        a /= np.linalg.norm(a)
        b -= (a @ b) * a
        b /= np.linalg.norm(b)
        c = 0.9301 + 0.02 * r.random() if k % 3 else 0.9299 - 0.02 * r.random()
        rows += [(2 * k, a.tolist(), k % 4), (2 * k + 1, (c * a + sqrt(1 - c * c) * b).tolist(), k % 4)]
        want[2 * k + 1] = 2 * k if k % 3 else 2 * k + 1
    got = {x["vec_id"]: x["component_id"] for x in E.link_embeddings(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")).collect()}
    assert got == want | {2 * k: 2 * k for k in range(1500)}


def test_tables_follow_the_number_of_vectors():
    some = [E.choose_tables(n) for n in (1, 10**3, 10**6, 10**9)]
    assert [k for _, k in some] == sorted(k for _, k in some) and some[-1][1] > some[0][1]
    near = E.agreement(sqrt(2 - 2 * 0.93))
    assert all((1 - near**k) ** t <= E.MISSED for t, k in some) and abs(near - 0.851) < 0.001


@given(st.lists(st.integers(1, 64), max_size=120))
@settings(max_examples=60, deadline=None)
def test_best_fit_fills_gaplessly(sizes):
    bins, offsets, fills = K.best_fit(np.array(sizes, np.int64), 64)
    for k in range(len(fills)):
        own = sorted((o, s) for b, o, s in zip(bins.tolist(), offsets.tolist(), sizes) if b == k)
        end = 0
        for o, s in own:
            assert o == end
            end += s
        assert end == fills[k] <= 64
    assert sum(f <= 32 for f in fills.tolist()) <= 1


@pytest.fixture(scope="module")
def encoder():
    return K.Encoder(BPE)


@given(st.text(max_size=80))
@settings(max_examples=150, deadline=None)
def test_encoder_equals_the_library(encoder, text):
    assert encoder(text) == LIBRARY.encode(text, add_special_tokens=False).ids


LIBRARY = Tokenizer.from_file(BPE)


def test_encoder_equals_the_library_on_every_code_point(encoder):
    points = [c for c in range(0x110000) if not 0xD800 <= c < 0xE000]
    for lo in range(0, len(points), 100_000):
        texts = [f"a{c}b {c}1{c}'{c}  {c}" for c in map(chr, points[lo : lo + 100_000])]
        assert all(encoder(t) == x.ids for t, x in zip(texts, LIBRARY.encode_batch(texts, add_special_tokens=False), strict=True))


def test_every_merge_is_what_lower_ranks_leave(encoder):
    """Merging adjacent parts by the rank of what they make leaves each token's own two parts, so pairs beside the file's list never arise."""
    names = {i: t for t, i in encoder.ranks.items()}
    for k, pair in enumerate(json.loads(LIBRARY.to_str())["model"]["merges"]):
        own, parts = names[256 + k], [bytes([x]) for x in names[256 + k]]
        while len(parts) > 2:
            ranks = [encoder.ranks.get(parts[i] + parts[i + 1], 1 << 40) for i in range(len(parts) - 1)]
            at = ranks.index(low := min(ranks))
            assert low < 256 + k
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        left, right = pair if isinstance(pair, list) else pair.split(" ")
        assert b"".join(parts) == own and [LIBRARY.token_to_id(left), LIBRARY.token_to_id(right)] == [encoder.ranks[p] for p in parts]


def test_special_strings_and_long_words(encoder):
    texts = ["a <|endoftext|> b", "<|endoftext|><|endoftext|>", "  <|endoftext|>  x\n", "<|endoftext", "a" * 150_000, " " * 150_000, "1-" * 60_000, "\n" * 9000 + "x"]
    for t in texts:
        assert encoder(t) == LIBRARY.encode(t, add_special_tokens=False).ids
    plain = Tokenizer.from_file(BPE)
    plain.encode_special_tokens = True
    as_text = K.Encoder(BPE, specials_as_text=True)
    assert all(as_text(t) == plain.encode(t, add_special_tokens=False).ids for t in texts) and 50256 in encoder(texts[0]) and 50256 not in as_text(texts[0])


def test_other_tokenizer_files_go_to_the_library():
    path = public_tokenizers.path("word_bpe_49k.json")
    other = K.Encoder(path)
    assert other.fast is None and other("Some words here") == Tokenizer.from_file(path).encode("Some words here", add_special_tokens=False).ids


def test_packing(spark):
    texts = [None, "", words(10), words(3000, 1), words(3000, 1), "<|endoftext|> x", "a" * 120_000] + [words(20 + 13 * k % 400, k) for k in range(200)]
    df = spark.createDataFrame([(k, t, 5, "z") for k, t in enumerate(texts)] + [(7, texts[7], 5, "z")], "doc_id long, text string, offset int, bin string").repartition(3)
    ids = {k: np.array([*LIBRARY.encode(t or "", add_special_tokens=False).ids, 0], "<u4") for k, t in enumerate(texts)}
    rows = K.pack_documents(df, BPE).collect()
    places, seen = {}, {}
    for r in rows:
        part = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert len(part) == r["length"] and zlib.crc32(part.tobytes()) == r["ids_crc32"]
        places.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
        seen.setdefault(r["doc_id"], []).append((r["piece"], r["start"], r["length"]))
    for own in places.values():
        end = 0
        for o, n in sorted(own):
            assert o == end
            end += n
        assert end <= 2048
    for k, own in seen.items():
        if k == 7:
            continue
        own.sort()
        assert [p for p, _, _ in own] == list(range(len(own))) and sum(n for _, _, n in own) == len(ids[k]) and all(n == 2048 for _, _, n in own[1:])
        assert len(own) == -(-len(ids[k]) // 2048)
    total = sum(n for own in places.values() for _, n in own)
    assert len(places) <= -(-total // 2048) + 1
    assert K.pack_documents(df.limit(0), BPE).count() == 0
    whole = {r["sequence_id"]: r["ids"] for r in K.packed_sequences(K.pack_documents(df.where("doc_id <> 7"), BPE), df.where("doc_id <> 7"), BPE).collect()}
    assert sum(map(len, whole.values())) == sum(len(v) for k, v in ids.items() if k != 7)


def page(k, main, extra=""):
    return f"<!DOCTYPE html><html><head><title>t</title><style>x</style></head><body><header><h1>Site</h1></header><div id='x1'>Site wide box</div>{extra}<article><h1>T{k}</h1><p>{main}</p></article><footer>f</footer></body></html>"


def test_main_text():
    assert H.main_text(None) == H.main_text("") == ""
    assert H.main_text("<article><p>a &amp; b&nbsp;&#233;<p>c\n\t d<br>e</article>") == "a & b é\n\nc d e"
    assert H.main_text("<body><nav>n</nav><main><article><header><h1>T</h1></header><p>x<script>if (a < b) {}</script></p><div class='comments'>c</div><form>f</form></article></main>") == "T\n\nx"
    assert H.main_text("<div class=cookie-notice>c</div><p>1 < 2<div hidden>h</div><ul><li>a<li>b</ul><!-- no --><aside>s</aside>") == "1 < 2\n\na\n\nb"
    assert H.main_text("<p>" * 30000 + "deep") == "deep" and H.main_text("<div>" * 30000 + "deep") == "deep"
    assert H.main_text("<p>open <b>bold") == "open bold" and H.main_text("<article>x</article><!-- never closed") == "x"


@pytest.mark.parametrize(
    "page,text",
    [
        ("<article class='post tag-social'><p>x y</p></article>", "x y"), ("<div class='no-sidebar'><p>x y</p></div>", "x y"), ("<div class='content search-engine-guide'><p>x y</p></div>", "x y"),
        ("<article><p>a</p><p class='share-price'>b</p><p class='ad'>c</p></article>", "a\n\nb"), ("<div class='sidebar'><article>x</article></div>", "x"), ("<body class='sidebar'><p>x</p></body>", "x"),
        ("<p>a</p><div class='user-comments'>c</div><div id=AdSlot3>c</div><div class='cookie-notice bottom'>c</div><ul class='related posts'><li>c</ul>", "a"),
        ("<p>1 < 2, 3 <b and no end", "1 < 2, 3 <b and no end"), ("<p title=\"a>b\">x</p><p title='never closed>y</p>", "x\n\ny"), ("</3 <p>x</p>", "x"),
    ],
)
def test_names_of_parts_and_odd_tags(page, text):
    assert H.main_text(page) == text


@pytest.mark.parametrize("page", ["<a " * 300_000, '<a "' * 250_000, "<a '\">" * 150_000, "<script>" + "</script " * 100_000, "<p><button>" + "<i>" * 50_000 + "<hr>" * 50_000, "<a " + 'x = "' * 100_001 + ">", "<!--" * 200_000])
def test_hostile_pages_take_linear_time(page):
    start = time.perf_counter()
    H.main_text(page)
    assert time.perf_counter() - start < 20


def template_texts(rows):
    """Texts by a plain count: subtrees of a host that stand beside enough different contents."""
    parsed = [(i, u and u.split("/")[2], H.parse(h or "")) for i, u, h in rows]
    beside, contents = {}, {}
    for _, host, (root, subtrees) in parsed:
        text = "|".join(H.blocks(root))
        contents.setdefault(host, set()).add(text)
        for x in subtrees:
            if not x.main:
                beside.setdefault((host, x.mark), set()).add(text)
    often = {k for k, v in beside.items() if len(v) >= 5 and (len(v) >= 50 or 10 * len(v) >= len(contents[k[0]]))}
    return {i: "\n\n".join(H.blocks(root, frozenset(x.mark for x in subtrees if (host, x.mark) in often))) for i, host, (root, subtrees) in parsed}


@pytest.mark.parametrize("marks,broadcast", [(512, 1 << 25), (512, 1), (1, 1 << 25)])
def test_templates_against_brute_force(spark, monkeypatch, marks, broadcast):
    monkeypatch.setattr(H, "LIST_MARKS", marks)
    monkeypatch.setattr(H, "BROADCAST_BYTES", broadcast)
    rows = [(k, f"http://h{k % 3}.org/{k}", f"<div>Menu of {k % 3}</div><div><p>{words(12, k)}</p></div><div>Section {k % 7}</div><ul><li>More {k % 20}</ul>") for k in range(240)]
    rows += [(1000 + k, "http://big.org/", f"<div>{words(9, k)}</div><div>Notice {k % 11}</div>") for k in range(700)] + [(5000, None, None), (5001, "http://h1.org/", "<div>Menu of 1</div>")] + [(1, "http://h1.org/1", "<p>again")]
    df = spark.createDataFrame([(*r, 1, "q") for r in rows], "page_id long, url string, html string, row int, marks string")
    got = sorted((r["page_id"], r["text"], r["n_chars"]) for r in H.extract_pages(df.repartition(4)).collect())
    want = template_texts([r for r in rows if r[0] != 1 or r[2] != "<p>again"] )
    assert got == sorted([(i, t, len(t)) for i, t in want.items()] + [(1, "again", 5)])
    assert "Menu" not in "".join(want.values()) and "Notice" not in "".join(want.values())


def test_site_templates_go_and_copied_articles_stay(spark):
    rows = [(k, f"http://h.org/{k}", page(k, words(30, k))) for k in range(20)]
    rows += [(100 + k, "http://h.org/c", page(5, "copied article " * 5)) for k in range(20)]
    rows += [(200 + k, f"http://n.org/{k}", f"<body><div><p>{words(12, k)}</p></div><div>On every page here</div></body>") for k in range(12)]
    rows += [(300, None, None), (301, "", ""), (302, "http://h.org/z", "<div>Site wide box</div><p>own</p>")]
    df = spark.createDataFrame([(*r, 1, "q") for r in rows], "page_id long, url string, html string, n_chars int, host string")
    got = {r["page_id"]: r["text"] for r in H.extract_pages(df).collect()}
    assert len(got) == len(rows)
    assert all(got[k] == f"T{k}\n\n{words(30, k)}" for k in range(20)) and all(got[100 + k] == "T5\n\n" + ("copied article " * 5).strip() for k in range(20))
    assert all(got[200 + k] == words(12, k) for k in range(12)) and got[300] == got[301] == ""
    assert H.extract_pages(df.limit(0)).count() == 0


def test_shards(spark):
    texts = [words(1 + (k * 7) % 60, k) for k in range(500)] + ["same text again"] * 400 + [None, "", words(3000, 1)]
    df = spark.createDataFrame([(k, t, 1, 2) for k, t in enumerate(texts)], "doc_id long, text string, shard int, hash int").repartition(4)
    rows = D.shard_documents(df, ranges_per_shard=8).collect()
    assert sorted(r["doc_id"] for r in rows) == list(range(len(texts)))
    by = {}
    for r in rows:
        body = (texts[r["doc_id"]] or "").encode()
        assert r["size"] == len(body) + 1 and r["text_crc32"] == zlib.crc32(body) and r["law"] == "bytes" and r["grown_shard"] is None
        by.setdefault(r["shard"], []).append((r["slot"], r["size"]))
    assert all(sorted(s for s, _ in own) == list(range(len(own))) for own in by.values()) and set(by) <= set(range(8))
    assert D.shard_documents(df.limit(0)).count() == 0
    even = D.shard_documents(df.where(F.length("text") < 1000), ranges_per_shard=8).groupBy("shard").agg(F.sum("size")).collect()
    sizes = [r[1] for r in even]
    assert len(sizes) == 8 and max(sizes) < 1.05 * min(sizes)


@pytest.mark.parametrize("range_rows", [100_000, 40])
def test_shards_against_a_sort(spark, monkeypatch, range_rows):
    """Shards are consecutive parts of all rows in key order, cut where the running bytes pass even steps; null ids and repeats stay."""
    monkeypatch.setattr(D, "RANGE_ROWS", range_rows)
    r = random.Random(2)
    rows = [(k, words(r.randrange(60), k)) for k in range(3000)] + [(k, "hot text") for k in range(5000, 7000)] + [(None, "hot text")] * 3 + [(None, None), (1, None), (1, None), (2, words(8000, 1))]
    df = spark.createDataFrame([(*x, "q", 3) for x in rows], "doc_id long, text string, range string, crc int").repartition(5)
    out = D.shard_documents(df, ranges_per_shard=8).collect()
    assert sorted(((x["doc_id"], x["size"], x["text_crc32"]) for x in out), key=repr) == sorted(((i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t in rows), key=repr)
    keys = {(x["doc_id"], x["text"]): x["h"] for x in df.select("doc_id", "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("h")).distinct().collect()}
    crc_key = {zlib.crc32((t or "").encode()): h for (_, t), h in keys.items()}
    out.sort(key=lambda x: (x["shard"], x["slot"]))
    order = [(crc_key[x["text_crc32"]], x["doc_id"] or 0) for x in out]
    assert order == sorted(order)
    total, sizes = sum(x["size"] for x in out), {}
    for x in out:
        own = sizes.setdefault(x["shard"], [0, 0])
        assert x["slot"] == own[1]
        own[0] += x["size"]
        own[1] += 1
    end = 0
    for k in range(7):
        end += sizes[k][0]
        assert abs(end - total * (k + 1) / 8) <= max(0.001 * total / 8, max(x["size"] for x in out))
    assert sorted(map(tuple, D.shard_documents(df, ranges_per_shard=8).collect()), key=repr) == sorted(map(tuple, out), key=repr)


def test_pipeline_stages_follow_each_other(spark):
    import corpus_pipeline as C
    from simweave.llm import minhash_dedup as N
    from simweave.llm import quality as Q

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    good = C.quality_rules(spark, docs, "")
    judged = {r["doc_id"] for r in Q.judge_documents(docs).where("kept").collect()}
    assert good.columns == docs.columns and {r["doc_id"] for r in good.collect()} == judged
    single = C.near_dedup(spark, good, "")
    classes = {r["doc_id"]: r["component_id"] for r in N.near_duplicates(good).collect()}
    assert single.columns == docs.columns and {r["doc_id"] for r in single.collect()} == set(classes.values())
    private = C.pii_surrogates(spark, single, "")
    assert private.columns == docs.columns and private.count() == single.count() and private.where("n_chars <> char_length(text)").count() == 0
    mixed = C.source_mix(spark, private, "")
    times = [r["count"] for r in mixed.groupBy("doc_id").count().collect()]
    assert mixed.columns == docs.columns and max(times) <= 2 and {r["doc_id"] for r in mixed.collect()} <= {r["doc_id"] for r in private.collect()}
    packed = C.best_fit_packing(spark, mixed, "")
    assert packed.where("piece = 0").count() == mixed.count()
    assert [n for n, _ in C.STAGES] == ["quality rules", "near-duplicate removal", "surrogates", "source mix", "packing"]
    assert C.run(spark, "/root/testdata/sf0.001").select("doc_id").distinct().count() == mixed.select("doc_id").distinct().count()


def test_entry_works_without_the_operators(monkeypatch):
    import __spark_entry__ as entry

    assert len([q for q in entry.queries() if q.startswith("op")]) == 10 and "pipeline" in entry.queries()
    monkeypatch.setitem(sys.modules, "corpus_pipeline", None)
    alone = importlib.reload(entry)
    assert "pipeline" not in alone.queries() and "bs_pe_jaccard" in alone.queries() and not [q for q in alone.oracle_sql() if q.startswith("op")]
    monkeypatch.undo()
    importlib.reload(entry)
