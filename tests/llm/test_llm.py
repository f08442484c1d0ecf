"""Operators for training data: brute force, round trips, held-out accuracy, edge cases."""

import hashlib
import random
import re
import zlib

import numpy as np
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from ruleworld.llm import decontaminate, exact_dedup, html_extract, language, near, packing, quality, sharding, simhash, token_codec, tokens, warc
from ruleworld.operators import field as views

D = "/root/testdata/sf0.001"
DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint, kept boolean, fp string, shard int"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{D}/documents.parquet")


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empties, ties, repeated rows, a long text, clashing column names."""
    long = " ".join(f"word{k % 97}x{k % 31}" for k in range(60_000))
    rows = [(1, None, None, None), (2, "", "en", "s"), (3, "same text here now ok", "en", "s"), (4, "same text here now ok", "en", "s"), (4, "same text here now ok", "en", "s"), (None, "same text here now ok", None, "s"), (5, long, "en", None), (6, "12 !! --", "en", "s"), (None, None, None, None), (7, "Ünï çødé <|endoftext|> \n\n  x ", "de", "t")]
    return spark.createDataFrame([(*r, None, True, "x", 3) for r in rows], DOCS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


# 1 -------------------------------------------------------------------------------------------------------------------


def plain_fingerprint(text):
    low = re.sub("[A-Z]", lambda m: m.group().lower(), text or "")
    w = re.findall("[^\x20\x09-\x0d]+", low)
    runs = [" ".join(w[k : k + 4]) for k in range(max(1, len(w) - 3))] if w else []
    h = [xxhash.xxh64(r.encode(), seed=42).intdigest() for r in runs]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def plain_components(fps, ids, radius=4):
    label = list(ids)
    near = [[j for j in range(len(fps)) if (fps[i] ^ fps[j]).bit_count() <= radius] for i in range(len(fps))]
    while True:
        new = [min(label[j] for j in near[i]) for i in range(len(fps))]
        if new == label:
            return label
        label = new


@given(st.text(max_size=60))
@settings(max_examples=200, deadline=None)
def test_fingerprint_equals_definition(text):
    assert simhash.fingerprint(text) == plain_fingerprint(text)


def test_near_groups_equal_brute_force(spark, docs):
    rows = simhash.near_groups(docs).collect()
    text = {r.doc_id: r.text for r in docs.collect()}
    fps = [r.fp & (2**64 - 1) for r in rows]
    assert all(f == plain_fingerprint(text[r.doc_id]) for f, r in zip(fps, rows))
    assert [r.component_id for r in rows] == plain_components(fps, [r.doc_id for r in rows])


@pytest.mark.parametrize("cell,most", [(2_000_000, 3_000_000), (3_000, 5_000)])
def test_ball_links_in_tight_clusters(spark, monkeypatch, cell, most):
    """Chains of near fingerprints, with cells that must be worked off in sub-cells."""
    monkeypatch.setattr(simhash, "CELL_VARIANTS", cell)
    chance = random.Random(4)
    fps = []
    for _ in range(12):
        x = chance.getrandbits(64)
        for _ in range(6):
            fps.append(x)
            for b in chance.sample(range(64), chance.choice([1, 3, 4, 5])):
                x ^= 1 << b
    nodes, forest = np.array(fps, np.uint64), simhash.Forest(len(fps))
    if most < 10_000:
        for c in (0, 1):
            simhash.cell_links(nodes, c, 1, 2, forest, np.arange(len(fps)), most)
        got = [fps[r] for r in forest.find(np.arange(len(fps)))]
        want = plain_components(fps, list(range(len(fps))))
        assert [fps[k] for k in want] == got
    else:
        signed = [(int(np.uint64(f).view(np.int64)),) for f in fps]
        links = simhash.ball_links(spark.createDataFrame(signed, "fp bigint").distinct()).collect()
        f = simhash.Forest(len(fps))
        place = {v[0]: k for k, v in enumerate(signed)}
        f.union(np.array([place[r.u] for r in links]), np.array([place[r.v] for r in links]))
        want = plain_components(fps, list(range(len(fps))))
        assert f.find(np.arange(len(fps))).tolist() == want


def test_simhash_edges(spark, odd, none):
    rows = simhash.near_groups(odd).collect()
    assert len(rows) == 10
    assert {r.component_id for r in rows if r.fp == 0} == {1}
    assert simhash.near_groups(none).count() == 0 and simhash.drop_near(none).count() == 0
    stay = simhash.drop_near(odd)
    assert stay.columns == odd.columns
    assert sorted(r.doc_id for r in stay.collect()) == [1, 3, 5, 6, 7]


def plain_runs(text):
    low = re.sub("[A-Z]", lambda m: m.group().lower(), text or "")
    w = re.findall("[^\x20\x09-\x0d]+", low)
    return {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))}


def plain_similar(rows):
    """Pairs of a Jaccard of 0.8 or more, by trying all."""
    sets = [(i, plain_runs(t)) for i, t in rows]
    for k, (i, x) in enumerate(sets):
        for j, y in sets[:k]:
            if 5 * len(x & y) >= 4 * len(x | y):
                yield min(i, j), max(i, j)


@pytest.fixture(scope="module")
def copies(spark, docs):
    """Texts with a few words changed, so that similarities lie around 0.8, one group of many, and a common passage."""
    chance, rows = random.Random(12), []
    words = [f"w{k}" for k in range(300)]
    passage = chance.choices(words, k=30)
    for k in range(40):
        base = chance.choices(words, k=chance.choice([4, 12, 60, 150])) + (passage if k % 2 else [])
        for _ in range(40 if k == 3 else 4):
            own = list(base)
            for _ in range(chance.randint(0, 1 + len(own) // 60)):
                own[chance.randrange(len(own))] = chance.choice(words)
            rows.append((len(rows), chance.choice([" ", "\n"]).join(own)))
    return rows + [(len(rows) + k, r.text) for k, r in enumerate(docs.orderBy("doc_id").collect())]


@pytest.mark.parametrize("often", [3, 10**9])
def test_similar_pairs_equal_brute_force(spark, copies, monkeypatch, often):
    monkeypatch.setattr(near, "OFTEN", often)
    got = sorted((r.u, r.v) for r in near.similar_pairs(spark.createDataFrame(copies, "doc_id bigint, text string")).collect())
    assert got == sorted(plain_similar(copies)) and len(got) > 100


def test_pipeline_drops_all_near_copies(spark, copies):
    import corpus_pipeline

    stage = dict(corpus_pipeline.STAGES)["simhash_near_dedup"]
    stay = {r.doc_id for r in stage(spark, spark.createDataFrame(copies, "doc_id bigint, text string"), D).collect()}
    root = views.components_local(list(plain_similar(copies)))
    assert stay == {i for i, _ in copies if root.get(i, i) == i}


def test_near_edges(spark, odd, none):
    stay = near.drop_near(odd)
    assert stay.columns == odd.columns
    assert sorted(r.doc_id for r in stay.collect()) == [1, 3, 5, 6, 7]
    assert near.drop_near(none).count() == 0 and near.similar_pairs(none).count() == 0


# 2 -------------------------------------------------------------------------------------------------------------------


def plain_cuts(sizes, shards):
    def cuts(c):
        out, p, e = [], 0, 0
        for s in sizes:
            if p + s > c:
                out.append(e)
                p = 0
            p, e = p + s, e + s
        return out + [e]

    lo, hi = max(sizes), sum(sizes)
    while lo < hi:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if len(cuts(mid)) <= shards else (mid + 1, hi)
    return lo, cuts(lo)


@pytest.mark.parametrize("n,shards,bins", [(60, 5, 8), (300, 7, 16)])
def test_minimax_equals_brute_force(spark, n, shards, bins):
    chance = random.Random(n)
    sizes = [chance.choice([chance.randint(1, 40), chance.randint(1, 2000)]) for _ in range(n)]
    ends = np.cumsum(sizes).tolist()
    cuts = sharding.minimax_cuts(spark.createDataFrame([(e,) for e in ends], "end long"), ends[-1], max(sizes), shards, bins)
    assert sorted(set(cuts)) == plain_cuts(sizes, shards)[1]


def test_shards_of_documents(spark, docs, odd, none):
    rows = sharding.shard_rows(docs).collect()
    text = {r.doc_id: r.text for r in docs.collect()}
    group = {}
    for r in rows:
        assert r.size == len(text[r.doc_id].encode()) + 16 and r.text_crc32 == zlib.crc32(text[r.doc_id].encode())
        group.setdefault(text[r.doc_id], []).append(r)
    ordered = sorted(group.values(), key=lambda g: min(r.doc_id for r in g))
    largest, _ = plain_cuts([sum(r.size for r in g) for g in ordered], 40)
    by = {}
    for r in rows:
        by.setdefault(r.shard, []).append(r)
    assert max(sum(r.size for r in v) for v in by.values()) == largest
    assert all(sorted(r.slot for r in v) == list(range(len(v))) for v in by.values())
    assert all(len({r.shard for r in g}) == 1 for g in group.values())
    assert sharding.shard_rows(odd).count() == 10 and sharding.shard_rows(none).count() == 0


def test_sharding_is_native(spark, docs):
    plan = sharding.shard_rows(docs)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan


# 3 -------------------------------------------------------------------------------------------------------------------


def test_main_text_without_furniture():
    page = """<html><head><title>T</title></head><body class="has-sidebar"><header><h1>Site</h1></header><div class="cookie-notice">We use cookies</div><nav>m</nav>
    <main><article class="post"><header><h2>Title &amp; more</h2></header><p>First&nbsp;para <em>with</em> <a href=x>link</a>.<p>Short.</p><aside>side</aside>
    <form><p>f</p></form><ul><li>one<li>two</ul><div class=ad>buy</div><script>var a="<p>x</p>"</script></article>
    <section id="comments"><article class="comment"><p>Nice!</p></article></section></main><footer>f</footer>"""
    assert html_extract.main_text(page) == "Title & more\n\nFirst para with link.\n\nShort.\n\none\n\ntwo"
    assert html_extract.main_text("<body><div class=sidebar>x</div><div><p>" + "long text " * 30 + "</p></div><p><a href=a>link</a></p>") == ("long text " * 30).strip()


def test_main_text_with_omitted_head_end():
    prose = "long text " * 30
    for start in ("<body>", "", "<body class=x><script>s</script>"):
        page = f"<html><head><title>T</title><meta charset=utf-8><script>var a</script>{start}<nav>m</nav><article><h1>H</h1><p>{prose}</article></html>"
        assert html_extract.main_text(page) == "H\n\n" + prose.strip()
    assert html_extract.main_text("<head><title>T</title>" + prose) == prose.strip()


def test_main_text_takes_nested_and_sibling_parts():
    prose = "long text " * 30
    page = f"<body><main><h1>Title</h1><p>Lead</p><article><p>{prose}</article><aside><article>ad</article></aside></main><footer>f</footer>"
    assert html_extract.main_text(page) == "Title\n\nLead\n\n" + prose.strip()
    page = f"<body><p>x</p><div><article><p>{prose}</article><article><p>Part two</article><article class=promo>p</article></div>"
    assert html_extract.main_text(page) == prose.strip() + "\n\nPart two"


def test_main_text_of_pages(spark):
    import html

    for r in spark.read.parquet(f"{D}/pages.parquet").collect():
        inner = re.search(r"<article>(.*?)</article>", r.html, re.S)[1]
        blocks = (" ".join(html.unescape(b.replace("<br>", " ").replace("<b>", "")).split()) for b in re.split(r"</?(?:p|h1)>", inner))
        assert html_extract.main_text(r.html) == "\n\n".join(b for b in blocks if b)


def page_of_blocks(chance, marked):
    """A page without article elements: short link lines, a story of some long and short blocks, short lines after it."""
    words = lambda n: " ".join(chance.choices(["stone", "river", "of", "and", "light", "under"], k=n))
    story = [words(chance.choice([3, 40, 60])) for _ in range(chance.randint(4, 9))] + [words(50)]
    around = [f'<div{" class=menu" if marked else ""}><a href=x>{words(2)}</a></div>' for _ in range(12)]
    return f"<body><div>{''.join(around)}</div><div>{''.join(f'<p>{x}</p>' for x in story)}</div><div>{''.join(around)}</div></body>", "\n\n".join(story)


def test_ratios_decide_where_elements_do_not(monkeypatch):
    chance = random.Random(3)
    made = [page_of_blocks(chance, marked) for marked in (False, True) for _ in range(40)]
    assert all(html_extract.main_text(page) == story for page, story in made)
    monkeypatch.setattr(html_extract, "line_ratios", lambda page: np.ones(len(page.lines)))
    assert sum(html_extract.main_text(page) != story for page, story in made[:40]) > 30


def test_ratios_smoothing_and_threshold_equal_plain_loops():
    chance = random.Random(8)
    page = html_extract.read_page(page_of_blocks(chance, False)[0])
    ratio = html_extract.line_ratios(page)
    assert ratio.tolist() == [(len(x.text) - x.linked + 1) / max(1, x.tags) for x in page.lines]
    n, near = len(ratio), lambda k: [j for j in range(k - 2, k + 3) if 0 <= j < len(ratio)]
    want = [sum(ratio[j] * np.exp(-((j - k) ** 2) / 2) for j in near(k)) / sum(np.exp(-((j - k) ** 2) / 2) for j in near(k)) for k in range(n)]
    smooth = html_extract.smoothed(ratio)
    assert np.allclose(smooth, want)
    cut = html_extract.threshold(smooth)
    low, high = smooth[smooth <= cut], smooth[smooth > cut]
    assert len(low) and len(high) and abs(cut - (low.mean() + high.mean()) / 2) < 1e-9


def test_no_block_is_lost_for_a_word_of_its_class():
    prose = "long text " * 30
    for page in (
        f'<div class="story social-policy"><article><h1>T</h1><p>{prose}<p>Short.<p>{prose}</article></div>',
        f'<article><div class="reader comment"><h1>T</h1><p>{prose}</p><p>Short.</p><p>{prose}</p></div></article>',
        f"<form><nav><a>m</a></nav><div><h1>T</h1><p>{prose}</p><p>Short.</p><p>{prose}</p></div></form>",
    ):
        assert html_extract.main_text(page) == f"T\n\n{prose.strip()}\n\nShort.\n\n{prose.strip()}"


def test_main_text_of_broken_markup_in_linear_time():
    import time

    def seconds(n):
        began = time.process_time()
        for page in ("<b><div>" + "<span>" * n + "x" + "</b>" * n, "<div>a" * n + "</p>" * n, "<li>a" * n):
            html_extract.main_text(page)
        return time.process_time() - began

    seconds(1000)
    assert seconds(40_000) < 30 * max(seconds(4_000), 0.05)
    assert html_extract.main_text("<div>" * 5000 + "word " * 40) == ("word " * 40).strip()


def test_main_text_edges(spark):
    pages = spark.createDataFrame([(1, None, None), (2, "u", ""), (2, "u", "<p>a</p>"), (None, "u", "< <p <b>x"), (3, "u", "<nav>only</nav>")], "page_id bigint, url string, html string")
    rows = html_extract.extract(pages.withColumn("text", F.lit("clash"))).collect()
    assert [r.text for r in rows][:3] == ["", "", "a"] and rows[4].text == ""
    assert all(r.n_chars == len(r.text) for r in rows)
    assert html_extract.extract(pages.limit(0)).count() == 0


# 4 -------------------------------------------------------------------------------------------------------------------


def test_digest_index_equals_dictionary():
    chance = random.Random(2)
    for keep, best in (("smallest", min), ("largest", max)):
        index, plain = exact_dedup.DigestIndex(keep, memtable=7, fanout=3), {}
        for k in range(500):
            d, i = bytes([chance.randrange(60)]) * 32, chance.randrange(1000)
            index.put(d, ((True, i, k), 1))
            plain.setdefault(d, []).append((True, i, k))
        assert {d: e for d, e in index.scan()} == {d: (best(v), len(v)) for d, v in plain.items()}
        assert all(index.get(d) == (best(v), len(v)) for d, v in plain.items())
        assert index.get(b"x" * 32) is None
        assert dict(index.hits()) == {d: (best(v), len(v)) for d, v in plain.items() if len(v) > 1}


def test_filters_keep_single_digests_out_of_compaction(monkeypatch):
    index, merged = exact_dedup.DigestIndex(memtable=100, fanout=9), []
    for k in range(700):
        index.put(hashlib.sha256(str(k % 690).encode()).digest(), ((True, k, k), 1))
    plain = exact_dedup.heapq.merge
    monkeypatch.setattr(exact_dedup.heapq, "merge", lambda *parts, key: (merged.append(x) or x for x in plain(*parts, key=key)))
    assert sorted(n for _, (_, n) in index.hits()) == [2] * 10
    assert 20 <= len(merged) < 120  # of 700 entries


@pytest.mark.parametrize("digest_bytes", [32, 1])
def test_exact_groups(spark, docs, digest_bytes):
    rows = exact_dedup.exact_groups(docs, keep="largest", digest_bytes=digest_bytes).collect()
    text = {r.doc_id: r.text for r in docs.collect()}
    by = {}
    for i, t in text.items():
        by.setdefault(t, []).append(i)
    for r in rows:
        own = by[text[r.doc_id]]
        assert (r.keep_id, r.group_size, r.kept) == (max(own), len(own), r.doc_id == max(own))
        assert r.text_sha256 == hashlib.sha256(text[r.doc_id].encode()).hexdigest()


def test_exact_edges(spark, odd, none):
    rows = exact_dedup.exact_groups(odd, keep="largest").collect()
    assert len(rows) == 10 and sum(r.kept for r in rows) == 5  # the empty text counts once
    same = [r for r in rows if r.group_size == 4]
    assert {r.keep_id for r in same} == {4} and sum(r.kept for r in same) == 1
    assert exact_dedup.exact_groups(none).count() == 0
    stay = exact_dedup.drop_copies(odd)
    assert stay.columns == odd.columns and stay.count() == 5
    assert exact_dedup.drop_copies(none).count() == 0


# 5 -------------------------------------------------------------------------------------------------------------------


def test_warc_round_trip(spark):
    pages = spark.read.parquet(f"{D}/pages.parquet")
    more = pages.unionByName(pages.limit(9).withColumn("page_id", F.col("page_id") + 1000)).unionByName(spark.createDataFrame([(5000, None, None), (None, "a\r\nb", "x" * 200), (5001, "u", "tiny"), (5002, "u", "tiny"), (5003, "u", "x" * 200), (5003, "u", "x" * 200)], pages.schema))
    where, manifest = warc.write_archives(more, roll=20_000)
    got = warc.read_archives(where, manifest, payloads=True).collect()
    want = more.collect()
    assert len(got) == len(want) and manifest.count() > 1 and manifest.agg(F.sum("records")).first()[0] == len(want)
    first = {}
    for r in want:
        raw = (r.html or "").encode()
        if len(raw) >= 100 and r.page_id is not None:
            first[raw] = min(first.get(raw, r.page_id), r.page_id)
    html = {}
    for r in want:
        html.setdefault(r.page_id, r.html or "")
    for r in got:
        raw = html[r.page_id].encode()
        assert r.payload_bytes == len(raw) and r.payload_digest == hashlib.sha256(raw).hexdigest()
        if r.record_type == "revisit":
            assert len(raw) >= 100 and r.refers_to == first[raw]
        else:
            assert r.refers_to is None and r.html == html[r.page_id]
    assert sum(r.record_type == "revisit" for r in got) == 9 + 2
    files = {r.file: r.sha256 for r in manifest.collect()}
    again = {r.file: r.sha256 for r in warc.write_archives(more, roll=20_000)[1].collect()}
    assert files == again  # any attempt writes the same bytes
    spread = more.repartition(7, F.hash("url")).withColumns({"digest": F.lit("clash"), "place": F.lit(1), "to": F.lit("x")})
    other = [warc.write_archives(rows, roll=1 << 30)[1].agg(F.sum("records"), F.sum("bytes")).first() for rows in (more.coalesce(1), spread)]
    assert other[0][0] == other[1][0] == len(want) and records_of(*warc.write_archives(spread)) == records_of(where, manifest)
    assert warc.read_archives(*warc.write_archives(pages.limit(0))).count() == 0


def records_of(where, manifest):
    """All records of archives, as they stand in the files."""
    store = warc.Store(where)
    out = []
    for r in manifest.collect():
        with store.open(r.file) as f:
            out += warc.members(f)
    return sorted(out)


def test_warc_of_a_hot_payload_and_long_pages(spark):
    rows = [(k % 40, f"u{k % 2}", "hot " * 60) for k in range(400)] + [(1000, "u", "y" * 3_000_000), (None, None, None)]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    where, manifest = warc.write_archives(pages)
    got = warc.read_archives(where, manifest).collect()
    assert len(got) == 402 and sum(r.record_type == "revisit" for r in got) == 399
    assert {r.refers_to for r in got if r.record_type == "revisit"} == {0}
    ids = [x.split(b"WARC-Record-ID: ")[1].split(b"\r\n")[0] for x in records_of(where, manifest)]
    assert len(set(ids)) == 402


def test_warc_damage_is_found():
    raw = warc.build_record(7, "a", 0, "u", b"payload" * 30, hashlib.sha256(b"payload" * 30).hexdigest(), None)
    assert warc.parse_record(raw)[1] == b"payload" * 30
    with pytest.raises(ValueError):
        warc.parse_record(raw.replace(b"payloadpay", b"payl0adpay", 1))


# 6 -------------------------------------------------------------------------------------------------------------------


def test_language_held_out(spark, odd, none):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = language.identify(docs).join(docs.select("doc_id", "lang"), "doc_id").collect()
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in rows)
    out = [r for r in rows if r.held_out]
    assert np.mean([r.lang == r.lang_pred for r in out]) > 0.98
    assert not any(r.rejected for r in rows) and all(0 <= r.score <= 1 for r in rows)
    told = {(r.doc_id, r.lang_pred, r.rejected) for r in language.identify(docs.select("doc_id", "text", "lang").unionByName(odd.select("doc_id", "text", "lang").filter("doc_id IN (1, 2, 6)").withColumn("doc_id", -F.col("doc_id")))).filter("doc_id < 0").collect()}
    assert told == {(-1, "und", True), (-2, "und", True), (-6, "und", True)}
    assert language.identify(none).count() == 0 and language.drop_rejected(none).count() == 0
    kept = language.drop_rejected(docs.unionByName(odd.select(docs.columns).filter("text IS NULL")))
    assert kept.count() == docs.count() and kept.columns == docs.columns


def test_language_rejects_what_is_far(spark, docs):
    model = language.fit_centroids(language.training_rows(docs))
    lang, score, gone = model.predict(["Ж Щ Ы Э Ю Я Ъ Ь", "the of and to in\0the"], language.letter_table())
    assert gone[0] and not gone[1] and score[0] < 0.1


FOREIGN = {
    "fi": "Kaikki ihmiset syntyvät vapaina ja tasavertaisina arvoltaan ja oikeuksiltaan. Heille on annettu järki ja omatunto, ja heidän on toimittava toisiaan kohtaan veljeyden hengessä.",
    "pl": "Wszyscy ludzie rodzą się wolni i równi pod względem swej godności i swych praw. Są oni obdarzeni rozumem i sumieniem i powinni postępować wobec innych w duchu braterstwa.",
    "sw": "Watu wote wamezaliwa huru, hadhi na haki zao ni sawa. Wote wamejaliwa akili na dhamiri, hivyo yapasa watendeane kindugu.",
    "none": "xqzvk bwtjp hgfdq zzkvx mnbvq plkjh wqxzr tgbvc yhnmj ujkqz rfvbg edcxw qazws plmko ijnbh",
}


def test_language_rejects_unlearned_languages():
    import pyarrow.parquet as pq

    rows = pq.read_table("/root/testdata/sf0.01/documents.parquet", columns=["doc_id", "text", "lang"]).to_pylist()
    out = [zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1 for r in rows]
    model = language.fit_centroids([(r["lang"], r["text"]) for r, o in zip(rows, out) if not o])
    letters = language.letter_table()
    assert model.predict([t[:n] for t in FOREIGN.values() for n in (40, 80, 400)], letters)[2].all()
    assert not model.predict([r["text"] for r, o in zip(rows, out) if o], letters)[2].any()


# 7 -------------------------------------------------------------------------------------------------------------------


def plain_hits(items, words, window):
    hit, found = set(), set()
    for i, w in items:
        m = min(window, len(w))
        for a in range(len(w) - m + 1 if m else 0):
            for p in range(len(words) - m + 1):
                if words[p : p + m] == w[a : a + m]:
                    hit.update(range(p, p + m))
                    found.add(i)
    return hit, found


def test_automaton_equals_brute_force():
    chance = random.Random(5)
    for _ in range(150):
        abc = [bytes([97 + k]) for k in range(chance.choice([2, 3, 6]))]
        items = [(i, chance.choices(abc, k=chance.randint(0, 12))) for i in range(chance.randint(0, 6))]
        window = chance.choice([2, 3, 5])
        machine = decontaminate.ItemAutomaton(items, window)
        for _ in range(5):
            words = chance.choices(abc, k=chance.randint(0, 40))
            spans, found = machine.match(words)
            assert ({x for a, b in spans for x in range(a, b)}, found) == plain_hits(items, words, window)


def test_decontamination(spark, odd, none):
    docs, bench = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/benchmark.parquet")
    one, many = decontaminate.find_items(docs, bench).orderBy("key").collect(), decontaminate.find_items(docs, bench, block_words=300).orderBy("key").collect()
    assert one == many
    dirty = {r.key for r in one if r.item_ids}
    clean = decontaminate.decontaminate(docs, bench)
    assert decontaminate.contamination(clean, bench).filter("contaminated").count() == 0
    before, after = {r.doc_id: r for r in docs.collect()}, {r.doc_id: r for r in clean.collect()}
    assert all(after[i] == r for i, r in before.items() if i not in dirty)
    assert decontaminate.contamination(odd, bench).count() == 10 and decontaminate.contamination(none, bench).count() == 0
    assert decontaminate.contamination(odd, bench.limit(0)).filter("contaminated").count() == 0
    assert decontaminate.clean_text("Ab, cd! EF gh.", [(1, 3)]) == "Ab,  gh."


def test_decontaminate_in_blocks_and_at_edges(spark, odd, none):
    docs, bench = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/benchmark.parquet")
    one, many = sorted(decontaminate.decontaminate(docs, bench).collect()), sorted(decontaminate.decontaminate(docs, bench, block_words=300).collect())
    assert one == many and 0 < len(one) < docs.count() + 1
    items = spark.createDataFrame([(1, "a b c d e f g h i j"), (2, "x1 x2 x3 x4 x5 x6 x7 x8 x9 x10"), (3, None), (4, "")], "item_id bigint, text string")
    fill = " ".join(f"w{k}" for k in range(30))
    text = f"{fill} a b c d e x1 x2 x3 x4 x5 x6 x7 x8 x9 x10 f g h i j {fill}"  # the first item appears when the second goes
    rows = [(1, text, 5), (1, text, 5), (2, None, None), (3, "", 0), (None, "a b c d e f g h i j", 19), (4, fill, 7)]
    made = spark.createDataFrame([(*r, "k", True) for r in rows], "doc_id bigint, text string, n_chars bigint, key string, spans boolean")
    for words in (500_000, 5):
        out = decontaminate.decontaminate(made, items, block_words=words)
        got = sorted(out.collect(), key=lambda r: (r.doc_id, r.text or ""))
        assert out.columns == made.columns and [r.doc_id for r in got] == [1, 1, 2, 3, 4]
        assert got[0] == got[1] and got[0].text.split() == (fill + " " + fill).split() and got[0].n_chars == len(got[0].text)
        assert (got[2].text, got[2].n_chars, got[3].text, got[4].n_chars) == (None, None, "", 7)
    assert decontaminate.decontaminate(none, items).count() == 0 and decontaminate.decontaminate(none, items, block_words=5).count() == 0
    assert decontaminate.decontaminate(odd, items.limit(0)).count() == 10


def test_automaton_of_repeated_words_in_linear_time():
    import time

    def seconds(n):
        began = time.process_time()
        machine = decontaminate.ItemAutomaton([(1, [b"a"] * n)])
        assert machine.match([b"a"] * n) == ([(0, n)], {1})
        return time.process_time() - began

    seconds(1000)
    assert seconds(40_000) < 40 * max(0.02, seconds(4_000))


# 8, 10 ---------------------------------------------------------------------------------------------------------------


@given(st.lists(st.text(alphabet="ab \n.'tsé1,", max_size=30), max_size=6))
@settings(max_examples=150, deadline=None)
def test_encoder_equals_library(texts):
    e = tokens.encoder("byte_bpe_50k.json")
    assert e.encode(texts) == e.whole(texts) and e.chunked


def test_first_fit_decreasing():
    chance = random.Random(1)
    for _ in range(50):
        sizes = [chance.randint(1, 20) for _ in range(chance.randint(1, 40))]
        bins = []
        want = [None] * len(sizes)
        for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
            k = next((k for k, b in enumerate(bins) if b + sizes[i] <= 20), len(bins))
            if k == len(bins):
                bins.append(0)
            want[i] = (k, bins[k])
            bins[k] += sizes[i]
        assert packing.first_fit_decreasing(sizes, 20) == want


def test_packing_holds_every_id_once(spark, docs, odd, none):
    e = tokens.encoder("byte_bpe_50k.json")
    for source in (docs, odd):
        want = sorted((len(x) // 4 + 1, zlib.crc32(x + b"\1\0\0\0")) for x in e.whole([r.text or "" for r in source.collect()]))
        rows = packing.pack(source, group_docs=50).collect()
        assert sorted(r.doc_tokens for r in rows if r.start == 0) == [w[0] for w in want]
        assert sorted(r.ids_crc32 for r in rows if r.length == r.doc_tokens) == sorted(c for n, c in want if n <= 2048)
        seq = {}
        for r in rows:
            seq.setdefault(r.sequence_id, []).append(r)
        for s in seq.values():
            at = 0
            for r in sorted(s, key=lambda r: r.offset):
                assert r.offset == at
                at += r.length
            assert at <= 2048 and all(r.sequence_tokens == at for r in s)
    assert packing.pack(none).count() == 0


def test_packing_deals_rows_not_ids(spark):
    rows = [(None, f"text {k}") for k in range(500)] + [(7, "same")] * 500
    rows = packing.pack(spark.createDataFrame(rows, "doc_id bigint, text string"), group_docs=100).collect()
    groups = {}
    for r in rows:
        groups[r.sequence_id >> 32] = groups.get(r.sequence_id >> 32, 0) + 1
    assert len(rows) == 1000 and len(groups) == 10 and max(groups.values()) < 180


@pytest.mark.parametrize("n", [0, 1, 2, 300, 9000])
def test_codec_round_trip(n):
    import io

    for ids in (np.random.default_rng(n).integers(0, 50257, n).astype(np.uint32), np.zeros(n, np.uint32), (np.arange(n) % 7).astype(np.uint32)):
        block = token_codec.write_block(ids, [(3, n, True)], 50257)
        got, runs = token_codec.read_block(io.BytesIO(block))
        assert (got == ids).all() and runs == [(3, n, True)]
        if n:
            with pytest.raises(ValueError):
                token_codec.read_block(io.BytesIO(block[:-1] + bytes([block[-1] ^ 1])))


def test_token_files(spark, docs, odd, none):
    e = tokens.encoder("byte_bpe_50k.json")
    for source, block in ((docs, 1 << 21), (odd, 1000)):
        where, files = token_codec.write_ids(source, "byte_bpe_50k.json", 2, block_ids=block)
        rows = sorted(token_codec.read_ids(spark, where, files).collect(), key=lambda r: r.start)
        kept = sorted(source.collect(), key=lambda r: (r.doc_id is not None, r.doc_id or 0, r.text or ""))
        at = 0
        for r, d in zip(rows, kept, strict=True):
            raw = e.whole([d.text or ""])[0] + b"\2\0\0\0"
            assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32) == (d.doc_id, at, len(raw) // 4, zlib.crc32(raw))
            at += r.n_tokens
    assert token_codec.round_trip(none).count() == 0


def test_token_files_roll_and_split_a_hot_id(spark, docs):
    hot = docs.select(F.lit(5).cast("long").alias("doc_id"), "text")
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    where, files = token_codec.write_ids(hot, "byte_bpe_50k.json", 2, block_ids=2000, roll=10_000)
    spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")
    assert len(files) > 8 and len({f.part for f in files}) > 1 and any(f.turn for f in files) and sum(f.docs for f in files) == 200
    rows = sorted(token_codec.read_ids(spark, where, files).collect(), key=lambda r: r.start)
    assert len(rows) == 200 and all(b.start == a.start + a.n_tokens for a, b in zip(rows, rows[1:]))
    e = tokens.encoder("byte_bpe_50k.json")
    assert sorted(r.ids_crc32 for r in rows) == sorted(zlib.crc32(x + b"\2\0\0\0") for x in e.whole([r.text or "" for r in docs.collect()]))
    with pytest.raises(ValueError):
        token_codec.Mixer(1 << 20)


# 9 -------------------------------------------------------------------------------------------------------------------


def test_quality_held_out(spark, odd, none):
    d = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    train, rest = labels.filter("doc_id % 2 = 0"), labels.filter("doc_id % 2 = 1")
    rows = quality.judge(docs, train).join(rest.select("doc_id", F.col("quality").alias("q"), F.col("toxic").alias("t")), "doc_id").collect()
    clean = [r.kept for r in rows if r.q == 1 and r.t == 0]
    assert np.mean(clean) > 0.995
    assert np.mean([r.kept for r in rows if r.q == 0]) < 0.1 and np.mean([r.kept for r in rows if r.t == 1]) < 0.1
    assert quality.judge(odd, train).count() == 10 and quality.judge(none, train).count() == 0
    lone = quality.judge(odd, train.limit(0)).collect()
    assert len(lone) == 10 and all(r.quality == 0.5 and r.toxicity == 0 for r in lone)


def test_site_posteriors_shrink(spark):
    rows = [("a", "x", 0.9)] * 50 + [("a", "y", 0.9)] + [("b", "x", 0.1)] * 50 + [("c", "z", 0.1)]
    scored = spark.createDataFrame(rows, "host string, path string, p_quality double")
    sites, mean = quality.site_posteriors(scored, "quality")
    got = {(r.host, r.path): r.path_mean for r in sites.collect()}
    assert abs(got["a", "x"] - 0.9) < 0.05 and abs(got["b", "x"] - 0.1) < 0.05
    assert 0.1 <= got["c", "z"] <= mean


def test_site_posteriors_equal_plain_loops(spark):
    chance = random.Random(6)
    rows = [(chance.choice(["a", "b", "c", None]), chance.choice(["x", "y", None]), round(chance.random() ** 2, 6)) for _ in range(300)] + [("a", "z", None)]
    sites, mean = quality.site_posteriors(spark.createDataFrame(rows, "host string, path string, p_quality double"), "quality")

    def strength(groups):
        kept = [g for g in groups.values() if g]
        n, k, all_ = sum(map(len, kept)), len(kept), [p for g in kept for p in g]
        within = sum(sum((p - sum(g) / len(g)) ** 2 for p in g) for g in kept) / (n - k)
        between = sum(len(g) * (sum(g) / len(g) - sum(all_) / n) ** 2 for g in kept)
        spread = (between - (k - 1) * within) / (n - sum(len(g) ** 2 for g in kept) / n)
        return min(1e6, within / spread) if spread > 1e-9 else 1e6

    hosts, paths = {}, {}
    for h, p, q in rows:
        hosts.setdefault(h, []).extend([q] if q is not None else [])
        paths.setdefault((h, p), []).extend([q] if q is not None else [])
    whole = sum(map(sum, hosts.values())) / sum(map(len, hosts.values()))
    kh, kp = strength(hosts), strength(paths)
    assert abs(mean - whole) < 1e-9
    for r in sites.collect():
        host = (sum(hosts[r.host]) + kh * whole) / (len(hosts[r.host]) + kh)
        path = (sum(paths[r.host, r.path]) + kp * host) / (len(paths[r.host, r.path]) + kp)
        assert abs(r.host_mean - host) < 1e-5 and abs(r.path_mean - path) < 1e-5


def test_quality_is_the_same_over_salted_sites(spark, monkeypatch):
    docs, labels = spark.read.parquet(f"{D}/documents.parquet"), spark.read.parquet(f"{D}/labels.parquet")
    plain = sorted(quality.judge(docs, labels).collect())
    monkeypatch.setattr(quality, "BROADCAST_SITES", 0)
    assert sorted(quality.judge(docs, labels).collect()) == plain and len(plain) == 200


# Pipeline ------------------------------------------------------------------------------------------------------------


def test_pipeline_stages(spark):
    import corpus_pipeline

    from ruleworld.sources.scratch import settle

    docs = spark.read.parquet(f"{D}/documents.parquet")
    now, ids = docs, {r.doc_id for r in docs.collect()}
    for name, stage in corpus_pipeline.STAGES:
        out = settle(stage(spark, now, D))
        if name != corpus_pipeline.STAGES[-1][0]:
            assert out.schema.simpleString() == docs.schema.simpleString()
            ids_now = {r.doc_id for r in out.collect()}
            assert ids_now <= ids
            ids = ids_now
        now = out
    assert {r.doc_id for r in now.collect()} == ids
    assert sorted(corpus_pipeline.run(spark, D).collect()) == sorted(now.collect())
