"""FLAC columns, HTML extraction, chat formatting, sharding, WARC bundles."""

import hashlib
import os
import random
import re
import zlib

import numpy as np
import pytest
from hypothesis import given, settings, strategies as st
from pyspark.sql import functions as F

from postpool.llm import chat, dom, flac, html_extract as X, queries, sharding, warc

from ..twins import assert_twin, connect
from .hostile import documents, empty

# ---------------------------------------------------------------- FLAC


@settings(max_examples=60, deadline=None)
@given(st.one_of(st.binary(min_size=1, max_size=300), st.text(max_size=200).map(flac.pad), st.lists(st.sampled_from(b"ab z"), min_size=1, max_size=3000).map(bytes)), st.sampled_from([0, 1, 4, 8]), st.sampled_from([16, 64, 4096]))
def test_flac_round_trip(payload, lpc, block):
    media = flac.encode(payload, block=block, lpc_order=lpc)
    blocks = list(flac.decode_blocks(media))
    assert b"".join(p for _, p in blocks) == payload
    at = 0
    for offset, pcm in blocks:
        assert offset == at
        at += len(pcm)
    for sample in {0, len(payload) // 2, len(payload) - 1}:
        offset, pcm = flac.seek(media, sample)
        assert offset <= sample < offset + len(pcm) and payload[offset : offset + len(pcm)] == pcm


def test_flac_checksums():
    assert flac.crc8(b"123456789") == 0xF4 and flac.crc16(b"123456789") == 0xFEE8
    media = bytearray(flac.encode(b"some text, some more text. " * 200))
    for at in (len(media) - 1, len(media) - 700, media.rfind(b"\xff\xf8") + 5):
        bad = bytearray(media)
        bad[at] ^= 4
        with pytest.raises(ValueError):
            list(flac.decode_blocks(bytes(bad)))
    bad = bytearray(media)
    bad[26] ^= 1  # the MD5 in the stream information
    with pytest.raises(ValueError):
        list(flac.decode_blocks(bytes(bad)))


def test_flac_subframes_and_partitions():
    """All kinds of subframe occur, and partitions and escapes of other encoders are read."""
    kinds = set()
    for payload in (bytes(500), os.urandom(500), bytes(range(200)) * 3, b"abcabcabd" * 60):
        for lpc in (0, 8):
            media = flac.encode(payload, lpc_order=lpc)
            head = flac.read_head(media)
            kinds.add(media[head["start"] + 8] >> 1)
    assert 0 in kinds and 1 in kinds and any(8 <= k <= 12 for k in kinds) and any(k >= 32 for k in kinds)
    z = np.array([3, 0, 9, 1, 200, 7, 2, 2])
    bits = np.concatenate([flac._put(0, 2), flac._put(1, 4), flac._put(2, 4), flac._rice(z[:4], 2), flac._put(15, 4), flac._put(9, 5), *(flac._put(int(v) & 511, 9) for v in (-100, 5, 0, 255))])
    got = flac.Bits(np.packbits(bits).tobytes() + b"\0", 0).residual(8, 0)
    assert got.tolist() == [(int(v) >> 1) ^ -(int(v) & 1) for v in z[:4]] + [-100, 5, 0, 255]


def test_flac_frame_numbers():
    for n in (0, 127, 128, 2047, 2048, 65535, 65536, 2**21, 2**31 - 1):
        code = flac._coded(n)
        assert flac._uncoded(code, 0) == (n, len(code))
    assert [flac._coded(ord(c)) for c in "é€\U0001f600"] == [c.encode() for c in "é€\U0001f600"]


def test_flac_query(spark, sf):
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    for r in queries.op3_flac(spark, sf).collect():
        payload = flac.pad(texts[r.doc_id])
        media = flac.encode(payload)
        x = np.frombuffer(payload, np.uint8).astype(int) - 128
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(texts[r.doc_id].encode()), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
        assert (r.media_bytes, r.media_sha256) == (len(media), hashlib.sha256(media).hexdigest())
        assert r.feature.startswith(f"sum={x.sum()};energy={(x * x).sum()};")


def test_flac_edges(spark):
    out = {r.doc_id: r for r in flac.features(flac.store(documents(spark))).collect()}
    assert out[3].payload_sha256 == out[4].payload_sha256 == hashlib.sha256(bytes(64)).hexdigest() and out[3].n_bytes == 0 and out[3].payload_bytes == 64
    assert out[1].media_sha256 == out[2].media_sha256
    blocks = flac.pcm_blocks(flac.store(documents(spark).where("doc_id = 6"))).orderBy("sample_offset").collect()
    assert len(blocks) > 1 and sum(b.n_samples for b in blocks) == out[6].payload_bytes
    assert flac.features(flac.store(empty(spark))).count() == 0


@pytest.mark.parametrize("together", [1, 5000, 1 << 21])
def test_flac_streams_side_by_side(together):
    """Frames of several streams, orders and lengths are undone together, and every stream is checked for itself."""
    r = random.Random(3)
    payloads = [flac.pad("".join(r.choice("ab cd e\n") for _ in range(n))) for n in (0, 1, 63, 64, 4096, 9000, 300, 12000)] + [os.urandom(6400), bytes(128)]
    media = [flac.encode(p, lpc_order=o) for p, o in zip(payloads, [8, 0, 4, 8, 12, 8, 1, 2, 8, 8])]
    got = {}
    for i, at, pcm in flac.decode_all(media, together):
        assert at == len(got.get(i, b""))
        got[i] = got.get(i, b"") + pcm
    assert [got[i] for i in range(len(payloads))] == payloads
    bad = bytearray(media[6])
    bad[26] ^= 1
    with pytest.raises(ValueError):
        list(flac.decode_all([*media[:6], bytes(bad), *media[7:]], together))


def test_flac_media_is_read_from_files(spark, sf):
    plan = queries.op3_flac(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "media" in plan.split("FileScan")[1] and "documents.parquet" not in plan


def test_pcm_table(spark, sf, tmp_path):
    """Any sample is found by document and offset, in the payload's bytes."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    pcm = flac.write_pcm(flac.stored(docs), str(tmp_path / "pcm"))
    texts = {r.doc_id: flac.pad(r.text) for r in docs.collect()}
    long_ = max(texts, key=lambda d: len(texts[d]))
    for doc, sample in ((long_, 0), (long_, 5000), (long_, len(texts[long_]) - 1), (0, 17)):
        (b,) = flac.block_at(pcm, doc, sample).collect()
        assert bytes(b.pcm) == texts[doc][b.sample_offset : b.sample_offset + b.n_samples] and b.sample_offset <= sample < b.sample_offset + b.n_samples
    by = {}
    for b in sorted(pcm.collect(), key=lambda b: b.sample_offset):
        by[b.doc_id] = by.get(b.doc_id, b"") + bytes(b.pcm)
    assert by == texts


# ---------------------------------------------------------------- HTML


def article(html_text):
    """The article of the given template, by its tags."""
    import html

    inner = re.search(r"<article>(.*)</article>", html_text, re.S)[1]
    blocks = [" ".join(html.unescape(re.sub(r"<[^>]+>", "", b)).split()) for b in re.split(r"</?(?:p|h1)[^>]*>", inner)]
    return "\n".join(b for b in blocks if b)


def test_pages_of_the_given_template(spark):
    d = "/root/testdata/sf0.01"
    pages = {r.page_id: r.html for r in spark.read.parquet(f"{d}/pages.parquet").collect()}
    for r in queries.op5_boosted_trees(spark, d).collect():
        assert r.text == article(pages[r.page_id]) and r.n_chars == len(r.text)


def test_held_out_templates():
    model, inventor = X.train(), X.Inventor(99)
    exact = words = wrong = 0
    for _ in range(150):
        page = inventor.page()
        _, nodes = dom.parse(page)
        want = [x.text.replace(X.MARK, "") for x in nodes if x.tag == "#run" and X.MARK in x.text]
        got = X.extract([page.replace(X.MARK, "")], model)[0].split("\n")
        exact += want == got
        words += len(want)
        wrong += len(set(want) ^ set(got))
    assert exact / 150 > 0.9 and wrong / words < 0.05


def test_hand_made_page():
    page = """<html><head><title>no</title><style>x{}</style></head><body>
    <div class="cookie-notice"><p>We use cookies to make this better.</p><button>OK</button></div>
    <header><a href=/>Site</a><nav><ul><li><a>Home</a><li><a>News</a></ul></nav></header>
    <main><article><h1>Big &amp; small</h1><p>First   para with <b>bold</b> and&nbsp;more text that goes on for a while.<p>Second one, &lt;quoted&gt; here, is also long enough to count as text.
    <div class="advert"><p>Buy now!</p></div><p>Last.</p></article></main>
    <aside class="sidebar"><h3>Popular</h3><ul><li><a>One</a><li><a>Two</a></ul></aside>
    <section id="comments"><h3>3 comments</h3><div class="comment"><p>Nice text, thank you for it.</p></div></section>
    <form><label>Mail</label><input><button>Go</button></form><footer>&copy; us</footer><script>var x = "<p>no</p>";</script></body></html>"""
    got = X.extract([page], X.train())[0]
    assert got == "Big & small\nFirst para with bold and more text that goes on for a while.\nSecond one, <quoted> here, is also long enough to count as text.\nLast."


#: Layouts that the inventor of training pages doesn't make: (page, main text).
LAYOUTS = {
    "formula": ("""<body><nav class="menu"><a href=/a>Start</a> <a href=/b>About</a></nav><article><h1>On energy</h1><p>The energy is <math><mi>E</mi><mo>=</mo><mi>mc</mi></math> as known since long ago, and it holds for all of them.</p>
        <p hidden>This paragraph waits for a click before it shows, and it belongs to the article.</p><p aria-hidden=true>So does this one, which readers of screens pass over.</p></article><footer><p>&copy; 2020 all rights reserved</p></footer></body>""",
        "On energy\nThe energy is E=mc as known since long ago, and it holds for all of them.\nThis paragraph waits for a click before it shows, and it belongs to the article.\nSo does this one, which readers of screens pass over."),
    "table layout": ("""<table width=100%><tr><td colspan=2 id=banner><a href=/>Home of words</a></td></tr><tr><td id=nav><a href=/1>One</a><br><a href=/2>Two</a><br><a href=/3>Three</a></td>
        <td class=content><h2>A trip to the coast</h2><p>We left early in the morning, when the streets were still empty, and drove west for hours.</p><p>At noon we saw the sea. It was grey, and the wind was strong, but nobody minded.</p></td></tr>
        <tr><td colspan=2 class=footer>Copyright by the author. Mail to the webmaster.</td></tr></table>""",
        "A trip to the coast\nWe left early in the morning, when the streets were still empty, and drove west for hours.\nAt noon we saw the sea. It was grey, and the wind was strong, but nobody minded."),
    "documentation": ("""<div id=wrapper><div class="sideBar-left"><ul><li><a href=x>Install</a></li><li><a href=y>Configure</a></li></ul></div><div role=main><section><h1>Install</h1><p>Unpack the archive in a folder of your choice, then run the setup from there.</p>
        <pre>tar xf a.tar; ./setup</pre><h2>Upgrade</h2><ol><li>Stop the service first.</li><li>Run the setup again.</li></ol></section></div></div><footer><a href=p>Privacy</a> <a href=t>Terms</a></footer>""",
        "Install\nUnpack the archive in a folder of your choice, then run the setup from there.\ntar xf a.tar; ./setup\nUpgrade\nStop the service first.\nRun the setup again."),
    "story between adverts": ("""<main><div class="post-body"><p>It rained all week in the valley, and the river rose above the bridge by Friday.</p><div class="ad-slot-2"><span>Advertisement: buy a boat</span></div><p>On Sunday the water fell again. People came back, one house at a time, to see what was left.</p>
        <blockquote>We had never seen anything like it.</blockquote></div><div class="related-posts"><h3>More news</h3><ul><li><a href=1>Floods of the past</a></li><li><a href=2>Weather</a></li></ul></div></main>
        <section class="comments-area"><h3>2 comments</h3><ol><li class=comment><p>I was there, it was bad.</p></li><li class=comment><p>So was I.</p></li></ol></section>""",
        "It rained all week in the valley, and the river rose above the bridge by Friday.\nOn Sunday the water fell again. People came back, one house at a time, to see what was left.\nWe had never seen anything like it."),
}


@pytest.mark.parametrize("name", LAYOUTS)
def test_layouts_the_inventor_does_not_make(name):
    page, want = LAYOUTS[name]
    assert X.extract([f"<html><head><title>t</title></head><body>{page}</body></html>"], X.train())[0] == want


def test_token_odds_are_learnt():
    """Signs come from the pages alone; tokens that were never seen say nothing."""
    odds = X.train().tokens
    value = lambda t: odds.get(X.token_buckets(t)[0], 0.0)
    assert all(value(t) < -X.SIGN for t in ("sidebar", "cookie", "advert", "comment", "footer")) and all(value(t) > X.SIGN for t in ("article", "entry", "story"))
    assert value("zzqwx") == 0.0 and X.token_buckets("sideBar") == X.token_buckets("side-bar_2")


def test_decoding_is_consistent():
    """No kept node under a dropped one, and no consistent choice has a larger sum."""
    r = random.Random(4)
    for _ in range(200):
        nodes = [dom.Node("#root", None)]
        for _ in range(r.randint(0, 7)):
            n = dom.Node("div", r.choice(nodes))
            n.parent.children.append(n)
            nodes.append(n)
        nodes.sort(key=lambda x: x.depth)
        odds = np.array([r.uniform(-2, 2) for _ in nodes])
        kept = X.decode(nodes, odds)
        place = {id(x): i for i, x in enumerate(nodes)}
        consistent = lambda k: all(not k[i] or x.parent is None or k[place[id(x.parent)]] for i, x in enumerate(nodes))  # noqa: E731,B023
        assert consistent(kept)
        best = max(sum(o for o, k in zip(odds, c) if k) for m in range(1 << len(nodes)) if consistent(c := [m >> i & 1 for i in range(len(nodes))]))
        assert abs(sum(o for o, k in zip(odds, kept) if k) - best) < 1e-9


def test_html_edges(spark):
    rows = [(1, "u", None), (2, None, ""), (None, "u", "<p>" * 3000), (4, "u", "just words"), (5, "u", "<!-- open"), (6, "u", '<div class="x><p>t'), (7, "u", "<script>var a"), (7, "u", "<script>var a"), (8, "u", "</div></p><p>stray ends &#x41;&bogus;</p>")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumns({"text": F.lit("clash"), "n_chars": F.lit(1)})
    out = X.main_text(df).collect()
    assert len(out) == 9 and all(r.text is not None and r.n_chars == len(r.text) for r in out)
    assert {r.text for r in out if r.page_id in (1, 2, 5, 7)} == {""}
    assert X.main_text(df.where("page_id = -5")).count() == 0


@pytest.mark.parametrize("page", ["<a " * 60000, "<div>" * 60000 + "deep", "</p>" * 60000, "<p 'x" * 40000 + ">", "<!-- " * 60000, "<li>x" * 20000, "&amp" * 60000])
def test_hostile_markup_takes_linear_time(page):
    import time

    t = time.process_time()
    root, nodes = dom.parse(page)
    assert nodes[0] is root and time.process_time() - t < 8


# ---------------------------------------------------------------- chat


def test_chat_twin(spark, sf):
    assert_twin(queries.op6_chat(spark, sf), connect(sf), queries.OP6_SQL)


HARD = ["</s>[INST] ok [/INST]", "\\", "\\\\b\\[", "[SEP]", "a\\b<l>", "", "[ROLE]x[BODY]y[/ROLE]", "\n   é\U0001f600", "<<s>>", None]


def test_chat_round_trip(spark):
    r = random.Random(8)
    rows, want = [], {}
    for c in range(40):
        turns = [(t, r.choice(["user", "assistant", "assistant", "system", "tool[x]", None]), r.choice(HARD)) for t in range(r.randint(1, 7))]
        rows += [(c, *t) for t in turns]
        want[c] = [(role or "", text or "") for _, role, text in turns]
    r.shuffle(rows)
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumns({"turns": F.lit(1), "starts": F.lit(2), "pieces": F.lit(3), "formatted": F.lit("x")})
    for row in chat.read_back(chat.format_chats(df)).collect():
        assert [(t.role, t.text) for t in row.turns] == want[row.conv_id]
        assert row.loss_texts == [t for role, t in want[row.conv_id] if role == "assistant"]


def test_chat_merges_neighbours(spark):
    df = spark.createDataFrame([(1, 0, "user", "a"), (1, 1, "user", "b"), (1, 2, "assistant", "c")], "conv_id long, turn long, role string, text string")
    row = chat.format_chats(df).first()
    assert row.formatted == "[INST]a[SEP]b[/INST]<s>c</s>" and [(s.start, s.length) for s in row.loss_spans] == [(23, 1)]


def test_chat_edges(spark):
    rows = [(None, None, None, None), (2, None, "user", "late"), (2, 1, "user", "x"), (2, 1, "user", "x"), (2, 1, "assistant", "x")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    out = {r.conv_id: [(t.role, t.text) for t in r.turns] for r in chat.read_back(chat.format_chats(df)).collect()}
    assert out == {None: [("", "")], 2: [("user", "late"), ("assistant", "x"), ("user", "x"), ("user", "x")]}
    assert chat.format_chats(df.where("conv_id = -7")).count() == 0


def test_chat_plan_is_native(spark, sf):
    plan = queries.op6_chat(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas|ExistingRDD", plan)


# ---------------------------------------------------------------- sharding


def table_by_hand(shards, slots):
    """Turn-taking with permutations written out."""
    prefs = []
    for s in shards:
        o, k = sharding.preference(s, slots)
        prefs.append([(o + j * k) % slots for j in range(slots)])
    owner, nxt = [None] * slots, [0] * len(shards)
    while None in owner:
        for i, p in enumerate(prefs):
            if None not in owner:
                break
            while owner[p[nxt[i]]] is not None:
                nxt[i] += 1
            owner[p[nxt[i]]] = i
    return owner


@pytest.mark.parametrize("n, slots", [(1, 7), (3, 31), (5, 211), (7, 7)])
def test_lookup_table(n, slots):
    names = tuple(f"s{i}" for i in range(n))
    table = sharding.lookup_table(names, slots)
    assert table == table_by_hand(names, slots)
    counts = [table.count(i) for i in range(n)]
    assert max(counts) - min(counts) <= 1


def test_few_slots_move():
    names = tuple(f"s{i}" for i in range(20))
    before, after = sharding.lookup_table(names, 4099), sharding.lookup_table(names[:-1], 4099)
    moved = sum(a != b for a, b in zip(before, after) if a != 19)
    assert moved / 4099 < 0.1
    heavy = sharding.lookup_table(names, 4099, {"s0": 3})
    assert 2.5 < heavy.count(0) / heavy.count(1) < 3.5
    with pytest.raises(ValueError):
        sharding.lookup_table(names, 4100)


def test_sharding_twin(spark, sf):
    assert_twin(queries.op8_lookup(spark, sf), connect(sf), queries.oracle_sql()["op8_lookup"])


def test_sharding_edges(spark):
    out = sharding.place(documents(spark).drop("slot", "shard"), "doc_id")
    assert out.count() == 11 and out.where("shard IS NULL").isEmpty()
    assert out.where("doc_id = 2").select("shard").distinct().count() == 1
    assert sharding.place(documents(spark), "text").where("slot IS NULL OR shard = 's'").isEmpty()  # clashing columns are replaced
    assert sharding.place(empty(spark), "doc_id").count() == 0
    assert sharding.sizes(out).agg(F.sum("n_rows")).first()[0] == 11


# ---------------------------------------------------------------- WARC


def test_warc_twin(spark, sf):
    assert_twin(queries.op10_warc(spark, sf), connect(sf), queries.OP10_SQL)


def test_warc_bundles(spark, tmp_path):
    import zstandard

    r = random.Random(6)
    big = "z" * 1500
    rows = [(i, f"http://x/{i} \n", "".join(r.choice("abc é") for _ in range(r.randint(0, 4000)))) for i in range(120)] + [(500, None, big), (700, "u", big), (600, "u", big), (700, "u", big), (None, "u", big), (800, "u", None), (None, "u", "q" * 300), (900, "u", "q" * 300)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumns({"digest": F.lit("clash"), "owner": F.lit(1), "payload": F.lit("x")}).repartition(2)
    warc.write_bundles(pages, f"{tmp_path}/w", frame_bytes=8000, bundle_bytes=30000)
    bundles = spark.read.schema(warc.BUNDLE).parquet(f"{tmp_path}/w")
    back = warc.read_records(bundles).collect()
    assert len(back) == len(rows)
    html = {i: h or "" for i, _, h in rows if i is not None}
    for x in back:
        if x.record_type == "response" and x.page_id is not None:
            assert x.payload.decode() == html[x.page_id] and x.payload_digest == hashlib.sha1(x.payload).hexdigest()
    kinds = sorted((x.page_id or -1, x.record_type, x.refers_to, x.payload_bytes) for x in back if x.payload_bytes == 1500)
    assert kinds == [(-1, "revisit", 700, 1500), (500, "revisit", 700, 1500), (600, "revisit", 700, 1500), (700, "response", None, 1500), (700, "response", None, 1500)]
    assert {x.record_type for x in back if x.payload_bytes == 300} == {"response"}
    data = {hashlib.sha1(b.bundle).hexdigest(): bytes(b.bundle) for b in bundles.collect()}
    assert len(data) > 2
    for b in data.values():  # a plain Zstandard reader takes the whole bundle, skippable footer included
        whole = zstandard.ZstdDecompressor().stream_reader(b, read_across_frames=True).read()
        assert whole == b"".join(warc.frame(b, i) for i in range(len(warc.read_seek_table(b))))
    for e in warc.record_index(bundles).collect():  # any record by its frame and offset alone
        raw = warc.frame(data[e.bundle_id], e.frame)[e.offset : e.offset + e.length]
        head, _, end = warc.parse_record(raw)
        assert end == len(raw) and head["WARC-Record-ID"] == f"<urn:page:{'unknown' if e.page_id is None else e.page_id}>"


def test_warc_empty(spark, tmp_path):
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    assert warc.read_records(warc.archive(pages, f"{tmp_path}/e")).count() == 0
