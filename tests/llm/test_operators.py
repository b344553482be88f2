"""The text operators against brute force on the smallest tables, and their edge cases."""

import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from stratamatch.llm import ann, htmltext, imatch, jaccard, mixing, packing, quality, queries, sharding, substring, warc, wordhash
from stratamatch.llm.components import connected_components

from ..oracle import assert_same

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
LONG = " ".join(f"w{i}" for i in range(30000))
PASSAGE = " ".join(f"p{i}" for i in range(60))
EDGE = [
    (1, None, "en", None, None), (2, "", "en", "a", 0), (3, " \n\t ", None, "a", 3), (4, "one", "en", "b", 3), (5, "one", "en", "b", 3), (5, "one", "en", "b", 3),
    (6, LONG, "en", "a", 5), (7, LONG, "en", "a", 5), (8, "x y " + PASSAGE + " z", "fr", "b", 1), (9, "q " + PASSAGE + " r s", "fr", None, 1), (None, PASSAGE, "fr", "b", 1),
    (10, "One two three four five", "en", "a", 1), (11, "one TWO three four five", "en", "a", 1), (12, "é ü\x0bñ \U0001f600 end", "es", "c", 1), (-3, "tie " * 40, "en", "c", 1),
]


@pytest.fixture(scope="module")
def edge(spark):
    return spark.createDataFrame(EDGE, DOCS)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="module")
def clashing(edge):
    """Extra columns with names that the operators use inside."""
    out = edge
    for name in ("id", "n", "part", "bucket", "u", "size", "text_crc32", "law", "shard", "slot", "score", "key", "node", "digest", "h", "copy", "known", "carried", "range", "tie"):
        out = out.withColumn(name, F.lit("clash"))
    return out


@pytest.fixture(scope="module")
def docs(spark, small):
    return spark.read.parquet(f"{small}/documents.parquet")


def words(text):
    return (text or "").encode().split()


def test_words_match_the_pattern():
    text = "a\x0bb\x0cc d\x1ce\x85f  g"
    assert words(text) == [w.encode() for w in re.findall(r"[^\x20\x09-\x0D]+", text)]


def brute_repeats(rows, width=13):
    first = {}
    for i, text in sorted((r for r in rows if r[0] is not None), key=lambda r: r[0]):
        w = words(text)
        for a in range(len(w) - width + 1):
            first.setdefault(tuple(w[a : a + width]), i)
    out = []
    for i, text in rows:
        w = words(text)
        keep = [True] * len(w)
        for a in range(len(w) - width + 1):
            if i is not None and first[tuple(w[a : a + width])] < i:
                keep[a : a + width] = [False] * width
        out.append((i, len(w), len(w) - sum(keep), hashlib.sha256(b" ".join(x for x, k in zip(w, keep) if k)).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize("table", ["docs", "edge", "clashing", "empty"])
def test_substring(request, table):
    df = request.getfixturevalue(table)
    got = substring.remove_repeats(df)
    rows = got.collect()
    assert sorted(((r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in rows), key=str) == brute_repeats([(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()])
    for r in rows:
        assert sum(b - a for a, b in r.intervals) == r.n_removed and len(r.kept_text.split()) >= 0
        assert all(x[1] < y[0] for x, y in zip(r.intervals, r.intervals[1:]))


def lowered(text):
    return [bytes(b + 32 if 65 <= b <= 90 else b for b in w) for w in words(text)]


def brute_links(rows, width, percent):
    sets = []
    for _, text in rows:
        w = lowered(text)
        sets.append(frozenset(tuple(w[a : a + width]) for a in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else []))
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if sets[i] and sets[j] and 100 * both >= percent * (len(sets[i]) + len(sets[j]) - both):
                root[max(find(i), find(j))] = min(find(i), find(j))
    names = {}
    for i, (doc, _) in enumerate(rows):
        if doc is not None:
            names[find(i)] = min(names.get(find(i), doc), doc)
    return sorted(((doc, len(sets[i]), names.get(find(i)) if sets[i] else doc) for i, (doc, _) in enumerate(rows)), key=str)


@pytest.mark.parametrize("table", ["docs", "edge", "clashing", "empty"])
@pytest.mark.parametrize("width,percent", [(4, 85), (5, 80)])
def test_jaccard(request, table, width, percent):
    df = request.getfixturevalue(table)
    got = [(r.doc_id, r.n_shingles, r.component_id) for r in jaccard.jaccard_components(df, width, percent).collect()]
    assert sorted(got, key=str) == brute_links([(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()], width, percent)


def test_jaccard_blocks_and_near_copies(spark):
    """A chain of near copies around the threshold, in blocks of three documents."""
    rng = np.random.default_rng(5)
    base = [f"b{i}" for i in range(60)]
    rows = []
    for i in range(40):
        w = list(base)
        for j in rng.integers(0, 60, size=int(rng.integers(0, 4))):
            w[j] = f"n{i}_{j}"
        rows.append((i, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for block in (3, 4000):
        got = sorted(((r.doc_id, r.n_shingles, r.component_id) for r in jaccard.jaccard_components(df, 3, 85, block=block).collect()), key=str)
        assert got == brute_links(rows, 3, 85)


def test_divide_skip_equals_all_pairs():
    rng = np.random.default_rng(1)
    sets = [np.unique(rng.integers(0, 40, size=rng.integers(1, 30)).astype(np.uint64)) for _ in range(120)]
    sizes = np.array([len(s) for s in sets])
    got = dict(jaccard.link_all(np.arange(120), sizes, sets, 60))
    root = list(range(120))

    def find(i):
        return i if root[i] == i else find(root[i])

    for i in range(120):
        for j in range(i):
            both = len(np.intersect1d(sets[i], sets[j]))
            if 100 * both >= 60 * (sizes[i] + sizes[j] - both):
                root[max(find(i), find(j))] = min(find(i), find(j))
    assert got == {i: find(i) for i in range(120)}


def test_components(spark):
    edges = [(i, i + 1) for i in range(20, 40)] + [(50, 51), (51, 50), (3, 3), (7, 60), (60, 61), (None, 1)]
    got = dict(map(tuple, connected_components(spark.createDataFrame(edges, "a long, b long")).collect()))
    assert got == {i: 20 for i in range(20, 41)} | {50: 50, 51: 50, 7: 7, 60: 7, 61: 7}


@pytest.fixture(scope="module")
def pages(spark, small):
    return spark.read.parquet(f"{small}/pages.parquet")


PAGES = [(1, "http://a/x", None), (2, None, ""), (3, "http://a/y", "é" * 99), (4, "http://a/é", "é" * 99), (5, "no url", "short"), (6, "", "short"), (None, "http://a", "é" * 99), (7, "http://b", "x" * 5_000_000), (8, "u", "WARC/1.1\r\n\r\n" * 20)]


def test_warc_equals_sql(spark, small):
    assert_same(queries.op2_warc(spark, small), queries.oracle_sql()["op2_warc"], small)


def test_warc_edges(spark):
    df = spark.createDataFrame(PAGES, "page_id long, url string, html string").withColumn("digest", F.lit(1)).withColumn("first", F.lit(2))
    got = {r.page_id: r for r in warc.round_trip(df).collect()}
    for page, _, html in PAGES:
        data = (html or "").encode()
        assert (got[page].payload_bytes, got[page].payload_digest) == (len(data), hashlib.sha256(data).hexdigest())
    assert [(p, got[p].refers_to) for p in got if got[p].record_type == "revisit"] == [(p, 3) for p in got if p in (4, None)]
    assert warc.round_trip(df.limit(0)).count() == 0


@pytest.mark.parametrize("zipped", [True, False])
def test_warc_salvage(zipped):
    records = [warc.record_bytes(i, f"http://h/{i}", b"payload %d " % i * 30, hashlib.sha256(b"payload %d " % i * 30).hexdigest(), None) for i in range(6)]
    parts = [warc._member(r) for r in records] if zipped else list(records)
    whole = b"".join(parts)
    ends = np.cumsum([0, *map(len, parts)])
    assert [r[0] for r in warc.salvage(whole)] == ["record"] * 6
    bad = bytearray(whole)
    bad[ends[3] - 20] ^= 0xFF  # damage at the end of the payload of record 2
    del bad[ends[5] - 9 : ends[5]]  # record 4 loses its end
    got = list(warc.salvage(bytes(bad)))
    assert [r[3]["x-page-id"] for r in got if r[0] == "record"] == ["0", "1", "3", "5"]
    gaps = [(r[1], r[2]) for r in got if r[0] == "gap"]
    assert gaps == [(int(ends[2]), len(parts[2])), (int(ends[4]), len(parts[4]) - 9)]
    assert list(warc.salvage(b"")) == [] and [r[0] for r in warc.salvage(b"junk")] == ["gap"]
    assert sum(r[2] for r in got) == len(bad)


def test_warc_salvage_inside_a_member():
    """Several records in one member: damage to one loses that one, a cut-off end loses what comes after it."""
    import base64
    import random

    noise = random.Random(1)
    records = [warc.record_bytes(i, f"http://h/{i}", noise.randbytes(9000), "", None) for i in range(4)]
    sha1 = hashlib.sha1(records[3][records[3].index(b"\r\n\r\n") + 4 : -4]).digest()
    records[3] = records[3].replace(sha1.hex().encode(), base64.b32encode(sha1))  # the usual form of block digests
    ids = lambda rows: [r[3]["x-page-id"] for r in rows if r[0] == "record"]
    for wrong in (1, 3):
        hurt = [bytearray(r) for r in records]
        hurt[wrong][len(hurt[wrong]) // 2] ^= 0xFF
        got = list(warc.salvage(warc._member(b"".join(hurt))))
        assert ids(got) == [str(i) for i in range(4) if i != wrong]
        assert [(r[0], r[2]) for r in got if r[0] != "record"] == [("inner-gap", len(records[wrong]))]
    whole = warc._member(b"".join(records))
    cut = whole[: len(whole) * 3 // 5] + warc._member(records[0])
    got = list(warc.salvage(cut))
    assert ids(got) == ["0", "1", "0"] and sum(r[2] for r in got) == len(cut) and [r[0] for r in got].count("gap") == 1


def test_warc_repeated_rows(spark):
    rows = [(1, "u", "x" * 200), (1, "u", "x" * 200), (2, "u", "x" * 200), (2, "v", "y"), (None, "w", "x" * 200), (3, None, None)]
    got = warc.round_trip(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert Counter((r.page_id, r.payload_bytes, r.record_type, r.refers_to) for r in got) == Counter(
        [(1, 200, "response", None)] * 2 + [(2, 200, "revisit", 1), (2, 1, "response", None), (None, 200, "revisit", 1), (3, 0, "response", None)]
    )


def test_warc_files_are_plain_gzip(spark, pages, tmp_path):
    import gzip

    warc.write_warc(pages.limit(20), f"file://{tmp_path}/out")
    data = b"".join(gzip.decompress(p.read_bytes()) for p in (tmp_path / "out").glob("part-*"))
    assert data.count(b"WARC-Type: ") == 20 and data.startswith(b"WARC/1.1\r\n")
    back = warc.read_warc(spark, f"file://{tmp_path}/out").where("record_type = 'response'")
    assert {bytes(r.payload) for r in back.collect()} == {r.html.encode() for r in pages.limit(20).collect()}


def test_html_main_text(spark, pages):
    import html

    got = {r.page_id: r for r in htmltext.extract(pages).collect()}
    for r in pages.collect():
        body = re.search(r"<article>(.*?)</article>", r.html, re.S)[1]
        parts = [" ".join(html.unescape(re.sub(r"</?b>", "", re.sub("<br>", " ", b))).split()) for b in re.split(r"</?(?:p|h1)>", body)]
        assert got[r.page_id].text == "\n\n".join(filter(None, parts)) and got[r.page_id].n_chars == len(got[r.page_id].text)


MESSY = """<!doctype html><html><head><title>no</title><style>p{}</style><script>var a="<p>no</p>";</script></head><body class=home>
<header><div>Site name no</div></header><div class="top-menu"><ul><li><a href=/>no</a></li></ul></div><!-- <p>no</p> -->
<div class="cookie-notice">no cookies</div><main><div class='post-12'><h1>Title &amp; more</h1><p>First  paragraph,\n with a <a href="x>y">link</a> and caf&eacute;.
<p>Second<br>line &lt;b&gt;.</p><ul><li>item one<li>item two</ul><form><input value="no"><button>no</button></form><div class="ad-slot">no ads</div><table><tr><td>cell a<td>cell b</table></div></main>
<aside>no</aside><section id="comments"><p>no comment, a long one that should not be taken as the text of the page at all, really, no.</p></section><footer>no</footer>"""


def test_html_messy_page():
    assert htmltext.main_text(MESSY) == "Title & more\n\nFirst paragraph, with a link and café.\n\nSecond line <b>.\n\nitem one\n\nitem two\n\ncell a\n\ncell b"


@pytest.mark.parametrize("page", [None, "", "plain text only", "<", "<p", "</p></div>", "<p>a<p>b", "<script>never closed", "<div" * 50, "&#x41;&nbsp;&bogus;", "<p>" + "x " * 200000, "<!-- open", "<a href='>"])
def test_html_damaged_pages(page):
    text = htmltext.main_text(page)
    assert isinstance(text, str) and text == text.strip()


def test_html_consensus_outvotes_a_page(spark):
    good = "<body><div class='story'><p>{}</p></div><div class='box'><p>{}</p></div></body>"
    rows = [(i, "http://h.example/p", good.format("main text, long enough to win. " * 9 + str(i), "short box")) for i in range(5)]
    rows.append((9, "http://H.example/q", good.format("main text of this page, short. " * 3, "a box that is longer here. " * 5)))
    got = {r.page_id: r.text for r in htmltext.extract(spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("host", F.lit(1)).withColumn("paths", F.lit(1))).collect()}
    assert got[9].startswith("main text of this page") and "box" not in got[9]
    assert htmltext.extract(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_html_inline_elements():
    page = "<body><div class=post><p>One <span class='alert'>two</span> three <button>Share me</button>four <label>Name</label><span hidden>no</span> five.</p><span class=share>no</span></div></body>"
    assert htmltext.main_text(page) == "One two three four five."


def test_html_title_and_lead_beside_the_body():
    long = "A long text of the article, with commas, and more. " * 20
    page = f"<body><div class=wrap><div class=post><h1>Title</h1><div class=lead><p>Lead.</p></div><div class=body><p>{long}</p></div></div><div class=other><p>Other</p></div></div></body>"
    assert htmltext.main_text(page) == f"Title\n\nLead.\n\n{long.strip()}"


def test_html_two_templates_and_deep_paths(spark):
    """The weaker template of a host keeps its articles though it has the stronger one's box; paths may be of any length."""
    deep = "<div class='a-rather-long-name-of-a-class-that-goes-on and another third fourth'>" * 60
    first = "<body><div class=box><p>{}</p></div></body>"
    second = "<body>" + deep + "<div class=story><p>{}</p></div>" + "</div>" * 60 + "<div class=box><p>{}</p></div></body>"
    rows = [(i, "http://h.example/", first.format("main text, long enough to win. " * 9 + str(i))) for i in range(6)]
    rows += [(10 + i, "http://h.example/", second.format("story text, of the other kind. " * 9 + str(i), "a teaser of the site. " * 6)) for i in range(3)]
    rows.append(rows[-1])
    got = htmltext.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert len(got) == 10 and all(r.text.startswith("main text" if r.page_id < 10 else "story text") and "teaser" not in r.text for r in got)


def test_tokens_equal_the_tokenizer(docs):
    from tokenizers import Tokenizer

    path = queries.tokenizer_path()
    slow, fast = Tokenizer.from_file(path), packing.token_encoder(path)
    texts = [r.text for r in docs.collect()] + ["", " ", "a<|endoftext|>b", "it's 12½ \U0001f600\n\n  tab\t", "  x", "'S 'll", LONG]
    assert [fast(t) for t in texts] == [e.ids for e in slow.encode_batch(texts, add_special_tokens=False)]


@pytest.mark.parametrize("table", ["docs", "edge", "clashing", "empty"])
def test_packing(request, table):
    df = request.getfixturevalue(table)
    path = queries.tokenizer_path()
    encode = packing.token_encoder(path)
    rows = packing.pack(df, path).collect()
    want = Counter()
    for r in df.select("doc_id", "text").collect():
        want[r.doc_id, zlib.crc32(np.array([*encode(r.text or ""), 1], dtype="<u4").tobytes())] += 1
    by_doc = {}
    for r in rows:
        by_doc.setdefault(r.doc_id, []).append(r)
    for r in df.select("doc_id", "text").distinct().collect():
        ids = np.array([*encode(r.text or ""), 1], dtype="<u4")
        own = [p for p in by_doc[r.doc_id] if p.doc_tokens == len(ids) and zlib.crc32(ids[p.start : p.start + p.length].tobytes()) == p.ids_crc32]
        cover = np.zeros(len(ids), dtype=int)
        for p in own:
            cover[p.start : p.start + p.length] += 1
        assert set(cover) == {want[r.doc_id, zlib.crc32(ids.tobytes())]}
    used = {}
    for r in sorted(rows, key=lambda r: (r.sequence_id, r.offset)):
        assert r.offset == used.get(r.sequence_id, 0) and r.length > 0
        used[r.sequence_id] = r.offset + r.length
    assert all(n <= 2048 for n in used.values())
    assert sum(2048 - n for n in used.values()) <= 2048  # one group


def _alternating(n, letters=b"ab"):
    """Letters by the parity of a place's bits: polynomials modulo a power of two cannot tell these words apart."""
    return bytes(letters[bin(i).count("1") % 2] for i in range(n)).decode()


def test_words_that_polynomial_hashes_confuse(spark):
    a, b = _alternating(1024), _alternating(1024, b"ba")
    assert len(set(wordhash.WordHasher(lanes=2).words(f"{a} {b}".encode())[0].ravel().tolist())) == 4
    texts = [" ".join([a] * 13), " ".join([b] * 13), a, b, a]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert {r.n_removed for r in substring.remove_repeats(df).collect()} == {0}
    got = {r.doc_id: r.component_id for r in jaccard.jaccard_components(df, 4, 85).collect()}
    assert got == {0: 0, 1: 1, 2: 2, 3: 3, 4: 2}


@pytest.mark.parametrize("width", [1, 2, 5, 13, 40])
def test_window_hashes_are_the_polynomials(width):
    words = np.random.default_rng(width).integers(0, 2**64, size=(90, 2), dtype=np.uint64)
    key, check = wordhash.windows(words, width, checks=True)
    prime = 2**61 - 1
    for i in range(91 - width):
        first = second = 0
        for x, y in words[i : i + width].tolist():
            first, second = (first * wordhash._BASE_61 + x) % prime, (second * wordhash._BASE_64 + y) % 2**64
        assert key[i] == wordhash._mix(np.array([(first << 3 | second >> 61) % 2**64], dtype=np.uint64))[0]
        assert check[i] == wordhash._mix(np.array([second], dtype=np.uint64))[0]
    assert (wordhash.windows(np.tile(words, (600, 1)), width)[: 91 - width] == key).all()  # worked on in pieces


def test_sets_that_share_a_digest(spark, monkeypatch):
    """With a digest of two bits most sets share one; the other half tells them apart."""
    rows = [(i, " ".join(f"w{j}" for j in range(30 * (i // 2), 30 * (i // 2) + 20))) for i in range(24)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    whole = jaccard.digests
    monkeypatch.setattr(jaccard, "digests", lambda v: (whole(v)[0] & 3, whole(v)[1]))
    assert {r.doc_id: r.component_id for r in jaccard.jaccard_components(df, 3, 85).collect()} == {i: i // 2 * 2 for i in range(24)}


@pytest.mark.parametrize("n", [1, 40, 500])
def test_balanced_takes_the_cheapest_with_room(n):
    """Every step against a scan of all sequences."""
    sizes = sorted(np.random.default_rng(n).integers(1, 2048, size=n).tolist(), reverse=True)
    total = -(-sum(sizes) // 2048)
    cost, used, left = [0.0] * total, [0] * total, dict(enumerate(sizes))
    for k, a, b, s, at in packing.balanced(sizes, 2048):
        fits = [i for i in range(total) if 2048 - used[i] >= left[k]] or [i for i in range(total) if used[i] < 2048]
        assert s == min(fits, key=lambda i: (cost[i], i)) and at == used[s] and b - a == min(left[k], 2048 - used[s])
        used[s] += b - a
        cost[s] += packing.piece_cost(b - a)
        left[k] -= b - a
    assert not any(left.values()) and sum(used) == sum(sizes)


def test_other_tokenizer_files_go_through_the_tokenizer(tmp_path):
    import json

    from tokenizers import Tokenizer

    file = json.loads(open(queries.tokenizer_path(), encoding="utf-8").read())
    assert packing.is_plain(file)
    for change in ({"normalizer": {"type": "Lowercase"}}, {"pre_tokenizer": {**file["pre_tokenizer"], "add_prefix_space": True}}, {"model": {**file["model"], "merges": file["model"]["merges"][::-1]}}):
        assert not packing.is_plain({**file, **change})
    path = tmp_path / "lower.json"
    path.write_text(json.dumps({**file, "normalizer": {"type": "Lowercase"}}), encoding="utf-8")
    text = "Some UPPER words, 12 of them"
    assert packing.token_encoder(str(path))(text) == Tokenizer.from_file(str(path)).encode(text, add_special_tokens=False).ids != packing.token_encoder(queries.tokenizer_path())(text)


def brute_nearest(rows, k=5):
    good = {}
    for i, v in rows:
        if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v) and any(v):
            good.setdefault(i, []).append(np.array(v, dtype=float))
    out = {}
    for q in (i for i in good if i % 50 == 0):
        s = sorted((-max(ann.cosine(a, b[None])[0] for a in good[q] for b in bs), i) for i, bs in ((i, np.array(x)) for i, x in good.items()) if i != q for bs in [bs])
        out[q] = [i for _, i in s[:k]]
    return out


def test_neighbours_small_table_is_exact(spark, small):
    e = spark.read.parquet(f"{small}/embeddings.parquet")
    got = {}
    for r in sorted(ann.nearest(e, F.col("vec_id") % 50 == 0).collect(), key=lambda r: (r.query_id, r["rank"])):
        got.setdefault(r.query_id, []).append(r.vec_id)
    x = {r.vec_id: np.array(r.embedding, dtype=float) for r in e.collect()}
    ids = np.array(sorted(x))
    m = np.stack([x[i] for i in ids])
    for q in ids[ids % 50 == 0]:
        s = ann.cosine(x[q], m)
        order = [int(ids[i]) for i in np.lexsort((ids, -s)) if ids[i] != q][:5]
        assert got[q] == order


def test_neighbours_recall_on_curves(spark):
    e = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")
    rows = e.collect()
    ids, m = np.array([r.vec_id for r in rows]), np.array([r.embedding for r in rows], dtype=float)
    got = {}
    for r in ann.nearest(e, F.col("vec_id") % 50 == 0).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    hits = [len(got[q] & {int(ids[i]) for i in np.lexsort((ids, -ann.cosine(m[ids == q][0], m))) if ids[i] != q} & set(_top(ids, m, q))) / 5 for q in ids[ids % 50 == 0]]
    assert np.mean(hits) >= 0.9


def _top(ids, m, q):
    s = ann.cosine(m[ids == q][0], m)
    return [int(ids[i]) for i in np.lexsort((ids, -s)) if ids[i] != q][:5]


def test_neighbours_edges(spark):
    rows = [(0, [1.0, 0.0]), (1, [2.0, 0.0]), (2, [1.0, 1.0]), (3, None), (4, [0.0, 0.0]), (5, [float("nan"), 1.0]), (6, [None, 1.0]), (7, [1.0]), (None, [1.0, 0.0]), (9, [1.0, 0.0]), (9, [1.0, 0.0]), (50, [0.0, 3.0]), (100, [float("inf"), 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("id", F.lit(0)).withColumn("v", F.lit(0)).withColumn("score", F.lit(0))
    got = {}
    for r in sorted(ann.nearest(df, F.col("vec_id") % 50 == 0).collect(), key=lambda r: (r.query_id, r["rank"])):
        got.setdefault(r.query_id, []).append(r.vec_id)
    assert got == {0: [1, 9, 2, 50], 50: [2, 0, 1, 9]}
    assert ann.nearest(df.limit(0), F.col("vec_id") % 50 == 0).count() == 0


def test_neighbours_with_one_very_common_vector(spark):
    rng = np.random.default_rng(2)
    rows = [(i, ([1.0] * 8 if i % 3 == 0 else rng.normal(size=8).tolist())) for i in range(3000)]
    got = [(r.query_id, r.vec_id) for r in ann.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), F.col("vec_id") == 300).collect()]
    assert len(got) == 5 and all(v % 3 == 0 for _, v in got)


def test_hilbert_keys_are_a_walk():
    cells = np.array([(a, b, c) for a in range(4) for b in range(4) for c in range(4)])
    keys = ann.hilbert_keys(cells, 2)
    walk = cells[np.argsort(keys)]
    assert sorted(keys) == list(range(64)) and (np.abs(np.diff(walk, axis=0)).sum(1) == 1).all()


def brute_mix(rows):
    """Copies of each (id, source, size): targets by filling up, then one draw a row."""
    whole, weight = Counter(), {}
    for _, source, size in rows:
        whole[source] += size
    for i, source in enumerate(sorted(whole, key=lambda s: (s is None, s or ""))):
        weight[source] = (3, 1, 2)[i % 3]
    target, open_, left = {}, set(whole), 1.5 * sum(whole.values())
    while open_:
        level = left / sum(weight[s] for s in open_)
        full = {s for s in open_ if 2 * whole[s] < level * weight[s]}
        if not full:
            target |= {s: level * weight[s] for s in open_}
            break
        target |= {s: 2.0 * whole[s] for s in full}
        left -= sum(target[s] for s in full)
        open_ -= full
    out = []
    for doc, source, _ in rows:
        rate = target[source] / whole[source] if whole[source] else 0.0
        u = int(hashlib.md5(f"mix-1:{'null' if doc is None else doc}".encode()).hexdigest()[:12], 16) / 2**48
        out.append(int(rate) + (u < rate - int(rate)))
    return out


def test_mixing_equals_sql(spark, small):
    assert_same(queries.op7_mixing(spark, small), queries.oracle_sql()["op7_mixing"], small)


@pytest.mark.parametrize("table", ["edge", "clashing", "empty"])
def test_mixing_edges(request, table):
    df = request.getfixturevalue(table)
    rows = mixing.copies(df).collect()
    assert len(rows) == df.count()
    total = sum(r["size"] for r in rows)
    targets = {}
    for r in rows:
        assert r.copies in (0, 1, 2) and r["size"] * r.copies <= 2 * r["size"] and r.target <= 2 * r.source_size
        targets.setdefault((r.source_size, r.target), 0)
    if rows:
        assert sum(t for _, t in targets) == pytest.approx(1.5 * total)
    given = df.select("doc_id", "source", "text").collect()
    assert Counter((r.doc_id, r.copies) for r in rows) == Counter(zip((r.doc_id for r in given), brute_mix([(r.doc_id, r.source, len(words(r.text or ""))) for r in given])))
    mixed = mixing.mix(df)
    assert mixed.columns == df.columns and mixed.count() == sum(r.copies for r in rows)


@pytest.mark.parametrize("law", ["bytes", "key"])
@pytest.mark.parametrize("table", ["docs", "edge", "clashing", "empty"])
def test_sharding(request, table, law):
    df = request.getfixturevalue(table)
    rows, n = sharding.shard(df, law=law).collect(), df.count()
    assert len(rows) == n and {r.law for r in rows} <= {law}
    held = {s: sorted(r.slot for r in rows if r.shard == s) for s in range(8)}
    assert all(v == list(range(len(v))) for v in held.values()) and sum(map(len, held.values())) == n
    texts = Counter((r.doc_id, zlib.crc32((r.text or "").encode()), len((r.text or "").encode()) + 1) for r in df.select("doc_id", "text").collect())
    assert Counter((r.doc_id, r.text_crc32, r["size"]) for r in rows) == texts
    if law == "key":
        assert all(r.grown_shard in (r.shard, 8) for r in rows)
        now, more = ({r.doc_id: r.shard for r in x} for x in (rows, sharding.shard(df, 9, law).collect()))
        assert more == {r.doc_id: r.grown_shard for r in rows} and set(now) == set(more)
    else:
        assert all(r.grown_shard is None for r in rows)
    if (table, law) == ("docs", "bytes"):
        full = [sum(r["size"] for r in rows if r.shard == s) for s in range(8)]
        # No move of a whole text could bring the fullest and the least filled shard closer.
        least = min(sum(r["size"] for r in rows if r.text_crc32 == c) for c in {r.text_crc32 for r in rows if r.shard == full.index(max(full))})
        assert max(full) - min(full) <= least or max(full) - min(full) < 0.02 * sum(full) / 8
        shard_of, of_text = {}, Counter()
        for r in rows:
            of_text[r.text_crc32] += r["size"]
        small = [r for r in rows if 8 * 8 * of_text[r.text_crc32] < sum(full)]
        assert len(small) > 100 and all(shard_of.setdefault(r.text_crc32, r.shard) == r.shard for r in small)  # copies stay together


def test_a_stored_map_is_edited(spark, docs, tmp_path):
    path = f"file://{tmp_path}/map"
    first = {r.doc_id: r.shard for r in sharding.shard(docs, map_path=path).collect()}
    assert sharding.load_map(spark, path)[:2] == (1, 8)
    assert {r.doc_id: r.shard for r in sharding.shard(docs, map_path=path).collect()} == first
    assert sharding.load_map(spark, path)[0] == 1  # nothing changed
    more = docs.unionByName(docs.limit(20).selectExpr("doc_id + 1000000 as doc_id", "concat(text, ' new ', doc_id) as text", *[c for c in docs.columns if c not in ("doc_id", "text")]))
    rows = sharding.shard(more, map_path=path).collect()
    full = [sum(r["size"] for r in rows if r.shard == s) for s in range(8)]
    moved = sum(r["size"] for r in rows if r.doc_id in first and r.shard != first[r.doc_id])
    assert sharding.load_map(spark, path)[0] == 2 and moved < 0.2 * sum(full) and max(full) - min(full) < 0.1 * sum(full) / 8
    grown = sharding.shard(docs, 9, map_path=path).collect()
    assert {r.shard for r in grown} == set(range(9)) and sharding.load_map(spark, path)[:2] == (3, 9)


def test_one_text_on_a_third_of_the_rows(spark):
    rows = [(i, "the same text" if i % 3 == 0 else f"text {i} " * 3) for i in range(3000)]
    got = sharding.shard(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    full = [sum(r["size"] for r in got if r.shard == s) for s in range(8)]
    assert max(full) - min(full) < 0.02 * sum(full) / 8


def test_slot_maps():
    for n in range(1, 12):
        now, grown = sharding.slot_map(n), sharding.slot_map(n + 1)
        assert all(a == b or b == n for a, b in zip(now, grown))
        assert max(Counter(grown).values()) - min(Counter(grown).values()) <= n
    old = {i: i % 4 for i in range(20)}
    new = sharding.edited_map(old, [(i, 10 + 40 * (i < 3)) for i in range(20)] + [(99, 5)], 5)
    held = Counter()
    for k, s in new.items():
        held[s] += 50 if k < 3 else 5 if k == 99 else 10
    assert max(held.values()) - min(held.get(s, 0) for s in range(5)) <= 20
    assert sum(new[k] != old[k] for k in old) < 12


@pytest.mark.parametrize("table", ["docs", "edge", "clashing"])
def test_fingerprints(request, table):
    df = request.getfixturevalue(table)
    rows = df.select("doc_id", "text").collect()
    got = imatch.fingerprint_documents(df).collect()
    order = sorted(((r.doc_id, r.text or "") for r in rows), key=lambda r: (r[0] is not None, r[0] or 0), reverse=True)
    want = Counter()
    for k, (doc, text) in enumerate(order):
        follower = order[(k + 1) % len(order)][1]
        half = len(text) // 2
        want[doc, len(text), hashlib.sha256((text[: len(text) - half] + follower[:half]).encode()).hexdigest()] += 1
    assert Counter((r.doc_id, r.n_chars, r.edited_sha256) for r in got) == want
    by_id = {r.doc_id: r for r in got}
    same = {}
    for doc, text in order:
        assert same.setdefault(text, by_id[doc].fingerprint) == by_id[doc].fingerprint
    assert all(0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1 for r in got)
    if table == "docs":
        assert np.mean([r.near_edited for r in got]) > 10 * np.mean([r.near_next for r in got])


def brute_print(terms_of, common, cell_of):
    """The codes of a text's sorted terms in every subset; one of all terms if it has none in a subset."""
    cells = {}
    for t in sorted(terms_of):
        if t not in common:
            cells.setdefault(cell_of[t], []).append(t)
    return tuple(tuple(cells.get(i, ())) for i in range(imatch.LEVELS * imatch.EACH)) if cells else ("all", *sorted(terms_of))


def test_fingerprints_and_likeness_by_their_terms(spark, docs):
    """Fingerprints agree exactly where the terms of a subset do, and likeness is the share of such subsets."""
    rows = sorted(((r.doc_id, r.text or "") for r in docs.select("doc_id", "text").collect()), reverse=True)
    split = lambda t: {w for w in re.split("[ \t\n\x0b\x0c\r]+", t.lower()) if w}
    half = lambda t: len(t) // 2
    edited = {i: t[: len(t) - half(t)] + rows[(k + 1) % len(rows)][1][: half(t)] for k, (i, t) in enumerate(rows)}
    df = Counter(w for _, t in rows for w in split(t))
    common = {w for w, n in df.items() if n >= max(2, -(-len(rows) // imatch.COMMONEST))}
    every = sorted({w for _, t in rows for w in split(t)} | {w for t in edited.values() for w in split(t)})
    table = spark.createDataFrame([(w,) for w in every], "t string")
    cell_of = {r.t: r.c for r in table.select("t", imatch.cell_of(F.xxhash64("t")).alias("c")).collect()}
    got = {r.doc_id: r for r in imatch.fingerprint_documents(docs).collect()}
    own = {i: brute_print(split(t), common, cell_of) for i, t in rows}
    other = {i: brute_print(split(t), common, cell_of) for i, t in edited.items()}
    meaning = {}
    for i, _ in rows:
        assert meaning.setdefault(got[i].fingerprint, own[i]) == own[i] and meaning.setdefault(got[i].edited_fingerprint, other[i]) == other[i]
    assert len(set(meaning.values())) == len(meaning)

    def like(a, b):
        if a == b:
            return 1.0
        if "all" in (a[:1] + b[:1]):
            return 0.0
        same = least = 0
        for k in range(imatch.LEVELS):
            x, y = (p[k * imatch.EACH : (k + 1) * imatch.EACH] for p in (a, b))
            n = min(sum(map(bool, x)), sum(map(bool, y)))
            if n <= imatch.EACH * 3 // 4:
                least += n
                same += sum(bool(p) and p == q for p, q in zip(x, y))
        return same / least if least else 0.0

    for k, (i, _) in enumerate(rows):
        assert got[i].near_edited == pytest.approx(like(own[i], other[i])) and got[i].near_next == pytest.approx(like(own[i], own[rows[(k + 1) % len(rows)][0]]))


def test_fingerprints_of_nothing(empty):
    assert imatch.fingerprint_documents(empty).count() == 0


def test_fingerprints_run_no_python(docs):
    plan = imatch.fingerprint_documents(docs)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


def test_quality_learns_held_out_labels(spark):
    folder = "/root/testdata/sf0.01"
    labels = spark.read.parquet(f"{folder}/labels.parquet")
    rows = queries.op1_quality(spark, folder).join(labels, "doc_id").where("held_out").collect()
    assert np.mean([r.predicted == r.quality for r in rows]) >= 0.95
    good = [r.predicted for r in rows if r.quality == 1]
    assert np.mean(good) >= 0.97


def test_quality_edges(spark, edge, clashing, empty):
    labels = spark.createDataFrame([(1, 0), (None, 1), (4, None), (5, 1), (5, 0)], "doc_id long, quality int")
    for df in (edge, clashing):
        rows = quality.score_documents(df, labels, F.lit(True)).collect()
        assert len(rows) == len(EDGE) and {r.score for r in rows} == {1 / 5}
    none = labels.limit(0)
    assert {r.score for r in quality.score_documents(edge, none, F.lit(True)).collect()} == {0.5}
    assert quality.score_documents(empty, labels, F.lit(True)).count() == 0
    assert quality.keep_good(clashing, none).columns == clashing.columns


def test_quality_fits_on_a_bounded_sample(spark):
    folder = "/root/testdata/sf0.01"
    docs, labels = (spark.read.parquet(f"{folder}/{n}.parquet") for n in ("documents", "labels"))
    whole, some = ({r.doc_id for r in quality.keep_good(docs, labels, sample=n).select("doc_id").collect()} for n in (50_000, 200))
    assert len(whole ^ some) < 0.05 * docs.count()
    good = {r.doc_id for r in labels.where("quality = 1").collect()}
    assert len(good & some) >= 0.97 * len(good)


def test_discriminant_equals_the_formula(spark):
    rng = np.random.default_rng(0)
    d = len(quality.STATISTICS)
    x = np.vstack([rng.normal(size=(80, d)), rng.normal(1, 2, size=(60, d))])
    y = [0] * 80 + [1] * 60
    model = quality.fit(spark.createDataFrame([(v.tolist(), c) for v, c in zip(x, y)], "x array<double>, label int"), shrink=0.2, ridge=0.1)
    covs = [np.cov(x[np.array(y) == c].T, bias=True) for c in (0, 1)]
    pooled = (80 * covs[0] + 60 * covs[1]) / 140
    target = 0.9 * pooled + 0.1 * np.diag(np.diag(pooled))
    log = []
    for c, k in ((0, 80), (1, 60)):
        s = 0.8 * covs[c] + 0.2 * target + 1e-9 * np.eye(d)
        m = x[np.array(y) == c].mean(0)
        diff = x - m
        log.append(np.log(k / 140) - 0.5 * np.linalg.slogdet(s)[1] - 0.5 * np.einsum("ni,ij,nj->n", diff, np.linalg.inv(s), diff))
    assert np.allclose(model.score(x), 1 / (1 + np.exp(np.clip(log[0] - log[1], -500, 500))), atol=1e-6)


def test_substring_sql(spark, small):
    assert_same(queries.op3_substring(spark, small), queries.oracle_sql()["op3_substring"], small)


def test_jaccard_sql(spark, small):
    assert_same(queries.op8_jaccard(spark, small), queries.oracle_sql()["op8_jaccard"], small)
