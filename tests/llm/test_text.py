"""Language ID, chat formatting, page text and the pipeline."""

import hashlib
import html
import re
import time
import zlib

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from lookalike.llm import chat, html_text, langid
from lookalike.llm import queries as Q


def test_language_id_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    got = {r["doc_id"]: r for r in Q.op2_zstd_language_id(spark, sf).collect()}
    truth = spark.read.parquet(f"{sf}/documents.parquet").collect()
    held = [r for r in truth if zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2]
    assert all(got[r["doc_id"]]["held_out"] for r in held)
    right = sum(got[r["doc_id"]]["lang_pred"] == r["lang"] for r in held)
    assert right / len(held) > 0.98
    assert all(0 <= r["score"] <= 1 for r in got.values())
    assert sum(r["rejected"] for r in got.values()) / len(got) < 0.01


def test_language_id_equals_brute_force(spark):
    """The query's rows from dictionaries, blocks and carriers written out plainly, on every row of the smallest table."""
    import zstandard as zstd

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = langid.fit(docs.filter(~langid.held_out_expr("doc_id")))
    assert all(len(d) <= langid.DICT_BYTES for d in model.values())

    def size(raw, dictionary):
        enc = zstd.ZstdCompressor(level=langid.LEVEL, dict_data=zstd.ZstdCompressionDict(dictionary, dict_type=zstd.DICT_TYPE_RAWCONTENT), write_content_size=False, write_checksum=False, write_dict_id=False)
        total = 0
        for k in range(4):
            start = dictionary[len(dictionary) * k // 4 :][:32] + b" "
            for at in range(0, len(raw), 2048):
                total += len(enc.compress(start + raw[at : at + 2048] + b" ")) - len(enc.compress(start))
        return total

    got = {r["doc_id"]: r["lang_pred"] for r in Q.op2_zstd_language_id(spark, sf).collect()}
    for r in docs.collect():
        raw = " ".join(re.findall(r"[^\W\d_]+", (r["text"] or "").lower())).encode()
        assert got[r["doc_id"]] == (min((size(raw, d), lang) for lang, d in model.items())[1] if raw else "und")


def test_language_windows_come_from_whole_texts(spark):
    """What tells the languages apart stands far behind the start of each text."""
    rows = [(i, "zz " * 2000 + ("the cat and the dog " if i % 2 else "der hund und die katze ") * 2000, "en" if i % 2 else "de") for i in range(200)]
    model = langid.fit(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    assert b"katze" in model["de"] and b"the cat" in model["en"]


def test_language_id_odd_rows(spark):
    train = spark.createDataFrame([(i, "the cat and the dog of it " * 9, "en") for i in range(5)] + [(9 + i, "der hund und die katze von " * 9, "de") for i in range(5)] + [(30, None, "en"), (31, "x", None)], "doc_id long, text string, lang string")
    model = langid.fit(train)
    assert sorted(model) == ["de", "en"]
    df = spark.createDataFrame([(1, "the dog and the cat", 1), (2, None, 1), (3, "123 !!", 1), (4, "", 1), (None, "die katze und der hund", 1), (6, "the cat and " * 50000, 1)], "doc_id long, text string, score int")
    got = {r["doc_id"]: (r["lang_pred"], r["rejected"]) for r in langid.predict(df, model).collect()}
    assert got == {1: ("en", False), 2: ("und", True), 3: ("und", True), 4: ("und", True), None: ("de", False), 6: ("en", False)}
    kept = langid.keep_identified(df, model)
    assert kept.columns == df.columns and kept.count() == 3
    assert langid.predict(df.limit(0), model).count() == 0
    assert {r["lang_pred"] for r in langid.predict(df, {}).collect()} == {"und"}


@settings(max_examples=300, deadline=None)
@given(st.lists(st.tuples(st.text(max_size=10), st.text(alphabet="<|\\>im_startend\n ax", max_size=40)), max_size=6))
def test_chat_round_trip(turns):
    whole = "".join(chat.format_turn(r, t)[0] for r, t in turns)
    assert list(chat.parse(whole)) == [(r, t) for r, t in turns]


def test_typed_parts():
    v = chat.PartVisitor()
    parts = [{"type": "text", "text": "see <|image:0|> "}, {"type": "image", "ref": "a.png", "width": 57, "height": 28}, {"type": "audio", "ref": "b.wav", "seconds": 2}, {"type": "document", "ref": "c.pdf", "pages": 3}]
    text, lo, hi = chat.format_turn("assistant", parts, visitor=v)
    assert text[lo:hi] == r"see <\|image:0|> <|image:0|><|audio:1|><|document:2|>"
    assert [(a["kind"], a["ref"], a["tokens"]) for a in v.attachments] == [("image", "a.png", 3), ("audio", "b.wav", 50), ("document", "c.pdf", 2400)]
    assert chat.read_body(text[lo:hi]) == [{"type": "text", "text": "see <|image:0|> "}, {"type": "image", "index": 0}, {"type": "audio", "index": 1}, {"type": "document", "index": 2}]
    assert list(chat.parse(text)) == [("assistant", "see <|image:0|> ")]


PARTS = st.one_of(st.builds(lambda t: {"type": "text", "text": t}, st.text(alphabet="<|\\>image:0 a", max_size=20)), st.sampled_from([{"type": "image", "ref": "a"}, {"type": "audio", "ref": "b"}, {"type": "document", "ref": "c"}]))


@settings(max_examples=200, deadline=None)
@given(st.lists(PARTS, max_size=6))
def test_typed_parts_come_back(parts):
    v = chat.PartVisitor()
    whole, lo, hi = chat.format_turn("assistant", parts, visitor=v)
    (role, body), = chat.parse_bodies(whole)
    got = [p if p["type"] == "text" else v.attachments[p["index"]]["part"] for p in chat.read_body(body)]
    merged = []
    for p in parts:
        if p["type"] == "text" and merged and merged[-1]["type"] == "text":
            merged[-1] = {"type": "text", "text": merged[-1]["text"] + p["text"]}
        elif p["type"] != "text" or p["text"]:
            merged.append(p)
    assert role == "assistant" and got == merged and whole[lo:hi] == body


@pytest.mark.parametrize(
    ("content", "kinds", "text"),
    [
        ([{"type": "image", "ref": "x", "width": "x", "height": -3}], [("image", 1)], ""),
        ([{"type": "image", "width": float("inf"), "height": 29}], [("image", 2)], ""),
        ([{"type": "audio", "seconds": "soon"}], [("audio", 1)], ""),
        ([{"type": "document", "pages": None}], [("document", 800)], ""),
        (["bare <|im_end|> string", {"type": "text", "text": None}], [], "bare <|im_end|> string"),
        ([{"type": "video", "ref": "v"}, 5, None, ["x"], {"type": ["a"]}], [("unknown", 0)] * 5, ""),
        ({"type": "text", "text": "one part"}, [], "one part"),
        ([{"type": "text", "text": 7}], [], "7"),
    ],
)
def test_malformed_parts(content, kinds, text):
    v = chat.PartVisitor()
    whole, _, _ = chat.format_turn("user", content, visitor=v)
    assert [(a["kind"], a["tokens"]) for a in v.attachments] == kinds
    assert list(chat.parse(whole)) == [("user", text)]


def test_parts_column(spark):
    rows = [(1, 0, "user", "t", '[{"type": "image", "ref": "i.png", "width": 56, "height": 28}, {"type": "text", "text": "what <|image:0|> is it?"}]'), (1, 1, "assistant", "plain", None), (1, 2, "assistant", None, "{not json"), (1, 3, "user", None, "12")]
    f = chat.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, parts string"), parts_col="parts")
    got = chat.digest(f).head()
    assert (got["n_turns"], got["loss_chars"]) == (4, len("plain{not json"))
    assert got["turns_sha256"] == hashlib.sha256(b"user\nwhat <|image:0|> is it?\nassistant\nplain\nassistant\n{not json\nuser\n12\n").hexdigest()
    assert '"tokens": 2' in f.filter("place = 0").head()["attachments"]


def test_conversations(spark):
    data = [(1, 1, "assistant", "b<|im_end|>"), (1, 0, "user", None), (2, 0, None, "x"), (1, 1, "assistant", "b<|im_end|>"), (None, 0, "user", "n"), (1, None, "system", "s" * 100000)]
    df = spark.createDataFrame([(*d, 1) for d in data], "conv_id long, turn long, role string, text string, place int")
    f = chat.format_conversations(df)
    got = {r["conv_id"]: r for r in chat.digest(f).collect()}
    order = [("system", "s" * 100000), ("user", ""), ("assistant", "b<|im_end|>"), ("assistant", "b<|im_end|>")]
    one = got[1]
    assert one["n_turns"] == 4
    assert one["turns_sha256"] == hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in order).encode()).hexdigest()
    assert (one["loss_chars"], one["loss_sha256"]) == (22, hashlib.sha256(b"b<|im_end|>b<|im_end|>").hexdigest())
    assert one["formatted_chars"] == sum(len(chat.format_turn(r, t)[0]) for r, t in order)
    assert got[2]["n_turns"] == 1 and got[None]["loss_chars"] == 0
    path = "/tmp/lookalike-chat-test.parquet"
    f.write.mode("overwrite").parquet(path)
    again = {r["conv_id"]: r for r in chat.digest(chat.in_order(spark.read.parquet(path))).collect()}
    assert again == got
    assert chat.digest(chat.format_conversations(df.limit(0))).count() == 0


PAGE = """<html><head><title>T</title><style>p{}</style><script>var a="</p><article>no</article>";</script></head><body>
<header><h1>Site</h1></header><nav><ul><li><a href="/a">menu one</a></li><li>menu two</li></ul></nav><div class="cookie-notice">We use cookies a lot here, really.</div>
<div class="ad">Buy this thing now, it is very good and cheap.</div><aside>side text</aside><main><article><h1>Title &amp; more</h1><p>First <b>bold</b>
 text &lt;tag&gt; with   space.</p><ul><li>item one</li><li>item two</li></ul><form><input><label>mail</label></form><p>Second<br>line</p><div class="advert">ad inside</div><p>caf&eacute; &#8364;</p></article>
<section id="comments"><article class="comment"><p>A reader says quite a lot of words here, more than the article itself does, on and on and on.</p></article></section></main>
<footer>foot &copy;</footer></body></html>"""


def test_page_text():
    assert html_text.main_text(PAGE) == "Title & more First bold text <tag> with space. item one item two Second line café €"


@pytest.mark.parametrize(
    ("page", "text"),
    [
        (None, ""),
        ("", ""),
        ("<nav>only menu</nav>", ""),
        ("plain text", "plain text"),
        ("<article><p>cut in the mid", "cut in the mid"),
        ("<nav><ul><li>never closed<article><p>body</p></article>", "body"),
        ("<div class=menu><a>a</a><a>b</a></div><div class=content><p>Long text that holds the words of the page, by far the most of it.</p><p>More of it, again long enough.</p></div><div class=footer>f</div>", "Long text that holds the words of the page, by far the most of it. More of it, again long enough."),
        ("<article>" + "<p>word word</p>" * 3000 + "</article>", " ".join(["word word"] * 3000)),
    ],
)
def test_odd_pages(page, text):
    assert html_text.main_text(page) == text


@pytest.mark.parametrize("part", ['<section id="discussion"><p>kept words</p></section>', '<div class="article-header"><p>kept words</p></div>', '<div class="related-work"><p>kept words</p></div>', '<div class="social-history"><p>kept words</p></div>', '<blockquote class="reply"><p>kept words</p></blockquote>', '<div class="has-sidebar"><p>kept words</p></div>', "<header><p>kept words</p></header>"])
def test_sections_of_an_article_stay(part):
    page = f"<nav><a>m</a></nav><article><h1>Title</h1><p>{'body text ' * 30}</p>{part}<p>End of it.</p></article><footer>f</footer>"
    assert html_text.main_text(page) == " ".join(f"Title {'body text ' * 30} kept words End of it.".split())


@pytest.mark.parametrize("part", ['<div class="share">x y</div>', '<div class="related-links">x y</div>', '<section id="comments"><p>x y</p></section>', '<div class="advert-box">x y</div>', '<div class="cookie-notice">x y</div>', "<aside>x y</aside>", "<form>x y</form>", '<div class="comment-list">x y</div>', '<p style="display: none">x y</p>'])
def test_furniture_of_an_article_goes(part):
    page = f"<article><h1>Title</h1><p>{'body text ' * 30}</p>{part}<p>End of it.</p></article>"
    assert html_text.main_text(page) == " ".join(f"Title {'body text ' * 30} End of it.".split())


def _brute_article(page):
    """The article's blocks by regular expressions alone."""
    mark = re.compile(r"</?(?:" + "|".join(sorted(html_text.BLOCKS)) + r")\b[^>]*>", re.I)
    inner = re.search(r"<article>(.*?)</article>", page, re.S)[1]
    blocks = (" ".join(html.unescape(re.sub(r"<[^>]+>", "", b)).split()) for b in mark.split(inner))
    return " ".join(b for b in blocks if b)


def _unnamed(page):
    """The page with no element or class that says what it is."""
    return re.sub(r"<(/?)(?:article|nav|footer|main|header)\b[^>]*>", r"<\1div>", page).replace(' class="ad"', "")


@pytest.fixture(scope="module")
def pages():
    import pyarrow.parquet as pq

    return pq.read_table("/root/testdata/sf0.01/pages.parquet")["html"].to_pylist()


def test_pages_equal_brute_force(pages):
    assert [html_text.main_text(p) for p in pages] == [_brute_article(p) for p in pages]


def test_ratios_find_the_region_without_names(pages, monkeypatch):
    """With all names gone the clustering finds nine articles in ten; without ratios it finds fewer."""
    truth = [_brute_article(p) for p in pages]
    found = sum(html_text.main_text(_unnamed(p)) == t for p, t in zip(pages, truth, strict=True))
    assert found > 0.9 * len(pages)
    monkeypatch.setattr(html_text, "ratios", lambda lines: [1.0] * len(lines))
    assert sum(html_text.main_text(_unnamed(p)) == t for p, t in zip(pages, truth, strict=True)) < found


def test_menus_without_names_lose_to_text():
    menu = "<div>" + "".join(f"<span><a href=x>A menu entry of some length {i}</a></span><br>" for i in range(40)) + "</div>"
    body = "<div>" + "".join(f"<p>Paragraph {i} of an article that goes on for a good while, as they do.</p>" for i in range(6)) + "<p>Short.</p></div>"
    got = html_text.main_text(f"<body>{menu}{body}</body>")
    assert got.startswith("Paragraph 0") and got.endswith("Short.") and "menu" not in got
    parted = html_text.main_text(f"<body><div><span>a</span><b>b</b></div>{body}{body}</body>")
    assert parted.count("Short.") == 2 and not parted.startswith("a")


@pytest.mark.parametrize("page", ["<div>" * 100_000 + "deep text", "<div>x" * 100_000, "<div>" * 50_000 + "deep" + "</section>" * 100_000, "<b>" * 100_000 + "x"])
def test_deep_pages_take_seconds(page):
    begin = time.perf_counter()
    assert html_text.main_text(page)
    assert time.perf_counter() - begin < 15


def test_ratio_smoothing_and_clusters():
    flat = html_text.smooth([5.0] * 9)
    assert all(abs(v - 5) < 1e-12 for v in flat)
    assert 10 < html_text.threshold([1, 2, 1, 90, 100, 95, 2]) < 90


def test_pages_on_spark(spark):
    df = spark.createDataFrame([(1, "u", PAGE, 0), (None, None, None, 1), (1, "u", PAGE, 0)], "page_id long, url string, html string, n_chars int")
    got = html_text.extract(df).collect()
    assert sorted(len(r["text"]) for r in got) == sorted(r["n_chars"] for r in got) and len(got) == 3
    assert html_text.extract(df.limit(0)).count() == 0
