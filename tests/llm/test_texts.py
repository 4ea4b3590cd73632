import hashlib
import math
import random
import statistics

import pyarrow as pa
import pytest

from vecpath.llm import bpe, html
from vecpath.llm.queries import tokenizer_path

ODD = ["", "a", " ", "  \n ", "hello<|endoftext|> world <|endoftext|><|endoftext|>", "x" * 5000, "  lead", "tail  ",
       "it's 12 34éü  　x", "a\r\nb\tc", "\n\n\nA", "!!! ??? ***  ok" * 200, None, "é à ü " * 300]


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(tokenizer_path())


def test_codec_agrees_with_the_library(library):
    rng = random.Random(5)
    parts = ["the ", "word", "  ", "\n", "'ll", "é", "漢字", "123", "?!", "  ", "<|endoftext|>", "\t", "don't ", "A" * 40]
    texts = ODD + ["".join(rng.choices(parts, k=rng.randint(1, 600))) for _ in range(60)]
    texts += texts[-20:]
    tool = bpe.Codec(tokenizer_path())
    for t, (n, ids, decoded) in zip(texts, tool.batch(pa.array(texts))):
        want = library.encode(t or "", add_special_tokens=False).ids
        assert ids == ",".join(map(str, want)) and n == len(want)
        assert decoded.decode() == library.decode(want, skip_special_tokens=False)


def test_codec_reuses_chunks():
    tool = bpe.Codec(tokenizer_path())
    text = " ".join(f"word{i}" for i in range(20000))
    list(tool.batch(pa.array([text])))
    first = tool.encoded
    list(tool.batch(pa.array(["another start " + text])))
    assert tool.encoded - first < 20


def test_encode_decode_frame(spark, library):
    rows = [(i, t, "clash") for i, t in enumerate(ODD)]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_tokens string")
    out = bpe.encode_decode(df, tokenizer_path(), keep_ids=True).collect()
    assert len(out) == len(ODD)
    for r in out:
        want = library.encode(r.text or "", add_special_tokens=False).ids
        assert r.ids == want and r.decoded == (r.text or "")
        assert r.ids_sha256 == hashlib.sha256(",".join(map(str, want)).encode()).hexdigest()
    assert bpe.encode_decode(df.where("false"), tokenizer_path()).count() == 0


def test_tokenizer_that_is_not_byte_level_is_refused():
    with pytest.raises(ValueError):
        bpe.Codec(tokenizer_path("word_bpe_49k.json"))


ARTICLE = "<h1>A title, of sorts</h1><p>First words, with some more of them, and a stop.</p><p>Second <b>bold</b> part &amp; a&nbsp;half;\n\n really.<br>New line.</p>"
TEXT = "A title, of sorts First words, with some more of them, and a stop. Second bold part & a half; really. New line."


@pytest.mark.parametrize(
    "page",
    [
        f"<html><head><title>t</title></head><body><nav><a href=x>Home</a></nav><article>{ARTICLE}</article><footer>c</footer></body></html>",
        f"<body><header><h2>Site</h2></header><div class='ad'>Buy, buy, now!</div><article>{ARTICLE}<div class=comments><p>Nice, I say.</p></div></article>",
        f"<div id='menu'><ul><li><a href=1>One</a><li><a href=2>Two</a></ul></div><div class='story'>{ARTICLE}</div><div class='cookie-notice'>We use cookies, yes.</div>",
        f"<script>var a='<p>no</p>';</script><!-- <p>no</p> --><article><form><input><label>Mail</label></form>{ARTICLE}</article>",
    ],
)
def test_main_text(page):
    assert html.main_text(page) == TEXT


def test_path_ratios_find_the_content_without_marks():
    menu = "".join(f"<li><a href='{i}'>Section {i}</a></li>" for i in range(12))
    body = "".join(f"<p>Sentence number {i}, which goes on for a while, and then it ends.</p>" for i in range(8))
    page = f"<body><ul>{menu}</ul><div><h2>Head</h2>{body}</div><div><span>Imprint</span></div></body>"
    got = html.main_text(page)
    assert got.startswith("Head Sentence number 0") and "Section" not in got and "Imprint" not in got


@pytest.mark.parametrize("outer", ["body", "main"])
def test_article_elements_do_not_discard_text_outside_them(outer):
    parts = [f"Sentence number {i}, which goes on for a while, and then it ends." for i in range(8)]
    body = "".join(f"<p>{x}</p>" for x in parts)
    cards = "".join(f"<article><a href='{i}'>Card {i}</a></article>" for i in range(4))
    for page in (f"<{outer}><div>{body}</div>{cards}</{outer}>", f"<{outer}><article>Note.</article><div>{body}</div></{outer}>"):
        got = html.main_text(page)
        assert " ".join(parts) in got and "Card" not in got


def test_short_paths_of_an_article_stay():
    body = "".join(f"<p>Sentence number {i}, which goes on for a while, and then it ends.</p>" for i in range(8))
    page = f"<article>{body}<div><i>By X</i></div></article><div><span>Imprint</span></div>"
    assert html.main_text(page).endswith("By X") and html.main_text(page.replace("article", "section")).endswith("ends.")


def test_odd_pages():
    for page in ["", None, "<", "<<>>", "<p", "<!-- x", "<div " * 500, "</p></div>", "&bogus; &#0; &#x110000;", "<script>x", "\0<p>\0"]:
        assert isinstance(html.main_text(page), str)
    assert html.main_text("<p>a<p>b") == "a b"


def test_extract_frame(spark):
    rows = [(1, "u", f"<article>{ARTICLE}</article>", "clash"), (2, None, None, None), (2, None, None, None)]
    out = html.extract(spark.createDataFrame(rows, "page_id long, url string, html string, text string")).collect()
    assert sorted((r.page_id, r.text, r.n_chars) for r in out) == [(1, TEXT, len(TEXT)), (2, "", 0), (2, "", 0)]


STORY = "".join(f"<p>Paragraph {i} of the story, with commas, and enough words to count as text.</p>" for i in range(8))


@pytest.mark.parametrize(
    "page",
    [
        f'<article class="post with-share">{STORY}</article>',
        f'<div class="layout has-sidebar">{STORY}</div>',
        f'<div class="post no-comments">{STORY}</div>',
        f'<div class="layout sidebar-left"><main>{STORY}</main><div class="sidebar"><p>Side text, with things in it.</p></div></div>',
        f'<div class="story">{STORY}</div>' + "<article><h3>Teaser</h3><p>Short note.</p></article>" * 3,
        f'<div class="story">{STORY}<div id="comments">{STORY.replace("Paragraph", "Remark") * 3}</div></div>',
    ],
)
def test_hints_do_not_delete_the_story(page):
    got = html.main_text(f"<html><body><nav>a b</nav>{page}</body></html>")
    assert all(f"Paragraph {i} of the story" in got for i in range(8))
    assert "Side text" not in got and "Remark" not in got and "Teaser" not in got


def chosen_by_brute_force(blocks, share=0.25):
    """The same decision written out block by block, from its description."""
    left = [b for b in blocks if not b.boiler]
    if not left:
        return []

    def ratio(path):
        own = [b for b in left if b.path == path]
        chars, marks = sum(len(b.text) for b in own), sum(sum(c in ".,;:!?…、。，！？" for c in b.text) for b in own)
        linked = sum(min(b.linked, len(b.text)) for b in own)
        return chars / len(own) * (1 + marks / len(own)) * (1 - linked / chars) ** 2

    r = [ratio(b.path) for b in left]
    smooth = []
    for i in range(len(r)):
        near = {j: math.exp(-((i - j) ** 2) / 2) for j in range(i - 2, i + 3) if 0 <= j < len(r)}
        smooth.append(sum(r[j] * w for j, w in near.items()) / sum(near.values()))
    both = [math.sqrt(a * b) for a, b in zip(r, smooth)]
    fused = {p: statistics.mean(v for v, b in zip(both, left) if b.path == p) for p in {b.path for b in left}}
    least = min(share * statistics.pstdev(r), max(fused.values()))
    lifted = []
    for b in left:
        inside = [c for c in left if c.region == b.region]
        mean = sum(fused[c.path] * len(c.text) for c in inside) / sum(len(c.text) for c in inside)
        lifted.append(max(fused[b.path], mean) if b.region else fused[b.path])
    keep = [v >= least and v > 0 for v in lifted]
    for i in reversed(range(len(left) - 1)):
        keep[i] = keep[i] or (left[i].tag in html.HEADINGS and keep[i + 1])
    return [b for b, k in zip(left, keep) if k]


def test_content_by_brute_force_on_random_trees():
    rng = random.Random(12)
    words = "rain, river town. bridge stone! market people hill; winter summer bread".split()

    def tree(depth):
        out = []
        for _ in range(rng.randint(1, 4)):
            tag = rng.choice(["div", "p", "ul", "li", "section", "article", "h2", "td"])
            body = tree(depth - 1) if depth and rng.random() < 0.6 else " ".join(rng.choices(words, k=rng.choice([1, 3, 40])))
            body = f"<a href=x>{body}</a>" if rng.random() < 0.1 else body
            out.append(f'<{tag} class="{rng.choice("abc")}">{body}</{tag}>')
        return "".join(out)

    some = 0
    for _ in range(300):
        blocks = html.blocks(tree(3))
        want = chosen_by_brute_force(blocks)
        some += 0 < len(want) < len(blocks)
        assert [b.text for b in html.content(blocks)] == [b.text for b in want]
    assert some > 50
