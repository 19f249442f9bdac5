import math
import random
import re
import time

import pytest
from pyspark.sql import functions as F

from semjoin.llm import htmltext

SF = "/root/testdata/sf0.01"
LONG = "words of the article go on and on for a while here"


@pytest.mark.parametrize(
    "markup",
    [
        '<p title="a hidden gem">{}</p>', '<p data-hidden="false">{}</p>', '<p data-class="nav">{}</p>', "<p title='class=\"nav\"'>{}</p>", '<p><a href="/x?id=related">{}</a></p>',
        '<p><svg class="i"/>{}</p>', '<p><svg><path d="M0"/></svg>{}</p>', "<p><math/>{}</p>", "<p><a href=/a/>{}</a></p>", "<p lang=it's>{}</p>", "<p class=text>{}", '<p aria-hidden="false">{}</p>',
    ],
)
def test_ordinary_markup_loses_nothing(markup):
    page = f"<body><nav><a href=/>Home</a></nav><div><h1>Head</h1><p>{LONG}</p>{markup.format('this part')}<p>{LONG} again</p></div></body>"
    assert htmltext.main_text(page) == f"Head {LONG} this part {LONG} again"


@pytest.mark.parametrize("markup", ["<p hidden>{}</p>", "<p HIDDEN=''>{}</p>", '<p style="color:red; display : none">{}</p>', "<p aria-hidden=true>{}</p>", "<div class='x nav-bar'>{}</div>", "<div id=sidebar>{}</div>", "<script src=x />{}</script>"])
def test_hidden_parts_go(markup):
    page = f"<body><div><h1>Head</h1><p>{LONG}</p>{markup.format('this part')}<p>{LONG} again</p></div></body>"
    assert htmltext.main_text(page) == f"Head {LONG} {LONG} again"


def test_density_decides_without_marked_articles(spark):
    """With div for article the same text, by density alone; without names of frames too."""
    for r in spark.read.parquet(f"{SF}/pages.parquet").collect():
        want = htmltext.main_text(r["html"])
        plain = re.sub(r"<(/?)(?:article|main)\b", r"<\1div", r["html"])
        assert want and htmltext.main_text(plain) == want == htmltext.main_text(re.sub(r' (class|id|role)="[^"]*"', "", plain))


def slow_density(node, whole):
    """Characters, tags, density and density sum of a node by their definitions, each from the whole subtree."""
    def walk(x, inside=False):
        for y in x.items:
            if isinstance(y, str):
                yield "text", len("".join(y.split())), inside
            else:
                link = inside or y.name == "a"
                yield ("a" if y.name == "a" else "inline" if y.name in htmltext.INLINE else "block"), 0, inside
                yield from walk(y, link)

    def counts(x):
        got = list(walk(x, x.name == "a"))
        chars, link_chars = sum(n for k, n, _ in got if k == "text"), sum(n for k, n, i in got if k == "text" and i)
        return chars, sum(k in ("a", "block") for k, _, _ in got), link_chars, sum(k == "a" or (k == "block" and i) for k, _, i in got)

    c, t, lc, lt = counts(node)
    rc, _, rl, _ = counts(whole)
    if not c:
        return 0.0
    base = c / max(1, c - lc) * lc + rl / max(1, rc) * c + math.e
    return c / max(1, t) * math.log(c / max(1, lc) * (max(1, t) / max(1, lt))) / math.log(math.log(base)) if math.log(base) > 1 else c / max(1, t)


def blocks_below(node):
    for x in node.items:
        if not isinstance(x, str):
            yield from [x] if x.name not in htmltext.INLINE else blocks_below(x)


def test_densities_equal_brute_force_on_random_trees():
    rng = random.Random(3)

    def page(depth):
        parts = []
        for _ in range(rng.randint(1, 4)):
            name = rng.choice(["div", "p", "a", "b", "section", "span", "li"])
            parts.append(rng.choice(["", "some text ", "x", "many more words of text to read here "]) + (f"<{name}>{page(depth - 1)}</{name}>" if depth else "leaf"))
        return "".join(parts)

    for _ in range(60):
        root = htmltext.parse(f"<body>{page(4)}</body>")
        for node in htmltext.measure(root):
            assert node.density == pytest.approx(slow_density(node, root))
            assert node.sum == pytest.approx(sum(x.density for x in blocks_below(node)))


def test_deep_and_long_pages_take_linear_time():
    began = time.time()
    for name in ("div class=ad", "b", "div", "span"):
        short = name.split()[0]
        page = f"<{name}>" * 8000 + "text" + f"</{short}>" * 8000
        htmltext.main_text(page)
        htmltext.main_text(f"<{name}>" * 8000 + "</i>" * 8000 + "<p>text" * 2000)
    assert htmltext.main_text("<body><div>" + "<p>word</p>" * 100_000 + "</div><div>z</div></body>") == " ".join(["word"] * 100_000)
    assert time.time() - began < 30


def test_tables(spark):
    none = spark.createDataFrame([], "page_id long, url string, html string")
    assert htmltext.extract(none).collect() == []
    rows = [(1, "u", "<p>x"), (1, "u", "<p>x"), (None, None, ""), (2, "u", None)]
    odd = spark.createDataFrame([(*r, "clash", 7) for r in rows], "page_id long, url string, html string, text string, n_chars int")
    got = sorted(map(str, (tuple(r) for r in htmltext.extract(odd).select(F.col("page_id"), "url", "text", "n_chars").collect())))
    assert got == sorted(map(str, [(1, "u", "x", 1), (1, "u", "x", 1), (None, None, "", 0), (2, "u", "", 0)]))
