import html
import re
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from roadweave.llm import labeller
from roadweave.llm.blocks import blocks
from roadweave.llm.pagemaker import PageMaker


def texts(page):
    return [b.text for b in blocks(page)]


def test_blocks_of_broken_and_odd_html():
    assert texts("<p>a<p>b <b>c</b>\n d<br>e<div>f</div>") == ["a", "b c d e", "f"]
    assert texts("<p><b>one<br><p>two</p>three") == ["one", "two", "three"]
    assert texts("<ul><li>a<li>b<ul><li>c</ul></ul>") == ["a", "b", "c"]
    assert texts("<script>var t='</p>';</script><style>x</style>t &amp; &lt;b&gt; &#233;&nbsp;z") == ["t & <b> é z"]
    assert texts("<!-- <p>no</p> --><p title='>'>yes</p><!-- open") == ["yes"]
    assert texts("a < b <3 <") == ["a < b <3 <"]
    assert texts("<head><title>no</title></head><body>yes") == ["yes"]
    assert texts("<script>never closed <p>x") == [] and texts("") == [] and texts("<") == ["<"]
    assert texts("<table><tr><td>1<td>2<tr><td>3</table>") == ["1", "2", "3"]


def test_paths_and_links():
    first, second = blocks('<div class="Side bar"><a href=x>go there</a></div><article id=main><p>t</p></article>')
    assert first.path == ("div",) and first.words == ("side", "bar") and first.linked > 0.9
    assert second.path == ("article", "p") and second.words == ("main",) and second.linked == 0


def test_links_and_open_quotes():
    anchor, link = blocks("<div><a name=x>not a link, though never closed</div><div><a href=y><b><i><u><s>deep</s></u></i></b></a></div>")
    assert anchor.linked == 0 and link.linked == 1
    assert texts("<p title='open>one</p><p>two") == ["one", "two"]
    assert texts("<a b <i c") == ["<a b <i c"] and texts("<![CDATA[x <p>y") == ["y"] and texts("<![CDATA[a<b]]>c") == ["a<bc"]


@pytest.mark.parametrize(
    "page",
    ["<div>x" * 200_000, "<a b " * 200_000, "<a href=\"" * 100_001 + ">", "<a \"'" * 150_000 + "\">'", "</i>" * 250_000, "<span>" * 80_000 + "<div>y</span>" * 40_000, "<![CDATA[" * 110_000, "<!-- " * 200_000, "<script " * 125_000, "<p>" * 300_000 + "z", "<div class='a b'><p>t" * 50_000, "&" * 1_000_000],
    ids=["divs", "open tags", "quotes", "both quotes", "ends", "spans", "cdata", "comments", "scripts", "paragraphs", "nested", "references"],
)
def test_a_megabyte_of_odd_html_takes_seconds(page):
    began = time.perf_counter()
    own = blocks(page)
    labeller.vectors(own)
    assert time.perf_counter() - began < 10


def test_gradients_are_those_of_the_loss():
    rng = np.random.default_rng(0)
    model = labeller.Labeller(3)
    for owner in (model, model.ahead, model.back):
        for name in ("v", "d") if owner is model else owner.names:
            setattr(owner, name, getattr(owner, name).astype(np.float64))
    pages = [rng.normal(size=(n, labeller.TAG_DIM + labeller.WORD_DIM + labeller.NUMBERS)) for n in (4, 2)]
    x, mask = labeller.padded(pages)
    x, mask = x.astype(np.float64), mask.astype(np.float64)
    y = (rng.random(mask.shape) < 0.5) * mask

    def loss():
        p = model._forward(x, mask)[0]
        return float((-(y * np.log(p) + (1 - y) * np.log(1 - p)) * mask).sum() / mask.sum())

    for (owner, name), g in model._gradients(x, mask, y).items():
        value = getattr(owner, name)
        for _ in range(3):
            at = tuple(rng.integers(0, n) for n in value.shape)
            was = value[at]
            value[at] = was + 1e-4
            up = loss()
            value[at] = was - 1e-4
            down = loss()
            value[at] = was
            assert abs((up - down) / 2e-4 - g[at]) < 2e-3 * max(1, abs(g[at])), name


def test_padding_changes_nothing():
    model = labeller.trained()
    pages = [labeller.vectors(blocks(PageMaker(s).page()[0])) for s in range(5)]
    together = model.label(pages)
    for page, p in zip(pages, together):
        assert np.allclose(model.label([page])[0], p, atol=1e-4)


def test_accuracy_on_unseen_made_pages():
    model, maker, right, n = labeller.trained(), PageMaker(12345), 0, 0
    for _ in range(200):
        page, known = maker.page()
        own = blocks(page)
        if not own:
            continue
        y = labeller.labelled(own, known) > 0.5
        right += ((model.label([labeller.vectors(own)])[0] > 0.5) == y).sum()
        n += len(y)
    assert right >= 0.975 * n


def test_whole_pages_table(spark):
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    got = {r["page_id"]: r for r in labeller.extract(pages).collect()}
    wrong = 0
    for r in pages.collect():
        article = re.search("<article>(.*)</article>", r["html"], re.S)[1]
        parts = [" ".join(html.unescape(re.sub("<[^>]+>", " ", x)).split()) for x in re.split("</?(?:p|h1)>", article)]
        own = got[r["page_id"]]
        wrong += own["text"] != "\n".join(p for p in parts if p)
        assert own["n_chars"] == len(own["text"]) and own["url"] == r["url"]
    assert wrong <= 0.01 * len(got)


@pytest.mark.parametrize("extra", [True, False])
def test_odd_rows(spark, extra):
    rows = [(1, "u", None), (2, None, ""), (3, "u", "<p>"), (3, "u", "<p>"), (None, "u", "<article><p>" + "word " * 50_000 + "</article>")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    if extra:
        pages = pages.withColumn("text", F.lit(1)).withColumn("n_chars", F.lit("x"))
    got = labeller.extract(pages).collect()
    assert len(got) == 5 and {r["text"] for r in got if r["page_id"] is not None} == {""}
    assert labeller.extract(pages.limit(0)).count() == 0
