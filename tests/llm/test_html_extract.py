import numpy as np
import pytest

from tupleshare.llm import html_extract
from tupleshare.llm.html_extract import best_region, extract, learn, learnt_weights, main_text
from tupleshare.llm.html_labels import LABELLED


def test_weights_have_their_signs():
    tags, words = learnt_weights()
    assert all(w < 0 for w in tags.values()) and words["text"] > words["link"] > 0


@pytest.mark.parametrize("k", range(len(LABELLED)))
def test_labelled_pages_held_out(k, monkeypatch):
    """The content of each page is found with weights from the others."""
    weights = learn(LABELLED[:k] + LABELLED[k + 1 :])
    monkeypatch.setattr(html_extract, "learnt_weights", lambda: weights)
    before, content, after = LABELLED[k]
    assert main_text(before + content + after) == main_text(f"<article>{content}</article>")


def test_region_against_all_regions():
    rng = np.random.default_rng(6)
    for n in [*range(12), *[30] * 50]:
        gains = rng.integers(-4, 5, n).tolist()
        sums = {(i, j): sum(gains[i:j]) for i in range(n) for j in range(i + 1, n + 1)}
        top = max([0, *sums.values()])
        a, b = best_region(gains)
        assert sum(gains[a:b]) == top and (a, b) == (min((ij for ij, v in sums.items() if v == top), key=lambda ij: (ij[1], -ij[0])) if top else (0, 0))


def test_inside_of_the_article():
    page = (
        "<nav><a>Menu</a></nav><article><header><h1>Big &amp; small</h1></header><p>one two three four\n  five<br>six seven"
        "<script>var t='</p>';</script><div class='ad'>Buy this</div><p>eight &eacute; nine &#x41; ten, <i>in</i>line words go on"
        "<form>Name <input></form><aside>Not this</aside><ul><li>first item<li>second item</ul></article><footer>&copy; me</footer>"
    )
    assert main_text(page) == "Big & small\n\none two three four five six seven\n\neight é nine A ten, inline words go on\n\nfirst item\n\nsecond item"


def test_edges(spark):
    rows = [(1, "u", None), (2, None, ""), (3, "v", "<p></p><!-- x -->"), (4, "w", "plain words"), (4, "w", "plain words"), (None, "z", "<p>a</p>" * 20000), (5, "", "<p>cut &am"), (6, "", "<p class=\"x>broken 'quote")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "'c' AS text", "1 AS id", "2 AS n_chars")
    got = [(r.page_id, r.url, r.text, r.n_chars) for r in extract(df).collect()]
    assert [g[2] for g in got[:5]] == ["", "", "", "plain words", "plain words"]
    assert got[5][2] == "\n\n".join("a" * 20000) and got[5][3] == 59998
    assert got[6][2] == "cut &am" and got[7][2] == "broken 'quote"
    assert extract(df.limit(0)).count() == 0


def test_adverts_and_marks_inside():
    links = "".join(f"<a href='/{k}'>Buy {k}</a>" for k in range(8))
    page = f"<nav>Menu</nav><article><p>First short one.</p><div class='ad'><ul>{links}</ul></div><p>Second paragraph of the text.</p><ul>{links}</ul><p>Last.</p></article><footer>x</footer>"
    assert main_text(page) == "First short one.\n\nSecond paragraph of the text.\n\n" + "".join(f"Buy {k}" for k in range(8)) + "\n\nLast."
    assert main_text("<p>long<wbr>word and pic<img src=x>ture</p>") == "longword and picture"
    assert main_text('<p class="x>one two</p><p class="y">three</p>') == "one two\n\nthree"
    assert main_text('<p title="a > b">one <a title="x <b> y">two</a> 3 < 4</p>') == "one two 3 < 4"
    assert main_text("<div class='has-sidebar'><button>one two three</div><p>four five") == "one two three\n\nfour five"
    assert main_text("<p>one two<script>never closed <p>three") == "one two"
