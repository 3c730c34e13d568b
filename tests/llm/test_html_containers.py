"""Names on containers of a page don't empty it, and a run keeps all its blocks."""

import pytest

from spanweave.llm import html_main

BODY = "<h1>A title</h1><p>" + "first words of the text " * 8 + "</p><p>" + "more words follow here " * 8 + "</p>"
WANT = "\n".join(["A title", ("first words of the text " * 8).strip(), ("more words follow here " * 8).strip()])


@pytest.mark.parametrize("page", [
    '<body class="single no-sidebar">%s</body>', '<body class="sidebar">%s</body>', '<body><div class="post comments-open">%s</div></body>', '<body><article class="has-related">%s</article></body>',
    '<body><div class="widget-post-content">%s</div></body>', '<body><div class="widget"><article>%s</article></div></body>', '<body><div id="widget">%s</div></body>', '<body><form>%s</form></body>',
])
def test_containers_keep_their_text(page):
    assert html_main.main_text(page % BODY, html_main.weights_of({})) == WANT


def test_header_with_title_and_weak_blocks_stay():
    page = "<body><header><h1>A title</h1></header><p>" + "good words here " * 20 + "</p><p class=odd>weak part</p><p>" + "good words again " * 20 + "</p></body>"
    weights = html_main.Weights(0.5, {"is:odd": -3.0}, {})
    assert html_main.main_text(page, weights).split("\n")[::2] == ["A title", "weak part"]


def test_sample_counts_distinct_labelled_pages(spark):
    rows = [(k, "<article><p class=x>" + f"word{k} text " * 30 + "</p></article><div class=y>" + "off " * 30 + "</div>") for k in range(20)]
    pages = spark.createDataFrame(rows * 6 + [(99, f"<p>{k}</p>") for k in range(200)], "page_id bigint, html string")
    weights = html_main.fit(pages, sample=20)
    assert weights.names["is:x"] > 0 > weights.names["is:y"]
    everyone = html_main.fit(spark.createDataFrame(rows, "page_id bigint, html string"))
    assert weights == everyone
