"""Broken quotes, elements that are never closed, embedded content, and words that carry the decision."""

import pytest

from spanweave.llm import html_main

PLAIN = html_main.weights_of({})
TEXT = "plain words of an article " * 10


@pytest.mark.parametrize(("page", "want"), [
    ("<p title=don't>First text it's here</p>", "First text it's here"),
    ("<p data-x=\"a > b\" title='c > d'>Text</p>", "Text"),
    ('<p title="open>Text</p><p>More</p>', "Text\nMore"),
    ("<p =\"x>y\">Text</p>", "Text"),
    ("<a <b <c", "<a <b <c"),
    ("<p>Before</p><button>Send<p>After</p>", "Before\nSend\nAfter"),
    ("<p>Before</p><button>Send</button><p>After</p>", "Before\nAfter"),
    ("<p>Let <math><mi>x</mi></math> be <object>what</object> <canvas>it</canvas> is</p>", "Let x be what it is"),
    ("<p>Text</p><script>never closed <p>no</p>", "Text"),
    ("<article><div class='social-science'><p>Kept</p></div></article>", "Kept"),
    ("<body class='share-page notice'><p>Kept too</p></body>", "Kept too"),
])
def test_markup(page, want):
    assert html_main.main_text(page, PLAIN) == want


def test_many_open_tags_are_read_in_proportion():
    for part in ("<a ", "<button>", "<p x=\"", "<!", "</", "<p ='"):
        html_main.main_text(part * 100_000, PLAIN)


def test_words_decide_where_markup_does_not():
    """Pages without names for what is around the article; its words have been seen outside of articles."""
    menu = "<div>" + "</div><div>".join(["home contact products"] * 6) + "</div>"
    labelled = [f"<body>{menu}<article><div>{TEXT}</div><div>{TEXT}</div></article>{menu}</body>"] * 5
    weights = html_main.weights_of(html_main.counted(iter(labelled)))
    assert weights.terms["home"] < 0 < weights.terms["plain"]
    assert html_main.main_text(f"<body>{menu}<div>{TEXT}</div><div>{TEXT} more</div>{menu}</body>", weights) == f"{TEXT.strip()}\n{TEXT}more".replace("  ", " ")


def best_run(scores):
    """By trying all runs: the first of the greatest, as (sum, begin, end)."""
    best = (0.0, 0, 0)
    for a in range(len(scores)):
        for b in range(a + 1, len(scores) + 1):
            total = scores[a][1] + sum(t + w for t, w in scores[a + 1 : b])
            if total > best[0] + 1e-9:
                best = (total, a, b)
    return best


def test_scan_finds_the_best_run():
    import random

    r = random.Random(3)
    for _ in range(200):
        names = [f"n{k}" for k in range(6)]
        weights = html_main.Weights(0.0, {f"is:{n}": r.uniform(-3, 3) for n in names}, {"div": -r.random(), "p": -r.random()})
        page = "".join(f"<{t} class={r.choice(names)}>{'w ' * r.randrange(1, 9)}</{t}>" for t in r.choices(["div", "p"], k=12))
        found = list(html_main.blocks(page))
        scores = [(max(-1.0, sum(weights.tags.get(t, 0.0) for t in b.tags)), max(-25.0, weights.words(b))) for b in found]
        total, a, b = best_run(scores)
        got = html_main.main_text(page, weights).split("\n") if html_main.main_text(page, weights) else []
        run = [x.text for x in found[a:b]]
        mine = [k for k in range(len(found)) if [x.text for x in found[k : k + len(got)]] == got]
        assert got == run or any(abs(scores[k][1] + sum(t + w for t, w in scores[k + 1 : k + len(got)]) - total) < 1e-9 for k in mine)
