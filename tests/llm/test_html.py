from claimloom.llm import html_text

PAGE = """<!DOCTYPE html><html><head><meta charset=utf-8><title>T</title><style>p{}</style></head><body>
<div class="cookie-notice"><p>We use cookies to improve this page. Please accept them all.</p></div>
<header><div class=logo>Site name</div></header><nav><ul><li><a href="/a,b">Home</a></li><li><a href=/c>News</a></li></ul></nav>
<script>var t="</p><p>not text</p>";</script>
<article><h1>A &amp; B</h1><p><b>First&nbsp;line of   the
story here.<br>More<p>Second part, unclosed &lt;tag&gt;. It goes on<p>Third.</p><ul><li>one<li>two</ul></article>
<aside class="sidebar"><h3>Related</h3><p>Another story that you may like to read today.</p></aside>
<section id="comments"><h3>Comments</h3><div class="comment"><p>I liked this story very much, thank you. Great work.</p></div></section>
<form action=x><label>Your mail</label><input><button>Send</button></form>
<footer>&copy; 2020 Site name. All rights reserved.</footer></body></html>"""


def test_page():
    got = html_text.main_text(PAGE, html_text.trained())
    assert got == "A & B First line of the story here. More Second part, unclosed <tag>. It goes on Third. one two"


STORY = "<h1>The title of it</h1><p>A first sentence that is long enough to be prose, and goes on.</p><p>A second one of the same kind, which ends here.</p>"
WANT = "The title of it A first sentence that is long enough to be prose, and goes on. A second one of the same kind, which ends here."


def test_unclosed_and_implied_tags():
    field = html_text.trained()
    for page in (
        f"<html><body><div><button>Menu</div><article>{STORY}</article></body></html>",
        f"<html><body><select><option>a<option>b<article>{STORY}</article></body></html>",
        f"<html><body><button>Go<article>{STORY}</article></body></html>",
        f"<html><body><svg><g><path d=x><title>t</title><article>{STORY}</article></body></html>",
        f"<html><head><title>T</title><meta charset=utf-8><article>{STORY}</article>",
        f"<title>T</title><article>{STORY}</article>",
        f"<html><body><article>{STORY}<template><p>A hidden sentence that nobody is shown on the page.</p></template></article></body></html>",
        f"<html><body><article>{STORY}<video><p>Your browser cannot play this video, so read on.</p></video></article></body></html>",
    ):
        assert html_text.main_text(page, field) == WANT, page
    assert html_text.main_text("<html><body><article><p>We know that <math><mi>a</mi><mo>=</mo><mn>2</mn></math> holds, as was said before.</p></article></body></html>", field) == "We know that a=2 holds, as was said before."
    assert html_text.main_text("<article><p>Some <svg><g><text>no</text></g></svg>prose that goes on for a while, and then ends.</p></article>", field) == "Some prose that goes on for a while, and then ends."


def test_deep_pages_take_linear_time():
    import time

    took = []
    for n in (4000, 16000):
        began = time.process_time()
        assert len(html_text.blocks("".join(f'<div class="c{i} post">word' for i in range(n)))) == n
        took.append(time.process_time() - began)
    assert took[1] < 12 * took[0] + 0.2


def test_held_out_accuracy():
    field = html_text.trained()
    pairs = [(g, y) for feats, labels in html_text.training_pages(150, seed=5) for g, y in zip(field.decode(field.scores(feats)), labels)]
    assert sum(g == y for g, y in pairs) / len(pairs) > 0.985


def test_field_gradient_and_viterbi():
    field = html_text.Field()
    field.move = [[0.4, -0.3], [0.1, 0.6]]
    score = [0.5, -1.0, 2.0, 0.1]
    import itertools
    import math

    def value(y):
        return sum(s for s, l in zip(score, y) if l) + sum(field.move[a][b] for a, b in zip(y, y[1:]))

    every = list(itertools.product((0, 1), repeat=4))
    z = sum(math.exp(value(y)) for y in every)
    marginal, moves = field.expected(score)
    for i in range(4):
        assert abs(marginal[i] - sum(math.exp(value(y)) for y in every if y[i]) / z) < 1e-9
    assert abs(moves[0][1] - sum(math.exp(value(y)) * sum((a, b) == (0, 1) for a, b in zip(y, y[1:])) for y in every) / z) < 1e-9
    assert tuple(field.decode(score)) == max(every, key=value)


def test_edge_pages(spark):
    rows = [(1, None), (2, ""), (3, "<"), (4, "<p>" * 3000), (5, "<!-- open"), (6, "<script>never closed"), (7, PAGE), (7, PAGE), (None, "<article><p>" + "long text. " * 20000)]
    frame = spark.createDataFrame([(i, None, h, "clash") for i, h in rows], "page_id bigint, url string, html string, text string")
    got = html_text.extract(frame, html_text.trained()).collect()
    assert len(got) == len(rows) and all(r.n_chars == len(r.text) for r in got)
    assert {r.text for r in got if r.page_id in (1, 2, 4, 5, 6)} == {""}
    assert [r.n_chars for r in got if r.page_id is None] == [len("long text. ") * 20000 - 1]
