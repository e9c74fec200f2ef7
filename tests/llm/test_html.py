import itertools
import random

import numpy as np
import pytest

from rangecut.llm import html_seeds, html_text
from rangecut.llm.catalog import html_queries

BODY = "<p>The first paragraph of the story tells about the town, and what its people did that year.</p><p>Second one, with a <a href=x>link</a> and more of the story as it went on for long.</p>"
MAIN = "The first paragraph of the story tells about the town, and what its people did that year.\nSecond one, with a link and more of the story as it went on for long."
PAGES = [
    (f'<body><nav><a href=1>Home</a></nav><div class="ad">Buy this.</div><article><h1>Title &amp; more</h1>{BODY}</article><footer>&copy; x</footer>', "Title & more\n" + MAIN),
    (f'<div id="sidebar"><ul><li><a href=1>One thing</a></li></ul></div><div class="content"><h1>Title</h1>{BODY}</div><div class="comments"><p>Great article, thanks for writing it!</p></div>', "Title\n" + MAIN),
    (f"<article><header><h1>Title</h1></header>{BODY}<aside>Advert: buy now</aside><section id='comments'><p>I think that this is wrong, says a reader.</p></section></article>", "Title\n" + MAIN),
    (f"<article>{BODY}<form><label>Mail</label><input></form><script>var a='<p>no</p>'</script></article><div class='cookie-notice'>We use cookies.</div>", MAIN),
    ("", ""),
    ("<nav>only menu</nav>", ""),
    ("<article><p>cut off in the mid", "cut off in the mid"),
    ("<article><p>a &lt;b&gt; &#233;&nbsp;c\n\n d<br>e</p><!-- <p>no</p> --></article>", "a <b> é c d e"),
]


@pytest.mark.parametrize(("page", "text"), PAGES)
def test_pages(page, text):
    cutter = html_text.train([p for p, _ in PAGES] * 5)
    assert html_text.main_text(page, cutter) == text


def test_cut_is_minimal():
    rng = np.random.default_rng(0)
    for _ in range(60):
        n = int(rng.integers(1, 9))
        gain = rng.normal(size=n)
        edges = [(i, j, float(rng.uniform(0, 1.5))) for i in range(n) for j in range(i) if rng.uniform() < 0.5]
        worth = lambda x: sum(gain[i] for i in range(n) if x[i]) - sum(w for i, j, w in edges if x[i] != x[j])
        best = max(map(worth, itertools.product((False, True), repeat=n)))
        assert np.isclose(worth(html_text.minimum_cut(gain, edges)), best)


def test_frame(spark):
    rows = [(i, f"u{i}", p, "x") for i, (p, _) in enumerate(PAGES)] + [(None, None, None, None), (0, "u0", PAGES[0][0], "x")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, text string")
    out = html_text.extract(df, html_text.fit(df)).collect()
    assert len(out) == len(rows)
    assert all(r.n_chars == len(r.text) for r in out)
    assert {r.page_id: r.text for r in out}[0] == PAGES[0][1]
    assert html_text.extract(df.where("false"), html_text.train([])).count() == 0


WORDS = "river market bridge council summer winter farmer letter window garden story evening people water village council".split()


def sentence(rng, n):
    return " ".join(rng.choice(WORDS) for _ in range(n)).capitalize() + rng.choice(("", "."))


def page(rng, landmarks):
    """A page, and its text by construction: long and very short paragraphs, menus without links, a closing line."""
    title = sentence(rng, 5).rstrip(".")
    text = [sentence(rng, rng.choice((1, 2, 2, 12, 25, 40))) for _ in range(rng.randint(5, 9))]
    menu = "".join(f"<div>{sentence(rng, rng.choice((1, 2, 3)))}</div>" for _ in range(6))
    nav, article, footer = ("nav", "article", "footer") if landmarks else ("div", "div", "div")
    body = "".join(f"<div>{t}</div>" for t in text)
    return f"<body><{nav}>{menu}</{nav}><{article}><h1>{title}</h1>{body}</{article}><{footer}><div>Imprint</div><div>Contact</div></{footer}></body>", [title, *text]


def test_the_cut_mends_what_the_classifier_alone_gets_wrong():
    rng = random.Random(5)
    cutter = html_text.train([page(rng, True)[0] for _ in range(60)])
    assert cutter.edges[0] > 0.2  # siblings go together
    alone = joined = 0
    for _ in range(60):
        html, text = page(rng, False)
        blocks = html_text.blocks_of(html)
        truth = np.array([b.text in text for b in blocks])
        alone += ((cutter.gains(blocks) > 0) != truth).sum()
        joined += (cutter.content(blocks) != truth).sum()
    assert 3 * joined < alone and alone > 20


def test_hand_labelled_pages():
    """With landmarks and names nearly all hand-labelled blocks come out right, and the cut doesn't make more errors."""
    cutter = html_text.train([p for p, _ in PAGES])
    wrong = {False: 0, True: 0}
    for e in html_text.examples_of([]):
        if not e.blotted:
            wrong[False] += ((cutter.gains(e.blocks) > 0) != e.labels).sum()
            wrong[True] += (cutter.content(e.blocks) != e.labels).sum()
    assert wrong[True] <= wrong[False] <= 6
    assert all(html_seeds.MARK not in b.text for e in html_text.examples_of([]) for b in e.blocks)


def test_registered_query(spark, tmp_path):
    rows = [(i, f"u{i}", p, "x", 1) for i, (p, _) in enumerate(PAGES * 3)] + [(None, None, None, None, None), (0, "u0", PAGES[0][0], "x", 1), (900, "u", "<article>" + "<p>long text that goes on and on.</p>" * 3000, "x", 1)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, text string, n_chars int")
    df.write.parquet(str(tmp_path / "pages.parquet"))
    out = html_queries.op8_html_extract(spark, str(tmp_path))
    assert dict(out.dtypes) == {"page_id": "bigint", "url": "string", "text": "string", "n_chars": "bigint"}
    got = out.collect()
    assert len(got) == len(rows)
    for r in got:
        want = "" if r.page_id is None else "\n".join(["long text that goes on and on."] * 3000) if r.page_id == 900 else (PAGES * 3)[r.page_id][1]
        assert r.text == want and r.n_chars == len(want)
