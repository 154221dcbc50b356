import random
import time

import pytest

from evenbatch.llm.html import DEFAULT_WEIGHTS, Page, extract, extract_pages, learn_weights

CASES = [
    (None, ""),
    ("", ""),
    ("<nav>a b c</nav>", ""),
    ("<article><h1>T &amp; U</h1><p>one\n two<br>three<p>four <b>five</b><script>var x='</p>'</script></article><footer>f</footer>", "T & U\none two three\nfour five"),
    ("<body><div class='menu'>x</div><div id=main><h1>Head</h1><p>" + "w " * 30 + "</p><div class='ad'>buy</div><p>end</p></div><div class='comments'>nice</div></body>", "Head\n" + "w " * 29 + "w\nend"),
    ("<article><p>a</p><aside>x</aside><form><input>y</form><p>b</p><section class='comments'><p>me</p></section></article>", "a\nb"),
    ("<main><ul><li>one<li>two</ul><table><tr><td>c<td>d</table></main>", "one\ntwo\nc\nd"),
    ("<article><p>a</p><svg/><p>b c d</p></article>", "a\nb c d"),
    ("<article><p>a b c<svg width=1 /> d e</p><p>f</p></article>", "a b c d e\nf"),
    ("<article><p>a b<iframe src=x> c</p><svg><text>no</text></svg><p>d</p></article>", "a b c\nd"),
    ("<article><a href=x>only link</a></article>", "only link"),
    ("<article><ul><li><a href=x>one</a><li><a href=y>two</a></ul></article>", "one\ntwo"),
    ("<article><div class='header-note'><p>In text</p></div><p>and more</p><div class='share'>tell</div></article>", "In text\nand more"),
    ("<article class='post related-2'><p>text stays</p><div class='comment-list'>me</div></article>", "text stays"),
    ("<article><p>x<span class='ad'>no</span> y</p><!-- z --><p hidden>h</p><p>1 &lt; 2 &#65;", "x y\n1 < 2 A"),
]


@pytest.mark.parametrize("source,want", CASES)
def test_cases(source, want):
    assert extract(source) == want


def test_learned_weights_keep_signs():
    w = learn_weights(["<nav><a href=x>l m</a></nav><article><p>" + "word " * 50 + "</p></article><footer><p>x</p></footer>"] * 3)
    assert w["word"] > 0 > w["tag"] and w["link"] < 0 and learn_weights([])["tag"] < 0


def test_frame(spark):
    rows = [(1, "u", "<article><p>é  x</p></article>", 9), (2, None, None, 9), (None, "v", "", 9), (1, "u", "<article><p>é  x</p></article>", 9)]
    got = extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string, text int")).collect()
    assert sorted((r.page_id or 0, r.text, r.n_chars) for r in got) == [(0, "", 0), (1, "é x", 3), (1, "é x", 3), (2, "", 0)]
    assert extract_pages(spark.createDataFrame([], "page_id long, url string, html string"), DEFAULT_WEIGHTS).count() == 0


@pytest.mark.parametrize("mark", ["article", "main"])
def test_the_run_reaches_beyond_a_mark_that_holds_only_the_heading(mark):
    body = " ".join(f"w{i}" for i in range(60))
    page = f"<body><nav>menu</nav><{mark}><h1>Head line</h1></{mark}><div><p>{body}</p><p>{body}</p></div><footer>foot</footer></body>"
    assert extract(page) == f"Head line\n{body}\n{body}"


def test_the_region_is_the_best_of_all_intervals():
    rng = random.Random(3)
    parts = ["<p>", "</p>", "<b>", "</b>", "one two", "w " * 9, "<a href=x>l m</a>", "<nav>n n</nav>", "<article>", "</article>", "<br>", "<div class='ad'>x</div>", "<div>", "</div>"]
    for _ in range(300):
        page = Page("".join(rng.choices(parts, k=rng.randint(1, 25))))
        scores = page.scores(DEFAULT_WEIGHTS)
        best = max([sum(scores[i:j]) for i in range(len(scores)) for j in range(i + 1, len(scores) + 1)], default=0.0)
        a, b = page.region(DEFAULT_WEIGHTS)
        assert sum(scores[a:b]) == pytest.approx(max(best, 0.0))


@pytest.mark.parametrize("part", ["<p>w w w <b>", "<div>w</x>", "<b><li>w", "<svg>w ", "<header>w</header><i>"])
def test_long_pages_of_unclosed_tags_take_time_in_proportion(part):
    page = "<body>" + part * (100_000 // len(part))
    began = time.process_time()
    extract(page)
    assert time.process_time() - began < 3
