import pytest

from evsketch.llm import html

BODY = "".join(f"<p>Paragraph {i} has a good many plain words in it, so that it is long and dense enough to read.</p>" for i in range(6))
TEXT = " ".join(f"Paragraph {i} has a good many plain words in it, so that it is long and dense enough to read." for i in range(6))
NAV = "<nav><ul>" + "".join(f"<li><a href=/{i}>Link {i}</a></li>" for i in range(9)) + "</ul></nav>"
LINKS = "<div>" + "".join(f"<a href=/{i}>see also page {i}</a> " for i in range(12)) + "</div>"


@pytest.mark.parametrize(
    "page",
    [
        f"<html><head><title>t</title><style>p{{}}</style></head><body>{NAV}<article>{BODY}</article><footer>c</footer></body></html>",
        f"<body>{NAV}{LINKS}<div class='content'>{BODY}</div><div id=sidebar>{BODY[:200]}</div><footer>&copy; x</footer></body>",
        f"<body><div class='ad'>Buy now and save a lot of money on everything you ever wanted</div><main>{BODY}<form><p>Name <input></p></form><div class='comments'><p>I think that this is a really great article, thank you so much!</p></div></main></body>",
        f"<body><header>Site</header><article>{BODY}<aside>aside text</aside><script>var x = '<p>no</p>';</script><div class='cookie-notice'>We use cookies</div></article></body>",
    ],
)
def test_article_without_the_rest(page):
    assert html.main_text(page) == TEXT


@pytest.mark.parametrize("named", ["class='single-post has-sidebar'", "class=nav-open", "id='right-sidebar'", "class='sidebar'"])
def test_names_of_the_whole_page_drop_nothing(named):
    for inner in (f"<main {named}>{BODY}</main>", f"<article {named}>{BODY}</article>", f"<div>{BODY}</div>"):
        assert html.main_text(f"<html {named}><body {named}>{NAV}{inner}<footer>c</footer></body></html>") == TEXT


@pytest.mark.parametrize("name", ["widget-content", "social-science"])
def test_parts_of_names_drop_only_what_is_thin(name):
    assert html.main_text(f"<body>{NAV}<div class='{name}'>{BODY}</div></body>") == TEXT
    assert html.main_text(f"<body>{NAV}<article>{BODY}<div class='{name}'><a href=/>more</a></div></article></body>") == TEXT


def test_references_white_space_and_unclosed_tags():
    page = "<article><h1>A &amp; B</h1><p>one\n\t two&nbsp;<b>three</b>four<p>five &lt; six<br>seven</article>"
    assert html.main_text(page) == "A & B one two threefour five < six seven"


def test_edge_inputs(spark):
    rows = [(1, "u", None, 0), (2, "u", "", 0), (3, None, "plain text, no tags", 0), (4, "u", "<p>" * 3000 + "deep", 0), (5, "u", "<div class='x", 0), (None, "u", "<p>a</p>", 0), (6, "u", "<a b='" * 50, 0)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, text int")
    got = {r.page_id: r for r in html.extract(df).collect()}
    assert got[1].text == got[2].text == "" and got[3].text == "plain text, no tags" and got[4].text == "deep" and got[None].text == "a"
    assert all(r.n_chars == len(r.text) for r in got.values())
    assert html.extract(df.limit(0)).count() == 0
