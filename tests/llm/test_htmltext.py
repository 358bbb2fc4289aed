from joinlearn.llm import htmltext, queries

WORDS = "Lorem ipsum dolor sit amet consectetur adipiscing elit sed do eiusmod tempor incididunt ut labore et dolore magna aliqua ut enim ad minim veniam"
MENU = "<ul>" + "".join(f'<li><a href="/{i}">Item {i}</a></li>' for i in range(8)) + "</ul>"


def test_article_with_everything_around_it():
    page = f"""<html><head><title>T</title><style>p{{}}</style><script>var a="</p>";</script></head><body><nav>{MENU}</nav><div class="cookie-notice">We use cookies</div>
    <article><h1>A  title</h1><p>{WORDS}&nbsp;&amp;  more</p><div class="ad">Buy now</div><p>Short.</p></article>
    <aside><p>{WORDS}</p></aside><section id="comments"><p>{WORDS} first!</p></section><form><p>Search</p></form><footer>&copy; us</footer></body></html>"""
    assert htmltext.main_text(page) == f"A title\n{WORDS} & more\nShort."


def test_page_without_article_uses_the_distribution():
    page = f'<body><div>{MENU}</div><div id="content"><p>{WORDS}</p><p>{WORDS} two</p><p>Last one.</p></div><div class="sidebar"><p>{WORDS}</p></div><div>Imprint</div></body>'
    assert htmltext.main_text(page) == f"{WORDS}\n{WORDS} two\nLast one."


def test_surge_and_dive():
    assert htmltext.region([3, 4, 200, 180, 190, 5, 4, 3, 2]) == (2, 4)
    assert htmltext.region([]) == (0, -1) and htmltext.region([0, 0]) == (0, -1)


def test_broken_markup_and_empty():
    assert htmltext.main_text(None) == htmltext.main_text("") == htmltext.main_text("<html></html>") == ""
    assert htmltext.main_text(f"<p>{WORDS}<p><b>{WORDS}") == f"{WORDS}\n{WORDS}"
    assert htmltext.main_text("<article><p>" + "a b " * 200_000 + "</article>").startswith("a b a b")
    assert htmltext.main_text("<script>never closed <p>x") == ""


def test_query(spark, sf):
    rows = queries.op2_main_text(spark, sf).collect()
    assert rows and all(r.n_chars == len(r.text) and "<" not in r.text for r in rows)


def test_odd_rows(spark):
    pages = spark.createDataFrame([(1, None, None, 1), (None, "u", "<p>x</p>", 2), (1, None, None, 1)], "page_id long, url string, html string, text int")
    assert htmltext.extract(pages).count() == 3 and htmltext.extract(pages.limit(0)).count() == 0


def test_headline_and_closing_lines_stay():
    long = " ".join([WORDS] * 20)
    assert htmltext.main_text(f"<article><h1>Title</h1><div><p>{long}</p></div><p>A closing paragraph of some words</p></article>") == f"Title\n{long}\nA closing paragraph of some words"
    gap = "".join(f"<p>x{i}</p>" for i in range(9))
    got = htmltext.main_text(f"<article><section><p>{long}</p>{gap}</section><section><p>{WORDS} two</p></section></article>")
    assert got.startswith(long) and got.endswith(f"{WORDS} two")
    flat = htmltext.main_text(f"<body><p>{long}</p>{gap}<p>{WORDS} two</p><p>{WORDS} three</p></body>")
    assert long in flat and f"{WORDS} two\n{WORDS} three" in flat


def test_declared_article_at_every_size():
    for n in (100, 150, 400):
        page = f"<body><article>" + f"<p>{WORDS}</p>" * n + "</article><div>" + f"<p>{WORDS} thread</p>" * 2 * n + "</div></body>"
        assert htmltext.main_text(page) == "\n".join([WORDS] * n)


def test_everything_of_the_article_stays():
    page = f'''<div class="social-history"><article><h1>T</h1><p>{WORDS}</p><figure><figcaption>Cap</figcaption></figure><p><a href="x">one link</a></p>
    <svg><title>i</title><text x="1">Ab<tspan>c</tspan></text></svg><math><mi>x</mi></math><article class="comment"><p>first!</p></article></article></div><div class="comments"><article><p>no</p></article></div>'''
    assert htmltext.main_text(page.replace('<div class="comments"><article><p>no</p></article></div>', "")) == f"T\n{WORDS}\nCap\none link\nAbc x"


def test_same_rule_at_every_page_size():
    for n in (199, 200, 201, 5000):
        page = "<body><article>" + f"<p>{WORDS}</p>" * (2 * n // 5) + "</article><div>" + f"<p>{WORDS}</p>" * (n - 2 * n // 5) + "</div></body>"
        assert htmltext.main_text(page).count("\n") == 2 * n // 5 - 1


def test_surge_and_dive_choose_the_lines():
    flat = "".join(f"<p>{t}</p>" for t in ["Home", "News", WORDS, WORDS, "a b", WORDS, *["x"] * 5, "Imprint", "Contact"])
    assert htmltext.main_text(f"<body>{flat}</body>") == f"{WORDS}\n{WORDS}\na b\n{WORDS}"
    lengths = [3, 200, 0, 0, 0, 150, 150, 4]
    brute = [sum(lengths[i : i + 3]) for i in range(8)]
    assert htmltext.distribution(lengths, 3) == brute and htmltext.region(lengths) == (5, 6)


def test_deep_and_open_markup_is_read_in_time():
    import time

    n, began = 100_000, time.time()
    for page in ("<div>" * n + f"<p>{WORDS}</p>", "<div><p>x</p></b></section>" * n, '<a href="x>y ' * n, "<b " * n, "<![CDATA[" * n, "<div><section>" * n + "</div>" * n + WORDS, "<svg>" * n + WORDS, '<p class="ad">' * n + WORDS):
        htmltext.main_text(page)
    assert time.time() - began < 60
