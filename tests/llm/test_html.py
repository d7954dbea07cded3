"""Main text keeps the whole article, and only noise is left out."""

from html.parser import HTMLParser

from rolelattice.llm import html


def test_whole_article_is_kept():
    body = "<p>" + "long text of the body " * 60 + "</p>"
    nested = f"<html><body><div class=ad>buy</div><article><header><h1>Head</h1></header><p>lead</p><div class=body>{body}</div></article><div>terms</div></body></html>"
    plain = f"<body><div class=wrap><h1>Head</h1><div class=body>{body}</div><section><p>more of it</p></section></div><ul><li><a href=x>menu</a></li></ul></body>"
    host = html.candidate(html.blocks(nested))[0]
    assert host == "page>html>body>article"
    text = html.main_text(nested, host)
    assert text.startswith("Head\n\nlead\n\nlong text") and "terms" not in text and "buy" not in text
    for path in ("page>body>div.wrap>div.body", None):  # sections beside the host's container stay
        text = html.main_text(plain, path)
        assert text.startswith("Head\n\nlong text") and text.endswith("more of it")


def test_pages_of_links_have_text():
    article = "<body><article><ul><li><a href=a>first</a></li><li><a href=b>second</a></li></ul></article><div>some words</div></body>"
    for path in (None, "page>body>div"):
        assert html.main_text(article, path).startswith("first\n\nsecond")
    assert html.main_text("<body><div><a href=a>only link</a></div></body>", None) == "only link"
    card = "<body><div>the text of this page is here</div><article><p>card</p></article></body>"
    assert html.main_text(card, None) == "the text of this page is here\n\ncard"


def test_names_around_the_content_are_not_noise():
    inner = "<h1>Head</h1><p>" + "words of the text " * 20 + "</p>"
    for around in ("<div class='layout has-sidebar'>{}</div>", "<div id='page-no-comments'>{}</div>", "<div class='widget'><article class='post widget-ready'>{}</article></div>", "<main class='with-header'>{}</main>", "<div class=sidebar>{}</div>", "<form id=aspnet>{}</form>", "<div class=hidden><div class=social>{}</div></div>"):
        page = f"<body>{around.format(inner)}<div class=ad>buy</div><div id='cookie-banner'>we use cookies</div></body>"
        got = html.main_text(page, None)
        assert got.startswith("Head\n\nwords of") and "buy" not in got and "cookies" not in got, around


def test_names_within_the_content_stay_noise():
    talk = "<section id=comments><article class=comment><p>" + "a reader says this " * 40 + "</p></article></section>"
    page = f"<body><main><article class=post><div class=header><h1>Head</h1></div><p>short <span class=share>share</span>text</p><form>mail</form></article>{talk}</main></body>"
    assert html.main_text(page, None) == "Head\n\nshort text"
    assert html.main_text("<body><div class=comments><p>only this</p></div></body>", None) == "only this"


class Plain(HTMLParser):
    """Blocks of the one article of a page: text between the tags of headings and paragraphs."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.inside, self.found, self.now = False, [], ""

    def cut(self):
        if self.now.split():
            self.found.append(" ".join(self.now.split()))
        self.now = ""

    def handle_starttag(self, tag, attrs):
        self.inside |= tag == "article"
        if tag in ("article", "h1", "p"):
            self.cut()
        if tag == "br":
            self.now += " "

    def handle_endtag(self, tag):
        if tag in ("article", "h1", "p"):
            self.cut()
        self.inside &= tag != "article"

    def handle_data(self, data):
        if self.inside:
            self.now += data


def test_given_pages_equal_a_plain_parser(spark):
    """All pages of the table have one article of headings and paragraphs."""
    sf = "/root/testdata/sf0.01"
    got = {r.page_id: r.text for r in html.op8_html(spark, sf).collect()}
    pages = spark.read.parquet(f"{sf}/pages.parquet").select("page_id", "html").collect()
    assert len(got) == len(pages)
    for r in pages:
        p = Plain()
        p.feed(r.html or "")
        p.close()
        assert got[r.page_id] == "\n\n".join(p.found)
