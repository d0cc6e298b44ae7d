"""Article text that looks like boilerplate by a word of its attributes only, and whole pages against another reader."""

from html.parser import HTMLParser

import pytest

from proxembed.llm import html_text

PROSE = "A paragraph of prose, with commas, that is long enough to count as the text of an article, and goes on a little."
OTHER = "Another paragraph, of other words, which is long enough as well to be read as prose, and has no links at all in it."


@pytest.mark.parametrize("attributes", ['style="overflow:hidden"', 'class="hidden-gem"', 'title="a hidden place"', 'data-x="display:none"', 'data-aria-hidden="true"', 'aria-hidden="false"'])
def test_hidden_is_an_attribute_of_its_own(attributes):
    page = f"<body><div {attributes}><p>{PROSE}</p><p>{OTHER}</p></div></body>"
    assert html_text.extract(page).split("\n\n") == [PROSE, OTHER]


def test_links_to_hidden_places_stay():
    assert html_text.extract(f'<article><p>{PROSE} <a href="/hidden-valley">Valley</a></p></article>') == f"{PROSE} Valley"


@pytest.mark.parametrize("attributes", ["hidden", 'hidden=""', "HIDDEN", 'aria-hidden="true"', "aria-hidden=true", 'style="color:red; display : none"', "style='DISPLAY:NONE'"])
def test_hidden_goes(attributes):
    assert html_text.extract(f"<article><p>{PROSE}</p><div {attributes}><p>{OTHER}</p></div></article>") == PROSE


def test_words_cut_containers_only():
    page = f'<article><h2 id="related-work">Related work</h2><p>{PROSE} <span id="Social_structure">Society</span></p><section id="search-methods"><p>{OTHER}</p></section></article>'
    assert html_text.extract(page).split() == f"Related work {PROSE} Society {OTHER}".split()


@pytest.mark.parametrize("part", ['<div class="related"><p>{}</p></div>', '<section class="comments" id="x"><p>{}</p></section>', '<section id="related"><p><a href="x">{}</a></p></section>', '<section id="share"><p>Share this</p></section>'])
def test_boilerplate_in_articles_still_goes(part):
    assert html_text.extract(f"<article><p>{PROSE}</p>{part.format(OTHER)}</article>") == PROSE


def test_blocks_of_a_page_are_two_newlines_apart(spark):
    rows = spark.createDataFrame([(1, "u", f"<article><p>{PROSE}</p><p>{OTHER}</p></article>"), (2, "u", "one<hr>two"), (3, "u", None)], "page_id long, url string, html string")
    got = {r["page_id"]: (r["text"], r["n_chars"]) for r in html_text.main_text(rows).collect()}
    assert got == {1: (f"{PROSE}\n\n{OTHER}", len(PROSE) + len(OTHER) + 2), 2: ("one\n\ntwo", 8), 3: ("", 0)}


class ArticleReader(HTMLParser):
    """What stands in a page's article, read by the standard library: paragraphs and headings, without what can't be article text."""

    OUT = {"script", "style", "nav", "footer", "form", "aside", "noscript", "button"}
    ENDS = {"p", "h1", "h2", "h3", "h4", "div", "li", "ul", "ol", "article", "section", "blockquote", "pre", "td", "tr", "table", "figure", "figcaption", "nav", "footer", "aside", "form"}

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.article, self.out, self.blocks, self.parts, self.cut = 0, 0, [], [], []

    def end_block(self):
        text = " ".join("".join(self.parts).split())
        if text:
            self.blocks.append(text)
        self.parts = []

    def handle_starttag(self, tag, attrs):
        if tag in self.ENDS:
            self.end_block()
        if tag == "br":
            self.parts.append(" ") if self.article and not self.out and not self.cut else None
        if tag == "article":
            self.article += 1
        elif tag in self.OUT:
            self.out += 1
        elif tag in ("div", "section"):
            self.cut.append(bool(self.cut and self.cut[-1]) or any(w in (dict(attrs).get("class") or "") for w in ("ad", "comment", "cookie", "share", "related")))

    def handle_endtag(self, tag):
        if tag in self.ENDS:
            self.end_block()
        if tag == "article":
            self.article -= 1
        elif tag in self.OUT:
            self.out -= 1
        elif tag in ("div", "section") and self.cut:
            self.cut.pop()

    def handle_data(self, data):
        if self.article and not self.out and not (self.cut and self.cut[-1]):
            self.parts.append(data)


@pytest.mark.parametrize("sf", ["0.001", "0.01"])
def test_all_pages_against_another_reader(spark, sf):
    pages = spark.read.parquet(f"/root/testdata/sf{sf}/pages.parquet")
    got = {r["page_id"]: r["text"] for r in html_text.main_text(pages).collect()}
    rows, differ, seen = pages.select("page_id", "html").collect(), [], 0
    for r in rows:
        if not r["html"] or "<article" not in r["html"]:
            continue
        reader = ArticleReader()
        reader.feed(r["html"])
        reader.close()
        reader.end_block()
        seen += 1
        if got[r["page_id"]] != "\n\n".join(reader.blocks):
            differ.append(r["page_id"])
    assert seen > len(rows) / 2 and not differ


def test_line_breaks_are_white_space():
    assert html_text.extract(f"<article><p>{PROSE}<br>and<br/>more</p><p>{OTHER}</p></article>") == f"{PROSE} and more\n\n{OTHER}"


def test_empty_pages_and_wide_ids(spark):
    schema = "page_id long, url string, html string, text int, n_chars string"
    assert html_text.main_text(spark.createDataFrame([], schema)).count() == 0
    rows = spark.createDataFrame([(2**53 + 1, "u", f"<p>{PROSE}</p>", 1, "x"), (None, None, None, None, None), (2**53 + 1, "u", f"<p>{PROSE}</p>", 1, "x")], schema)
    assert sorted((r["page_id"] or 0, r["text"]) for r in html_text.main_text(rows).collect()) == [(0, ""), (2**53 + 1, PROSE), (2**53 + 1, PROSE)]
