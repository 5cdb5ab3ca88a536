"""Main text of HTML pages: a chain of expressions, or a parser with link-density pruning."""

from __future__ import annotations

from html.parser import HTMLParser

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mlcurate.session import prepare

#: What the chain removes whole, and what ends a line.
DROPPED = ("script", "style", "nav", "head", "footer", "aside")
BREAKS = "p|br|div|li|ul|ol|h[1-6]|tr|table|article|section|blockquote"
ENTITIES = {"&nbsp;": " ", "&lt;": "<", "&gt;": ">", "&quot;": '"', "&#39;": "'", "&amp;": "&"}


def text_by_sql(html: Column) -> Column:
    """Expressions only: drop comments, unwanted elements and ads, break lines at blocks, drop tags, decode entities, tidy spaces."""
    x = F.coalesce(html, F.lit(""))
    x = F.regexp_replace(x, r"(?s)<!--.*?-->", "")
    for tag in DROPPED:
        x = F.regexp_replace(x, rf"(?is)<{tag}[ >].*?</{tag}>", "")
    x = F.regexp_replace(x, r'(?is)<div class="ad">.*?</div>', "")
    x = F.regexp_replace(x, rf"(?i)</?(?:{BREAKS})(?: [^>]*)?/?>", "\n")
    x = F.regexp_replace(x, r"<[^>]*>", "")
    for k, v in ENTITIES.items():
        x = F.replace(x, F.lit(k), F.lit(v))
    x = F.regexp_replace(x, r"[ \t]+", " ")
    return F.regexp_replace(F.regexp_replace(F.regexp_replace(x, r" ?\n ?", "\n"), r"\n+", "\n"), r"^[ \n]+|[ \n]+$", "")


def title(html: Column) -> Column:
    return F.trim(F.regexp_extract(F.coalesce(html, F.lit("")), r"(?is)<title>(.*?)</title>", 1))


class _Reader(HTMLParser):
    """Blocks of text with the share of their characters that stand in links."""

    VOID = {"br", "img", "hr", "meta", "link", "input"}

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.skip, self.link, self.blocks, self.title, self.in_title = [], 0, [["", 0]], "", False

    def handle_starttag(self, tag, attrs):
        if tag == "title":
            self.in_title = True
        if tag in DROPPED and tag != "head" or "ad" in (dict(attrs).get("class") or "").split():
            self.skip.append(tag)
        elif self.skip and tag == self.skip[-1]:
            self.skip.append(tag)
        if tag == "a":
            self.link += 1
        if tag in ("p", "br", "div", "li", "tr", "article", "section", "h1", "h2", "h3", "h4", "h5", "h6", "blockquote", "table", "ul", "ol"):
            self.blocks.append(["", 0])

    def handle_endtag(self, tag):
        if tag == "title":
            self.in_title = False
        if self.skip and tag == self.skip[-1]:
            self.skip.pop()
        if tag == "a":
            self.link = max(0, self.link - 1)
        if tag in ("p", "div", "li", "tr", "article", "h1", "h2", "h3", "h4", "h5", "h6", "blockquote"):
            self.blocks.append(["", 0])

    def handle_data(self, data):
        if self.in_title:
            self.title += data
        elif not self.skip:
            self.blocks[-1][0] += data
            self.blocks[-1][1] += len(data) if self.link else 0


def read(html: str | None, most_links: float = 0.5) -> tuple[str, str]:
    """Title and text; never raises."""
    r = _Reader()
    try:
        r.feed(html or "")
        r.close()
    except (AssertionError, ValueError):
        pass
    out = [" ".join(t.split()) for t, linked in r.blocks if t.strip() and linked <= most_links * len(t)]
    return " ".join(r.title.split()), "\n".join(out)


def extract(pages: DataFrame, engine: str = "sql", most_links: float = 0.5) -> DataFrame:
    """(page_id, url, title, text)."""
    if engine == "sql":
        return pages.select("page_id", "url", title(F.col("html")).alias("title"), text_by_sql(F.col("html")).alias("text"))
    prepare(pages.sparkSession)

    def run(batches):
        import pyarrow as pa

        for b in batches:
            got = [read(x, most_links) for x in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *[pa.array([g[i] for g in got], pa.string()) for i in (0, 1)]], ["page_id", "url", "title", "text"])

    return pages.select("page_id", "url", "html").mapInArrow(run, "page_id long, url string, title string, text string")
