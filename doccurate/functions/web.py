"""URLs and HTML as Column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

_BLOCKS = "p|div|article|section|nav|footer|header|ul|ol|li|tr|table|br|h[1-6]|title|body|html|head"
#: Entities that are decoded (fixed values).
_ENTITIES = [("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")]


def decode_entities(text: Column) -> Column:
    for entity, char in _ENTITIES:
        text = F.replace(text, F.lit(entity), F.lit(char))
    return text


def _squeeze(text: Column) -> Column:
    lines = F.regexp_replace(F.regexp_replace(F.regexp_replace(text, r"[ \t]+", " "), r" ?\n ?", "\n"), r"\n+", "\n")
    return F.regexp_replace(lines, r"^[ \n]+|[ \n]+\z", "")


def _no_code(html: Column) -> Column:
    return F.regexp_replace(html, r"(?is)<script.*?</script>|<style.*?</style>|<!--.*?-->", " ")


def to_plain(html: Column) -> Column:
    """Visible text: block tags become line ends, other tags spaces, entities characters."""
    text = F.regexp_replace(_no_code(html), rf"(?i)</?(?:{_BLOCKS})\b[^>]*>", "\n")
    return _squeeze(decode_entities(F.regexp_replace(text, r"<[^>]*>", " ")))


def to_markdown(html: Column) -> Column:
    """Headings, emphasis, lists and links as Markdown; the rest as in to_plain."""
    text = _no_code(html)
    text = F.regexp_replace(text, r"(?i)<h1\b[^>]*>", "\n# ")
    text = F.regexp_replace(text, r"(?i)</?(?:b|strong)\b[^>]*>", "**")
    text = F.regexp_replace(text, r"(?i)<li\b[^>]*>", "\n- ")
    text = F.regexp_replace(text, r'(?is)<a\b[^>]*href="([^"]*)"[^>]*>(.*?)</a>', "[$2]($1)")
    text = F.regexp_replace(text, rf"(?i)</?(?:{_BLOCKS})\b[^>]*>", "\n")
    return _squeeze(decode_entities(F.regexp_replace(text, r"<[^>]*>", " ")))


def article_of(html: Column) -> Column:
    """Inner HTML of the first article element, else all."""
    inner = F.regexp_extract(html, r"(?is)<article[^>]*>(.*?)</article>", 1)
    return F.when(inner != "", inner).otherwise(html)


def hrefs(html: Column) -> Column:
    return F.regexp_extract_all(html, F.lit(r'href="([^"]*)"'), 1)


def absolute(base: Column, href: Column) -> Column:
    """href against base: absolute, host-rooted or relative to the host's root."""
    root = F.regexp_extract(base, r"^([a-z]+://[^/?#]*)", 1)
    return F.when(href.rlike("^[a-z]+://"), href).when(href.startswith("/"), F.concat(root, href)).otherwise(F.concat(root, F.lit("/"), href))


def canonical_url(url: Column) -> Column:
    """Lower-case scheme and host, no fragment, no tracking keys (utm_*, ref), other query keys in order."""
    bare = F.regexp_replace(url, r"#.*$", "")
    head = F.lower(F.regexp_extract(bare, r"^([A-Za-z]+://[^/?]*)", 1))
    path = F.regexp_extract(bare, r"^[A-Za-z]+://[^/?]*([^?]*)", 1)
    query = F.regexp_extract(bare, r"\?(.*)$", 1)
    keys = F.array_sort(F.filter(F.split(query, "&"), lambda k: (k != "") & ~k.rlike("^(utm_[^=]*|ref)(=|$)")))
    return F.when(head == "", bare).otherwise(F.concat(head, F.when(path == "", "/").otherwise(path), F.when(F.size(keys) > 0, F.concat(F.lit("?"), F.array_join(keys, "&"))).otherwise("")))
