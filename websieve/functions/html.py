"""Text blocks of HTML by a chain of replacements, without a UDF."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# The replacements, in order, and the entities that are decoded ("&amp;" last).
STEPS = (
    (r"(?is)<script[^>]*>.*?</script>|<style[^>]*>.*?</style>|<head[^>]*>.*?</head>|<!--.*?-->", "\n"),
    (r"(?i)</?(p|br|div|li|ul|ol|h[1-6]|nav|article|section|footer|header|table|tr|td|th|blockquote|pre)( [^>]*)?/?>", "\n"),
    (r"<[^>]*>", ""),
)
ENTITIES = (("&copy;", "©"), ("&middot;", "·"), ("&quot;", '"'), ("&lt;", "<"), ("&gt;", ">"), ("&nbsp;", " "), ("&#39;", "'"), ("&amp;", "&"))


def text_of(html: Column) -> Column:
    """The text of a page, block elements divided by line ends; lines may be blank."""
    for pattern, by in STEPS:
        html = F.regexp_replace(html, pattern, by)
    for entity, character in ENTITIES:
        html = F.replace(html, F.lit(entity), F.lit(character))
    return F.regexp_replace(html, r"[ \t\r]+", " ")


def blocks(html: Column) -> Column:
    """The non-blank blocks of a page, trimmed, in order."""
    return F.filter(F.transform(F.split(text_of(html), "\n"), lambda x: F.trim(x)), lambda x: x != "")


def declared_language(html: Column) -> Column:
    return F.regexp_extract(html, r'<html[^>]* lang="([a-zA-Z-]+)"', 1)


def sql_blocks(column: str) -> str:
    """The same chain in DuckDB's SQL."""
    for pattern, by in STEPS:
        column = f"regexp_replace({column}, '{pattern}', {'chr(10)' if by else chr(39) * 2}, 'g')"
    for entity, character in ENTITIES:
        column = f"replace({column}, '{entity}', '{character.replace(chr(39), chr(39) * 2)}')"
    column = f"regexp_replace({column}, '[ \\t\\r]+', ' ', 'g')"
    return f"list_filter(list_transform(string_split({column}, chr(10)), lambda x: trim(x, ' ')), lambda x: x <> '')"
