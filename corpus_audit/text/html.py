"""Visible text of html by expressions alone (enough for counting; see the llm subpackage for extraction)."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Patterns whose matches give way to a space, in this order; both Java's and RE2's engine read them alike.
STRIPPED = [r"(?is)<script.*?</script>", r"(?is)<style.*?</style>", r"(?s)<!--.*?-->", r"(?s)<[^>]*>"]
ENTITIES = [("&nbsp;", " "), ("&middot;", "·"), ("&copy;", "©"), ("&quot;", '"'), ("&#39;", "'"), ("&lt;", "<"), ("&gt;", ">"), ("&amp;", "&")]


def visible_text(html: Column) -> Column:
    for pattern in STRIPPED:
        html = F.regexp_replace(html, pattern, " ")
    for entity, char in ENTITIES:
        html = F.replace(html, F.lit(entity), F.lit(char))
    return F.trim(F.regexp_replace(html, r"[ \t\r\n]+", " "))


def title(html: Column) -> Column:
    return F.trim(F.regexp_extract(html, r"(?is)<title[^>]*>(.*?)</title>", 1))


def visible_text_sql(column: str) -> str:
    for pattern in STRIPPED:
        column = f"regexp_replace({column}, '{pattern}', ' ', 'g')"
    for entity, char in ENTITIES:
        column = f"replace({column}, '{entity}', '{char.replace(chr(39), chr(39) * 2)}')"
    return f"trim(regexp_replace({column}, '[ \\t\\r\\n]+', ' ', 'g'))"
