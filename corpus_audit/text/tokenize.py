"""Tokenizers as column expressions.

``unicode`` follows text segmentation in what matters for counting: runs of letters, marks, digits
and underscores, joined over a single inner full stop or apostrophe, and any other visible
character alone. Colon and digit-comma joins, Katakana and ideographs are not treated apart.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

_RUN = r"[\p{L}\p{M}\p{N}_]"
_OTHER = r"[^\p{L}\p{M}\p{N}_\s\p{Z}\x0B]"
#: Possessive forms match the same tokens and run without a stack of states.
UNICODE = rf"{_RUN}++(?:[.'’]{_RUN}++)*+|{_OTHER}"
WHITESPACE = r"[^\s\p{Z}\x0B]++"
#: The same for DuckDB's engine, inside a quoted string.
UNICODE_SQL = rf"{_RUN}+(?:[.''’]{_RUN}+)*|{_OTHER}"


def tokens(text: Column | str, mode: str = "unicode", pattern: str | None = None, encode: Callable[[str], list[str]] | None = None) -> Column:
    """Array of tokens; null text gives an empty array. Modes: unicode, whitespace, regex, pretrained."""
    text = F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))
    if mode == "pretrained":
        @F.pandas_udf("array<string>")
        def encoded(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
            for texts in batches:
                yield texts.map(encode)

        return encoded(text)
    chosen = {"unicode": UNICODE, "whitespace": WHITESPACE, "regex": pattern}[mode]
    return F.regexp_extract_all(text, F.lit(chosen), F.lit(0))


def n_tokens(text: Column | str = "text", mode: str = "unicode") -> Column:
    return F.size(tokens(text, mode)).cast("long")


def tokens_sql(column: str = "text") -> str:
    return f"regexp_extract_all(coalesce({column}, ''), '{UNICODE_SQL}')"
