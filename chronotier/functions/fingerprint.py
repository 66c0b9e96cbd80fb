"""Canonical text and content keys."""

from __future__ import annotations

import hashlib
import re
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from chronotier.functions.segment import BLANK


def let(value: Column, then) -> Column:
    """then(value) with value evaluated once: the optimizer writes a column that is used
    once into the lambda that uses it, where it would run for every element."""
    return F.get(F.transform(F.array(value), then), F.lit(0))


def canonical(text: Column, fold: str | None = "lower", whitespace: str = "collapse", unicode_form: str | None = None, repair: bool = False) -> Column:
    """whitespace: collapse (runs become one blank, ends are cut), outer or none; fold:
    lower, full (full case folding, an Arrow UDF) or None; unicode_form: NFC, NFKC, …
    (an Arrow UDF) or None; repair: bytes that are no UTF-8 become replacement marks.
    The defaults stay within built-in functions."""
    text = F.make_valid_utf8(text) if repair else text
    if unicode_form or fold == "full":
        text = _rewritten(fold == "full", unicode_form)(text)
    if whitespace == "outer":
        text = F.regexp_replace(text, f"^{BLANK}+|{BLANK}+$", "")
    if whitespace == "collapse":  # plain searches first: few texts need an expression
        other = reduce(lambda a, b: a | b, [F.contains(text, F.lit(c)) for c in "\t\n\r\f"])
        text = F.trim(F.when(other, F.regexp_replace(text, BLANK, " ")).otherwise(text))
        text = let(text, lambda t: F.when(F.contains(t, F.lit("  ")), F.regexp_replace(t, " +", " ")).otherwise(t))
    return F.lower(text) if fold == "lower" else text


def _rewritten(full: bool, form: str | None):
    import pandas as pd
    from pyspark.sql.functions import pandas_udf

    def rewrite(s):
        import unicodedata

        s = s.map(lambda x: x if x is None else unicodedata.normalize(form, x)) if form else s
        return s.str.casefold() if full else s

    rewrite.__annotations__ = {"s": pd.Series, "return": pd.Series}
    return pandas_udf(rewrite, "string")


def content_key(body: Column, bits: int = 256, **how) -> Column:
    """SHA-2 of the canonical text in hex; how goes to canonical, or raw=True."""
    return F.sha2(body if how.pop("raw", False) else canonical(body, **how), bits)


#: The bytes of BLANK, and each of them as a plain blank.
BLANKS = b" \t\n\r\f"
_PLAIN = bytes.maketrans(BLANKS, b" " * len(BLANKS))


def canonical_of(text: bytes) -> bytes:
    """canonical by its defaults, of UTF-8 bytes in Python."""
    text = text.translate(_PLAIN).strip(b" ")
    if b"  " in text:
        text = re.sub(b" +", b" ", text)
    return text.lower() if text.isascii() else text.decode("utf-8", "replace").lower().encode()


def key_of(body: bytes | None) -> str | None:
    """content_key by its defaults, of UTF-8 bytes in Python."""
    return None if body is None else hashlib.sha256(canonical_of(body)).hexdigest()


def short_key(key: Column) -> Column:
    """64 bits for joins at scale; compare the full keys of what meets."""
    return F.xxhash64(key)


def with_keys(segments, **how):
    return segments.withColumn("content_key", content_key(F.col("body"), **how))
