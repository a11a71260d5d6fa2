"""Tokenizers and text clean-up as Catalyst expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Stands between tokens in a key; below every character that a token may hold (no
#: token holds U+0000 to U+001F), so byte order of keys is order of token sequences,
#: shorter ones first.
SEP = "\x01"
#: Follows every key that begins with a given one.
AFTER = "\x02"
WORD = r"[\p{L}\p{N}]+|[^\s\p{L}\p{N}\x00-\x1f]"


def tokens(text: Column, mode: str = "word") -> Column:
    """Tokens of a text: ``word``, ``word_cased``, ``whitespace`` or ``char``."""
    if mode == "word":
        return F.regexp_extract_all(F.lower(text), F.lit(WORD), 0)
    if mode == "word_cased":
        return F.regexp_extract_all(text, F.lit(WORD), 0)
    if mode == "whitespace":
        return F.filter(F.split(text, r"[\s\x00-\x1f]+"), lambda x: x != "")
    if mode == "char":
        return F.regexp_extract_all(text, F.lit(r"[^\s\x00-\x1f]"), 0)
    if mode == "piece":
        # sub-words of at most four characters: a fixed-length stand-in for learned pieces
        return F.flatten(F.transform(tokens(text, "word"), lambda w: F.regexp_extract_all(w, F.lit(r"(?s).{1,4}"), 0)))
    raise ValueError(f"unknown tokenizer {mode!r}")


def key_of(words: Column) -> Column:
    return F.array_join(words, SEP)


def key_tokens(key: Column) -> Column:
    return F.split(key, SEP)


def key_size(key: Column) -> Column:
    return F.when(key == "", 0).otherwise(F.length(key) - F.length(F.replace(key, F.lit(SEP), F.lit(""))) + 1)


def html_text(html: Column) -> Column:
    """Readable text of a page: scripts, styles, comments and tags go, entities are decoded."""
    x = F.regexp_replace(html, r"(?is)<(script|style)\b.*?</(script|style)>", " ")
    x = F.regexp_replace(x, r"(?s)<!--.*?-->", " ")
    x = F.regexp_replace(x, r"(?s)<[^>]*>", " ")
    for entity, char in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        x = F.replace(x, F.lit(entity), F.lit(char))
    return F.trim(F.regexp_replace(x, r"\s+", " "))
