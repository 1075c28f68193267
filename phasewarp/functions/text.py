"""Preprocessing: formatting, segmentation, stop words, phrases.  Column expressions only."""

from __future__ import annotations

from collections.abc import Iterable

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from phasewarp.sources.stopwords import LANGUAGES, all_stop_words, stop_list

WORD = r"[\p{L}\p{N}]+"
LINK = r"(https?://|www\.)[^\s<>]+"
ENTITIES = (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&"))


def strip_html(html: Column) -> Column:
    """Visible text: scripts, styles and comments go with their content, then tags, then entities."""
    out = html
    for pattern in (r"(?is)<script\b.*?</script\s*>", r"(?is)<style\b.*?</style\s*>", r"(?s)<!--.*?-->", r"(?s)<[^>]*>"):
        out = F.regexp_replace(out, pattern, " ")
    for name, char in ENTITIES:
        out = F.replace(out, F.lit(name), F.lit(char))
    return out


def format_text(text: Column, keep: str = r"\p{L}\p{N}", html: bool = False) -> Column:
    """Lower case without links, markup, punctuation and irrelevant characters."""
    out = strip_html(text) if html else text
    out = F.regexp_replace(F.regexp_replace(F.lower(out), LINK, " "), rf"[^{keep}]+", " ")
    return F.trim(out)


def segment(text: Column, method: str = "regex", dictionary: Iterable[str] = (), longest: int = 4) -> Column:
    """Words of a text.  ``regex``: runs of letters and digits; ``char_bigram``: overlapping pairs
    of characters, for unspaced scripts; ``dict_maxmatch``: forward maximum matching."""
    low = F.lower(text)
    if method == "regex":
        return F.regexp_extract_all(low, F.lit(f"({WORD})"), F.lit(1))
    if method == "char_bigram":
        bare = F.regexp_replace(low, rf"[^\p{{L}}\p{{N}}]+", "")
        return F.when(F.length(bare) < 2, F.array()).otherwise(F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.length(bare) - 1)), lambda i: F.substring(bare, i, F.lit(2))))
    if method == "dict_maxmatch":
        return max_match(frozenset(dictionary), longest)(low)
    raise ValueError(f"unknown segmenter {method!r}")


def max_match(words: frozenset[str], longest: int):
    """A vectorised function that takes the longest dictionary word at each position, else one
    character; other characters separate."""

    @F.pandas_udf("array<string>")
    def run(texts: pd.Series) -> pd.Series:
        def cut(text):
            out, i = [], 0
            while text is not None and i < len(text):
                n = next((n for n in range(min(longest, len(text) - i), 1, -1) if text[i : i + n] in words), 1)
                if text[i : i + n].isalnum():
                    out.append(text[i : i + n])
                i += n
            return out

        return texts.map(cut)

    return run


def without_stop_words(words: Column, lang: Column | None = None, least: int = 2) -> Column:
    """Words of at least ``least`` characters that are not on the list of ``lang`` (without it, on
    none of all lists).  Repeats stay, so counts stay."""
    def left(listed: tuple[str, ...]) -> Column:
        return F.filter(words, lambda w: (F.length(w) >= least) & ~w.isin(*listed))

    if lang is None:
        return left(all_stop_words())
    out = None
    for code in LANGUAGES:
        out = F.when(lang == code, left(stop_list(code))) if out is None else out.when(lang == code, left(stop_list(code)))
    return out.otherwise(F.filter(words, lambda w: F.length(w) >= least))


def join_phrases(text: Column, phrases: Iterable[str]) -> Column:
    """Known phrases become one word, their spaces replaced by underscores."""
    out = F.lower(text)
    for p in phrases:
        out = F.replace(out, F.lit(p.lower()), F.lit(p.lower().replace(" ", "_")))
    return out


def without_numbers(words: Column) -> Column:
    return F.filter(words, lambda w: ~w.rlike(r"^\p{N}+$"))


def ngrams(words: Column, n: int = 2) -> Column:
    return F.when(F.size(words) < n, F.array().cast("array<string>")).otherwise(
        F.transform(F.sequence(F.lit(0), F.greatest(F.lit(0), F.size(words) - n)), lambda i: F.array_join(F.slice(words, i + 1, n), " "))
    )


def prepare(records: DataFrame, stop: str | None = "lang", phrases: Iterable[str] = (), keep_numbers: bool = True) -> DataFrame:
    """Records with their ``words``.  ``stop``: the column with the language, ``all``, or None."""
    words = segment(join_phrases(F.col("text"), phrases) if phrases else F.col("text"))
    if phrases:
        words = F.regexp_extract_all(join_phrases(F.col("text"), phrases), F.lit(r"([\p{L}\p{N}_]+)"), F.lit(1))
    if not keep_numbers:
        words = without_numbers(words)
    if stop == "all":
        words = without_stop_words(words)
    elif stop:
        words = without_stop_words(words, F.col(stop))
    return records.withColumn("words", words)
