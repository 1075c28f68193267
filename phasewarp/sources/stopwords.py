"""Stop lists, one file a language in ``lists``, so that neither a session nor Spark's jars are
needed to name their words (origin and licence: ``lists/LICENCE.txt``)."""

from __future__ import annotations

import functools
from pathlib import Path

#: Language codes of the tables that have a list.
LANGUAGES = ("en", "fr", "de", "es")
_LISTS = Path(__file__).with_name("lists")


@functools.cache
def stop_list(lang: str) -> tuple[str, ...]:
    return tuple((_LISTS / f"{lang}.txt").read_text(encoding="utf-8").split())


@functools.cache
def all_stop_words() -> tuple[str, ...]:
    return tuple(sorted(set().union(*map(stop_list, LANGUAGES))))
