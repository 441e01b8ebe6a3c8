"""The pre-token split of the byte-level vocabularies, with a quick way for plain Latin text."""

from __future__ import annotations

import re
from functools import lru_cache

import public_tokenizers
import regex

# Inside this alphabet Python's own classes agree with the Unicode properties of the published pattern.
_OUTSIDE = re.compile("[^\t-\r\x20-\x7eÀ-ÖØ-öø-ɏ]")
_QUICK = re.compile(r" ?[A-Za-zÀ-ÖØ-öø-ɏ]+|'(?:[stmd]|re|ve|ll)| ?[0-9]+| ?[!-/:-@\[-`{-~]+|[\t-\r ]+(?![^\t-\r ])|[\t-\r ]+")


@lru_cache(1)
def _exact() -> regex.Pattern:
    return regex.compile(public_tokenizers.PATTERN)


def is_plain(text: str) -> bool:
    return _OUTSIDE.search(text) is None


def pretokens(text: str) -> list[str]:
    return _QUICK.findall(text) if is_plain(text) else _exact().findall(text)
