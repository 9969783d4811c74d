"""Pre-token splitting that agrees with the tokenizers library, with its own pass as fall-back.

The fast split is used only for texts made of characters on which Python's and the
library's Unicode tables agree (ASCII without control codes, Latin letters up to U+024F);
all other texts, and texts that hold a special token's string, go whole through the library.
"""

from __future__ import annotations

import re

#: The split patterns that the two public vocabularies come with, for plain texts,
#: where a letter is what is alphanumeric but no digit.
BYTE_LEVEL = re.compile(r"'(?:[stmd]|re|ve|ll)| ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+")
WORD_END = re.compile(r"'(?:[stmd]|re|ve|ll)|[^\W\d_]+|\d|(?:[^\s\w]|_)+")
PLAIN = re.compile("[^\t\n\x0b\x0c\r\x20-\x7e\xa1-\xb1\xb4-\xb8\xba\xbb\xbf-įı-ɏ]")

_LOADED: dict = {}


def load(name: str):
    """The tokenizer of a vocabulary file: a path, or a name that public_tokenizers knows."""
    if name not in _LOADED:
        import os

        from tokenizers import Tokenizer

        path = name
        if not os.path.isabs(name):
            import public_tokenizers

            path = public_tokenizers.path(name)
        _LOADED[name] = Tokenizer.from_file(str(path))
    return _LOADED[name]


def specials(tokenizer) -> list[str]:
    return [t.content for t in tokenizer.get_added_tokens_decoder().values()]


def plain(text: str, special: list[str]) -> bool:
    return PLAIN.search(text) is None and not ("<|" in text and any(s in text for s in special))


class Cache(dict):
    """What one worker has worked out for pre-tokens, over all its tasks; let go when full."""

    kept: dict = {}

    @classmethod
    def of(cls, name: str, entries: int) -> dict:
        own = cls.kept.setdefault(name, {})
        if len(own) > entries:
            own.clear()
        return own


def unknown(split: list, *known: dict) -> list[str]:
    """Distinct pre-tokens that no table has."""
    found = set().union(*(s for s in split if s))
    for k in known:
        found = found.difference(k)
    return list(found)
