"""Byte-level BPE by public vocabularies; tokenizers are applied, never trained. The vocabulary's path or name is a parameter."""

from __future__ import annotations

import base64
import os
import re
from functools import cache

import numpy as np

VOCABULARY = "byte_bpe_50k.tiktoken"
#: White space in one run from which on the quick encoder could run out of stack.
LONG_RUN = 50_000
_LONG_RUN = re.compile(rf"\s{{{LONG_RUN}}}")


def _path(vocabulary: str) -> str:
    import public_tokenizers

    return vocabulary if os.path.exists(vocabulary) else public_tokenizers.path(vocabulary)


@cache
def encoding(vocabulary: str):
    """The vocabulary's encoding of ordinary text; it knows no added token."""
    import public_tokenizers
    import tiktoken

    with open(_path(vocabulary), "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


@cache
def plain_tokenizer(vocabulary: str):
    """The same vocabulary in the library that takes a run of white space of any length; a quarter of the speed otherwise."""
    from tokenizers import Tokenizer

    return Tokenizer.from_file(os.path.splitext(_path(vocabulary))[0] + ".json")


def ordinary_ids(text: str, vocabulary: str = VOCABULARY) -> list[int]:
    """Ids of a text that holds no added token."""
    if len(text) >= LONG_RUN and _LONG_RUN.search(text):
        return plain_tokenizer(vocabulary).encode(text, add_special_tokens=False).ids
    return encoding(vocabulary).encode_ordinary(text)


def token_ids(text: str | None, vocabulary: str = VOCABULARY) -> np.ndarray:
    """Ids of any text, in which the string of an added token is ordinary text."""
    return np.array(encoding(vocabulary).encode_ordinary("") if not text else _whole(text, vocabulary), np.uint32)


def _whole(text: str, vocabulary: str) -> list[int]:
    if len(text) < LONG_RUN or not _LONG_RUN.search(text):
        return encoding(vocabulary).encode_ordinary(text)
    tokenizer = plain_tokenizer(vocabulary)
    tokenizer.encode_special_tokens = True
    try:
        return tokenizer.encode(text, add_special_tokens=False).ids
    finally:
        tokenizer.encode_special_tokens = False
