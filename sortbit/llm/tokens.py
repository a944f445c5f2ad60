"""Token ids of texts by a public byte-level BPE vocabulary.

`byte_bpe_50k.json` defines the ids; the same vocabulary as ranks (`byte_bpe_50k.tiktoken`)
gives equal ids several times faster, and a test holds one against the other. Special
tokens' strings in a text are ordinary text. A text that the fast encoder's pattern engine
refuses (a very long run of white space) goes through the vocabulary's own tokenizer.
"""

from __future__ import annotations

import base64
import functools

import numpy as np

from .base import limit_threads

VOCABULARY = "byte_bpe_50k"


def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@functools.cache
def _slow(path: str):
    limit_threads()
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path)
    t.encode_special_tokens = True
    return t


@functools.cache
def _fast(path: str):
    limit_threads()
    import public_tokenizers
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, f)}
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def encode(text: str | None, vocabulary: str = VOCABULARY) -> np.ndarray:
    """The ids of one text; none for null and for an empty text."""
    if not text:
        return np.zeros(0, np.uint32)
    try:
        return np.array(_fast(vocabulary_path(f"{vocabulary}.tiktoken")).encode_ordinary(text), np.uint32)
    except BaseException as e:
        if isinstance(e, KeyboardInterrupt | SystemExit | GeneratorExit | MemoryError):
            raise
        return np.array(_slow(vocabulary_path(f"{vocabulary}.json")).encode(text, add_special_tokens=False).ids, np.uint32)
