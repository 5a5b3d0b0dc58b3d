"""Byte-pair token ids of whole texts.

The ids are those of the `tokenizers` file. Where a text holds only characters on which both libraries' word patterns are
known to agree, the much faster rank file of the same vocabulary gives them; all other texts, and texts that spell a special
token, go to `tokenizers` itself. A test holds the two against each other over every such character.
"""

from __future__ import annotations

import base64
import functools
import os
import re
from collections.abc import Callable

import numpy as np

JSON_FILE, RANKS_FILE = "byte_bpe_50k.json", "byte_bpe_50k.tiktoken"
#: Anything outside Latin letters, ASCII and common punctuation goes the slow way; so does a possible special token.
_OTHER = re.compile("[^\t\n\r\x20-\x7e\xa1-ɏ‐-―‘-‟•…€]|<\\|")


def public_path(name: str) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


@functools.cache
def _slow(json_path: str):
    """The reference encoder; loaded only in workers that meet a text which needs it, as it takes several times the memory of the ranks."""
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import Tokenizer

    return Tokenizer.from_file(json_path)


@functools.cache
def encoder(json_path: str | None = None, ranks_path: str | None = None) -> Callable[[str], np.ndarray]:
    """text -> uint32 ids; built once in a worker."""
    ranks_path = ranks_path or (public_path(RANKS_FILE) if json_path is None else None)
    json_path = json_path or public_path(JSON_FILE)

    def slow(text: str) -> np.ndarray:
        return np.array(_slow(json_path).encode(text, add_special_tokens=False).ids, np.uint32)

    if ranks_path is None:
        return slow
    import public_tokenizers
    import tiktoken

    with open(ranks_path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    fast = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    return lambda text: slow(text) if _OTHER.search(text) else fast.encode_to_numpy(text, disallowed_special=())
