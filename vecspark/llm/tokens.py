"""Byte-level BPE ids of whole texts, and the places where a text may be cut.

A text may be cut before any single space that stands between two characters that
are not white space: the pre-tokenizer never matches across such a place, so the
ids of the text are the ids of its pieces, one after the other.
"""

from __future__ import annotations

import base64
import json
import os
import re

import numpy as np

VOCABULARY = "byte_bpe_50k.tiktoken"  # the vocabulary of byte_bpe_50k.json as ranks
CUT = re.compile(r"(?<=\S) (?=\S)")


def added_tokens(path: str) -> dict[str, int]:
    """The added tokens of the JSON file beside a ranks file; none where there is no such file."""
    path = os.path.splitext(path)[0] + ".json"
    if not os.path.exists(path):
        return {}
    with open(path, encoding="utf-8") as file:
        return {x["content"]: x["id"] for x in json.load(file)["added_tokens"]}


def encoding(path: str | None = None, added: bool = False):
    """The tokenizer whose vocabulary file lies at ``path`` (None: the installed public one);
    ``added``: with the added tokens of its JSON file."""
    import public_tokenizers
    import tiktoken

    path = path or public_tokenizers.path(VOCABULARY)
    with open(path, "rb") as file:
        ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, file)}
    special = added_tokens(path) if added else {}
    ranks = {token: rank for token, rank in ranks.items() if rank not in special.values()}
    return tiktoken.Encoding("byte_bpe", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=special)


class PieceTokenizer:
    """Ids and counts of texts. Control strings in a text are ordinary text, or, with ``added``, the
    added tokens that the JSON tokenizer makes of them; none holds white space, so cuts stay safe."""

    def __init__(self, path: str | None = None, added: bool = False):
        self.encoding = encoding(path, added)
        self.plain = self.encoding._core_bpe.encode_ordinary
        self.added = tuple(self.encoding.special_tokens_set)
        if any(re.search(r"\s", x) for x in self.added):
            raise ValueError("an added token holds white space")

    def ids(self, text: str) -> np.ndarray:
        return self.encoding.encode_to_numpy(text, allowed_special="all", disallowed_special=()) if text else np.zeros(0, np.uint32)

    def count(self, text: str) -> int:
        if any(x in text for x in self.added):
            return len(self.ids(text))
        return len(self.plain(text))

    def pieces(self, text: str) -> list[str]:
        """Pieces in order; all but the first are meant with a space before them."""
        parts = text.split(" ")
        if all(p and not p[0].isspace() and not p[-1].isspace() for p in parts):
            return parts
        return CUT.split(text)
