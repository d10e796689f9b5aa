"""Edit-aware token counts: a segment tree of pre-token leaves for each document.

A leaf is a run of pieces that encode on their own (see ``tokens``); the tree is an
implicit binary heap of token and character sums. An edit is located by character
sums, the leaves it touches and one on either side are encoded anew, and only the
sums above them change. The neighbours make it exact: the cuts at their outer ends
stand between unedited characters, so the pre-tokenizer still stops there.

Defined cases: null text is empty (0 tokens); null or empty edits change nothing; an
edit beyond the end is clipped to the text; overlapping edits are applied from the last
to the first, each on what the later ones left; other columns are ignored.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.llm.common import arrow_rows, slices
from vecspark.llm.tokens import PieceTokenizer

LEAF_PIECES = 64
EDIT = "struct<position:bigint,removed:bigint,inserted:string>"


class TokenTree:
    """Sums of tokens and characters over leaves; node i has children 2i and 2i + 1, the root is 1."""

    def __init__(self, tokens: list[int], chars: list[int]):
        self.tokens, self.chars, self.width = tokens, chars, len(tokens) // 2

    @classmethod
    def of_leaves(cls, tokens: list[int], chars: list[int]) -> TokenTree:
        width = 1
        while width < max(1, len(tokens)):
            width *= 2
        pad = [0] * (width - len(tokens))
        tree = cls([0] * width + tokens + pad, [0] * width + chars + pad)
        for i in range(width - 1, 0, -1):
            tree.pull(i)
        return tree

    def pull(self, i: int) -> None:
        self.tokens[i] = self.tokens[2 * i] + self.tokens[2 * i + 1]
        self.chars[i] = self.chars[2 * i] + self.chars[2 * i + 1]

    @property
    def total(self) -> int:
        return self.tokens[1]

    def leaf_at(self, position: int) -> tuple[int, int]:
        """The leaf that holds a character position (the last one beyond the end), and where it starts."""
        i, start = 1, 0
        position = min(position, max(0, self.chars[1] - 1))
        while i < self.width:
            i *= 2
            if position - start >= self.chars[i]:
                start += self.chars[i]
                i += 1
        return i - self.width, start

    def replace(self, first: int, tokens: list[int], chars: list[int]) -> None:
        """New values of consecutive leaves; only their ancestors are summed again."""
        for k, (t, c) in enumerate(zip(tokens, chars, strict=True)):
            self.tokens[self.width + first + k], self.chars[self.width + first + k] = t, c
        low, high = (self.width + first) // 2, (self.width + first + len(tokens) - 1) // 2
        while low >= 1:
            for i in range(low, high + 1):
                self.pull(i)
            low, high = low // 2, high // 2


def leaves(tokenizer: PieceTokenizer, text: str, number: int | None = None, lead: bool = False) -> tuple[list[int], list[int]]:
    """Token and character sums of a text's leaves: ``number`` of them, or one per LEAF_PIECES pieces.

    ``lead``: a space stands before the text.
    """
    pieces = tokenizer.pieces(text) if text else []
    size = -(-len(pieces) // number) if number else LEAF_PIECES
    tokens, chars = [], []
    for at in range(0, len(pieces), max(1, size)):
        part = " ".join(pieces[at : at + size])
        part = " " + part if at or lead else part
        tokens.append(tokenizer.count(part))
        chars.append(len(part))
    if number:
        tokens += [0] * (number - len(tokens))
        chars += [0] * (number - len(chars))
    return tokens, chars


def build(tokenizer: PieceTokenizer, text: str) -> TokenTree:
    return TokenTree.of_leaves(*leaves(tokenizer, text))


def apply_edit(tokenizer: PieceTokenizer, tree: TokenTree, text: str, position: int, removed: int, inserted: str) -> tuple[TokenTree, str, int]:
    """The tree and text after an edit, and how many characters were encoded."""
    position = max(0, min(position, len(text)))
    end = max(position, min(len(text), position + removed))
    first, begin = tree.leaf_at(position)
    last, start = tree.leaf_at(max(position, end - 1))
    if first > 0:
        first -= 1
        begin -= tree.chars[tree.width + first]
    stop = start + tree.chars[tree.width + last]
    while last + 1 < tree.width:  # one leaf more that has text
        last += 1
        stop += tree.chars[tree.width + last]
        if tree.chars[tree.width + last]:
            break
    while first > 0 and not tree.chars[tree.width + first]:
        first -= 1
        begin -= tree.chars[tree.width + first]
    region = text[begin:position] + inserted + text[end:stop]
    edited = text[:position] + inserted + text[end:]
    lead = begin > 0 and region[:1] == " "  # leaves but the first begin with their space
    inner = region[lead:]
    number = last - first + 1
    if inner.count(" ") > 4 * LEAF_PIECES * number:
        return build(tokenizer, edited), edited, len(edited)
    tokens, chars = leaves(tokenizer, inner, number, lead)
    tree.replace(first, tokens, chars)
    return tree, edited, len(region)


TREES = "doc_id long, text string, tokens array<int>, chars array<int>"


def _build(path: str | None):
    schema = pa.schema([("doc_id", pa.int64()), ("text", pa.string()), ("tokens", pa.list_(pa.int32())), ("chars", pa.list_(pa.int32()))])

    def make():
        tokenizer = PieceTokenizer(path, added=True)

        def each(batch: pa.RecordBatch):
            for part in slices(batch):
                trees = [build(tokenizer, t or "") for t in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array([t.tokens for t in trees], schema.field(2).type), pa.array([t.chars for t in trees], schema.field(3).type)], schema=schema)

        return each

    return make


def token_trees(documents: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """(doc_id, text) -> the same with the arrays of a tree; map-only. ``tokens[1]`` is the count."""
    return arrow_rows(documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), _build(vocabulary), TREES)


COUNTS = "doc_id long, n_tokens long, edited_tokens long, edited_chars long, reencoded_chars long, leaves long"


def _edit(path: str | None):
    names = [c.split()[0] for c in COUNTS.split(", ")]
    schema = pa.schema([(n, pa.int64()) for n in names])

    def make():
        tokenizer = PieceTokenizer(path, added=True)

        def each(batch: pa.RecordBatch):
            for part in slices(batch):
                rows = []
                for doc_id, text, tokens, chars, edits in zip(*(part[n].to_pylist() for n in ("doc_id", "text", "tokens", "chars", "edits")), strict=True):
                    tree, text, encoded = TokenTree(tokens, chars), text or "", 0
                    before, n_leaves = tree.total, sum(1 for c in chars[len(chars) // 2 :] if c)
                    for e in sorted(edits or (), key=lambda e: -(e["position"] or 0)):
                        tree, text, n = apply_edit(tokenizer, tree, text, e["position"] or 0, e["removed"] or 0, e["inserted"] or "")
                        encoded += n
                    rows.append((doc_id, before, tree.total, len(text), encoded, n_leaves))
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], schema=schema)

        return each

    return make


def edited_counts(trees: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """(doc_id, text, tokens, chars, edits array<struct>) -> counts before and after the edits; map-only."""
    return arrow_rows(trees.select("doc_id", "text", "tokens", "chars", F.col("edits").cast(f"array<{EDIT}>").alias("edits")), _edit(vocabulary), COUNTS)
