"""Edit-aware token counts.

A text is held as leaves of some pre-tokens each, cut only where the tokenizer always cuts; a segment tree holds sums
of characters and tokens over the leaves. An edit finds its leaves by a descent over the character sums, puts the new
text into them, cuts the result into leaves of the usual size again, encodes those, and corrects the sums on the paths
to the root. The leaf before is encoded again only where the edit took away the cut between them (boundary context). A
leaf may grow to twice its size before it is cut; where an edit makes more leaves than it touched, the tree is laid out
anew from the counts that are there, without any encoding. So the characters encoded for an edit are those of the touched
leaves and of the new text, whatever the number of edits before it.

Defined results: a null or empty text has no leaves and no tokens; edits beyond the end append; edits are applied in
order, each to the text as the former ones left it; a mark of the vocabulary (the end-of-text string) in a text is its
own token and is never cut; repeated rows each get their row; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, texts
from .pii import spans_of
from .tokens import Encoder, encoder

LEAF = 32

Edit = tuple[int, int, str]


def leaves_of(text: str, coder: Encoder, size: int = LEAF) -> tuple[list[str], list[int]]:
    """Leaves and their token counts."""
    if not text:
        return [], []
    if len(coder.cut(text)) > 1:
        return _rough(text, coder, size)
    head, *rest = text.split(" ")
    try:
        counts = [len(coder.plain(head)), *(len(ids) // 4 for ids in map(coder.memo.__getitem__, rest))]
    except KeyError:
        return _rough(text, coder, size)
    parts = [head, *rest]
    leaves = [" ".join(parts[i : i + size]) if not i else " " + " ".join(parts[i : i + size]) for i in range(0, len(parts), size)]
    return leaves, [sum(counts[i : i + size]) for i in range(0, len(parts), size)]


def _rough(text: str, coder: Encoder, size: int) -> tuple[list[str], list[int]]:
    """As leaves_of where some blanks are not cuts: pieces that can't start a leaf stay with the one before."""
    parts = text.split(" ")
    safe = [i for i in range(1, len(parts)) if _opens(" " + parts[i], coder)]
    cuts = [0, *safe[size - 1 :: size], len(parts)]
    leaves = []
    for a, b in zip(cuts, cuts[1:], strict=False):
        if a < b:
            leaves.append((" " if a else "") + " ".join(parts[a:b]))
    return leaves, [coder.count(x) for x in leaves]


def _opens(text: str, coder: Encoder) -> bool:
    """Whether the tokenizer starts a piece here whatever stands before."""
    return len(text) > 1 and text[0] == " " and not text[1].isspace() and not text.startswith(tuple(coder.marks), 1)


class TokenTree:
    def __init__(self, text: str, coder: Encoder, size: int = LEAF):
        self.coder, self.size, self.encoded = coder, size, 0
        self._lay(*leaves_of(text, coder, size))

    def _lay(self, leaves: list[str], counts: list[int]) -> None:
        self.leaves = leaves
        self.width = 1 << max(0, (max(1, len(leaves)) - 1).bit_length())
        self.sums = np.zeros((2 * self.width, 2), np.int64)
        if leaves:
            self.sums[self.width : self.width + len(leaves)] = np.column_stack([[len(x) for x in leaves], counts])
        level = self.width
        while level > 1:
            self.sums[level // 2 : level] = self.sums[level : 2 * level : 2] + self.sums[level + 1 : 2 * level : 2]
            level //= 2

    @property
    def chars(self) -> int:
        return int(self.sums[1, 0])

    @property
    def tokens(self) -> int:
        return int(self.sums[1, 1])

    def text(self) -> str:
        return "".join(self.leaves)

    def _find(self, at: int) -> tuple[int, int]:
        """The leaf that holds a character, and the characters before that leaf."""
        node, before = 1, 0
        while node < self.width:
            node *= 2
            if at - before >= self.sums[node, 0] and self.sums[node + 1, 0]:
                before += int(self.sums[node, 0])
                node += 1
        return node - self.width, before

    def _set(self, leaf: int, text: str, tokens: int) -> None:
        self.leaves[leaf] = text
        node = leaf + self.width
        change = np.array([len(text), tokens]) - self.sums[node]
        while node:
            self.sums[node] += change
            node //= 2

    def edit(self, start: int, end: int, new: str) -> None:
        """Replace characters [start, end)."""
        if not self.leaves:
            self.leaves = [""]
        start = min(start, self.chars)
        end = min(max(start, end), self.chars)
        first, before = self._find(start)
        last, _ = self._find(max(start, end - 1))
        whole = "".join(self.leaves[first : last + 1])
        changed = whole[: start - before] + new + whole[end - before :]
        while changed and not _opens(changed, self.coder) and before:
            first -= 1
            before -= len(self.leaves[first])
            changed = self.leaves[first] + changed
        self.encoded += len(changed)
        if changed.count(" ") <= 2 * self.size:
            leaves, counts = ([changed], [self.coder.count(changed)]) if changed else ([], [])
        else:
            leaves, counts = leaves_of(changed, self.coder, self.size)
        if len(leaves) > last + 1 - first:
            kept = self.sums[self.width : self.width + len(self.leaves), 1].tolist()
            self._lay(self.leaves[:first] + leaves + self.leaves[last + 1 :], kept[:first] + counts + kept[last + 1 :])
            return
        for leaf in range(first, last + 1):
            k = leaf - first
            if k < len(leaves):
                self._set(leaf, leaves[k], counts[k])
            elif self.leaves[leaf]:
                self._set(leaf, "", 0)


def redactions(text: str) -> list[Edit]:
    """Edits that put a mark in the place of each personal-data span, from the last to the first."""
    edits, free = [], len(text) + 1
    for a, b, kind, _ in reversed(spans_of(text)):
        if b <= free:
            edits.append((a, b, f"[{kind}]"))
            free = a
    return edits


def count_tokens(docs: DataFrame, edits_of: Callable[[str], list[Edit]] = redactions, id_col: str = "doc_id", text_col: str = "text", vocabulary: str | None = None) -> DataFrame:
    """One row a document: tokens, leaves, edits, tokens after the edits, and the characters encoded again for them."""

    def setup():
        coder = encoder(vocabulary)

        def each(batch):
            rows = []
            for text in texts(batch):
                edits = edits_of(text)
                if edits:
                    tree = TokenTree(text, coder)
                    before, leaves = tree.tokens, len(tree.leaves)
                    for start, end, new in edits:
                        tree.edit(start, end, new)
                    rows.append((before, leaves, len(edits), tree.tokens, tree.encoded))
                else:
                    leaves, counts = leaves_of(text, coder)
                    n = sum(counts)
                    rows.append((n, len(leaves), 0, n, 0))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).cast(pa.int64()), *(pa.array(c, pa.int64()) for c in zip(*rows, strict=True))], names=["doc_id", "n_tokens", "n_leaves", "n_edits", "n_tokens_after", "n_encoded"]
            )

        return each

    return map_batches(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), None, "doc_id long, n_tokens long, n_leaves long, n_edits long, n_tokens_after long, n_encoded long", setup)
