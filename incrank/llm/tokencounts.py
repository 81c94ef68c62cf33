"""Token counts that follow edits.

A document is a sequence of pre-tokens, each with its token count, under a
segment tree of sums. An edit re-encodes only the pre-tokens it touches and,
before and after them, as much context as may split differently; their leaves
are replaced and the sums above them updated. The count of the whole document
is the root; the count of any span is a sum of a few nodes.
"""

from __future__ import annotations

import os
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .bpe import CACHE_CHARS, CACHE_PIECES
from .common import steps, texts_of


class PieceCounter:
    """Token counts of pre-tokens; remembers those that come again, in two generations."""

    def __init__(self, tokenizer, pattern: str) -> None:
        self.tokenizer, self.pattern, self.seen, self.old, self.chars = tokenizer, regex.compile(pattern), {}, {}, 0

    def split(self, text: str) -> list[str]:
        return self.pattern.findall(text)

    def counts(self, pieces: list[str]) -> list[int]:
        if len(self.seen) > CACHE_PIECES or self.chars > CACHE_CHARS:
            self.old, self.seen, self.chars = self.seen, {}, 0
        try:
            return list(map(self.seen.__getitem__, pieces))
        except KeyError:
            unknown = []
            for p in dict.fromkeys(pieces):
                if p not in self.seen:
                    self.chars += len(p)
                    if (n := self.old.get(p)) is None:
                        unknown.append(p)
                    else:
                        self.seen[p] = n
            for p, got in zip(unknown, self.tokenizer.encode_batch_fast(unknown, add_special_tokens=False), strict=True):
                self.seen[p] = len(got)
        return list(map(self.seen.__getitem__, pieces))


@lru_cache(maxsize=2)
def counter(path: str, pattern: str) -> PieceCounter:
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    tokenizer.encode_special_tokens = True
    return PieceCounter(tokenizer, pattern)


#: Pre-tokens of one leaf. Edits inside a leaf cost a pass over it; the tree above stays small.
LEAF = 64


class SegmentTree:
    """Sums over leaves, by levels of pairs. Replacing leaves updates only the nodes above them unless their number changes."""

    def __init__(self, leaves: np.ndarray) -> None:
        self.levels = [np.asarray(leaves, np.int64)]
        while len(self.levels[-1]) > 1:
            below = self.levels[-1]
            self.levels.append(np.add.reduceat(below, np.arange(0, len(below), 2)))

    @property
    def total(self) -> int:
        return int(self.levels[-1][0]) if len(self.levels[-1]) else 0

    def replace(self, at: int, value: int) -> int:
        """Set one leaf; returns how many nodes were updated."""
        change = value - int(self.levels[0][at])
        for level in self.levels:
            level[at] += change
            at >>= 1
        return len(self.levels)

    def before(self, end: int) -> int:
        """Sum of the leaves before ``end``: one node of each level at most."""
        total = 0
        for level in self.levels:
            if end & 1:
                total += int(level[end - 1])
            end >>= 1
        return total


class CountedText:
    """A document whose token count follows edits of character ranges."""

    def __init__(self, text: str, counts: PieceCounter) -> None:
        self.source = counts
        pieces = counts.split(text)
        sizes = counts.counts(pieces)
        self.leaves = [[pieces[k : k + LEAF], sizes[k : k + LEAF]] for k in range(0, len(pieces), LEAF)] or [[[], []]]
        self._grow()
        self.reencoded = self.updated = 0

    def _grow(self) -> None:
        self.tokens = SegmentTree([sum(s) for _, s in self.leaves])
        self.chars = SegmentTree([sum(map(len, p)) for p, _ in self.leaves])
        self.pieces = SegmentTree([len(p) for p, _ in self.leaves])

    @property
    def n_tokens(self) -> int:
        return self.tokens.total

    @property
    def n_pieces(self) -> int:
        return self.pieces.total

    @property
    def text(self) -> str:
        return "".join(p for ps, _ in self.leaves for p in ps)

    def _leaf_at(self, char: int) -> tuple[int, int]:
        """The leaf that holds a character, and the first character of that leaf: down the tree of lengths."""
        k, start, levels = 0, 0, self.chars.levels
        for level in reversed(levels[:-1]):
            k <<= 1
            if k + 1 < len(level) and char >= start + int(level[k]):
                start += int(level[k])
                k += 1
        return k, start

    def _flat(self, leaf: int, step: int):
        """(leaf, index in leaf) of pre-tokens from a leaf on, in either direction."""
        while 0 <= leaf < len(self.leaves):
            n = len(self.leaves[leaf][0])
            for i in range(n) if step > 0 else range(n - 1, -1, -1):
                yield leaf, i
            leaf += step

    def edit(self, start: int, end: int, new: str) -> None:
        """Replace characters start..end by ``new``.

        The region begins two pre-tokens before the edit. To its right it is
        split again until a boundary coincides with an old one, from where on
        the old pre-tokens hold: what a pre-token is depends on no text more than one
        character before it and the white space after it, so old and new
        must agree on a boundary that follows a character that is no space.
        """
        total = self.chars.total
        start, end = max(0, min(start, total)), max(0, min(end, total))
        end = max(start, end)
        # left: the first pre-token of the region
        leaf, at = self._leaf_at(min(start, max(total - 1, 0)))
        i = 0
        for i, p in enumerate(self.leaves[leaf][0]):
            if at + len(p) > start:
                break
            at += len(p)
        else:
            i = len(self.leaves[leaf][0])
        back = 2
        while back and (i > 0 or leaf > 0):
            if i == 0:
                leaf -= 1
                i = len(self.leaves[leaf][0])
                continue
            i -= 1
            at -= len(self.leaves[leaf][0][i])
            if not self.leaves[leaf][0][i].isspace():
                back -= 1
        first_leaf, first, left_at = leaf, i, at
        # right: take in whole pre-tokens until the new split meets an old boundary
        taken, wide = [], 8
        stream = ((b, j) for b, j in self._flat(leaf, 1) if b > first_leaf or j >= first)
        closed, length = False, 0
        last_leaf, last = leaf, i
        while True:
            grew = False
            for b, j in stream:
                p = self.leaves[b][0][j]
                taken.append(p)
                length += len(p)
                last_leaf, last, grew = b, j + 1, True
                if left_at + length >= end and (wide := wide - 1) <= 0:
                    break
            closed = not grew or left_at + length >= total
            old = "".join(taken)
            fresh = old[: start - left_at] + new + old[end - left_at :]
            pieces = self.source.split(fresh)
            if closed:
                keep_old = 0
                break
            # boundaries counted from the right end, which edits do not move
            old_ends, run = {}, 0
            for n, p in enumerate(reversed(taken)):
                if left_at + length - run <= end:
                    break
                old_ends[run] = n
                run += len(p)
            run, keep_old = 0, None
            for n, p in enumerate(reversed(pieces)):
                # the last two pieces may still change with what follows
                if n >= 2 and run in old_ends and old_ends[run] >= 2 and not p[-1].isspace() and run <= len(fresh) - (start - left_at) - len(new):
                    keep_old = (old_ends[run], n)
                    break
                run += len(p)
            if keep_old:
                old_tail, new_tail = keep_old
                for _ in range(old_tail):
                    if last == 0:
                        last_leaf -= 1
                        last = len(self.leaves[last_leaf][0])
                    last -= 1
                while last == 0 and last_leaf > first_leaf:
                    last_leaf -= 1
                    last = len(self.leaves[last_leaf][0])
                pieces = pieces[: len(pieces) - new_tail]
                break
            wide = max(8, len(taken))
        sizes = self.source.counts(pieces)
        self.reencoded += len(pieces)
        before, after = self.leaves[first_leaf], self.leaves[last_leaf]
        merged = [before[0][:first] + pieces + after[0][last:], before[1][:first] + sizes + after[1][last:]]
        if first_leaf == last_leaf and len(merged[0]) <= 2 * LEAF:
            self.leaves[first_leaf] = merged
            self.updated += self.tokens.replace(first_leaf, sum(merged[1]))
            self.chars.replace(first_leaf, sum(map(len, merged[0])))
            self.pieces.replace(first_leaf, len(merged[0]))
        else:
            split = [[merged[0][k : k + LEAF], merged[1][k : k + LEAF]] for k in range(0, len(merged[0]), LEAF)]
            self.leaves[first_leaf : last_leaf + 1] = split or ([] if len(self.leaves) > last_leaf - first_leaf + 1 else [[[], []]])
            self._grow()
            self.updated += 2 * len(self.leaves)


def planned_edits(text: str) -> list[tuple[int, int, str]]:
    """Three edits of a text that its checksum determines: a deletion, an insertion and a replacement, in the order they apply."""
    x, n = zlib.crc32(text.encode()), len(text)
    cut = x % (n + 1)
    end = min(n, cut + 1 + x % 37)
    n -= end - cut
    word = text[:11] + " edited" + str(x % 1000)
    into = (x >> 8) % (n + 1)
    n += len(word)
    swap = (x >> 16) % (n + 1)
    return [(cut, end, ""), (into, into, word), (swap, min(n, swap + 5), "'s  \n" if x & 1 else "don't 12")]


def apply_edit(text: str, start: int, end: int, new: str) -> str:
    return text[:start] + new + text[end:]


def edited_counts(docs: DataFrame, tokenizer_path: str, pattern: str, edits=planned_edits) -> DataFrame:
    """Token counts before and after each document's edits.

    doc_id, n_pieces, n_tokens: of the text; edits: how many; edited_pieces, edited_tokens: after them;
    reencoded: pre-tokens encoded again for all edits; tree_updates: nodes of the tree of token sums that changed;
    edited_crc32: of the edited text. Null text counts as empty; other columns are ignored.
    """
    names = ["doc_id", "n_pieces", "n_tokens", "edits", "edited_pieces", "edited_tokens", "reencoded", "tree_updates", "edited_crc32"]

    def kernel(batches):
        source = counter(tokenizer_path, pattern)
        for batch in steps(batches):
            rows = []
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                doc, todo = CountedText(text, source), edits(text)
                was = doc.n_pieces, doc.n_tokens
                for e in todo:
                    doc.edit(*e)
                rows.append((key, *was, len(todo), doc.n_pieces, doc.n_tokens, doc.reencoded, doc.updated, zlib.crc32(doc.text.encode())))
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], names)

    return texts_of(docs).mapInArrow(kernel, ", ".join(f"{n} bigint" for n in names))
