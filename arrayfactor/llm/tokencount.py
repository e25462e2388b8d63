"""Token counts that follow edits.

A text is cut into pre-tokens by the tokenizer's pattern; leaves of ``LEAF`` pre-tokens hold their part of
the text with its pre-tokens' sizes and token counts, and a segment tree over the leaves carries the sums of
characters and tokens. An edit re-encodes the pre-tokens that it touches with one before them, and goes
on to the first old pre-token boundary after it that the new cut meets: the pattern looks at nothing before
a pre-token and at one character after it, so what follows is unchanged. Only the leaves of that region
are read and changed, and the sums above them; no edit copies the text.

Trees are kept per text in the task that reads it; texts are read once, whole, without a shuffle.
Counts of pre-tokens of up to ``LONGEST`` characters are kept, in bounded memory, as long as the worker process
lives. The vocabulary is read on the driver from a path that is a parameter, and sent to the tasks.

Defined results: null counts as empty text with no tokens; texts of any length are counted whole; an empty table gives an empty result; edits are applied in the order given, each
on the result of the one before, with offsets clipped to the text; repeated rows, ids and extra
columns play no part.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .runtime import table

VOCABULARY = "/opt/tokenizers/byte_bpe_50k.tiktoken"
# fixed value: the pre-token pattern of the vocabulary
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
LEAF = 32
KEPT = 200_000
LONGEST = 64
ROWS = 256  # of a batch that are worked on at once


class Counter:
    """Tokens of a pre-token, by a byte-level merge vocabulary; counts are kept in a bounded memory."""

    def __init__(self, vocabulary: bytes):
        import tiktoken

        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in vocabulary.splitlines() if line)}
        self.coder = tiktoken.Encoding("counted", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.cut = regex.compile(PATTERN)
        self.known: dict[str, int] = {}

    def counts(self, pretokens: list[str]) -> list[int]:
        known = self.known
        if len(known) > KEPT:
            known.clear()
        out = []
        for p in pretokens:
            n = known.get(p)
            if n is None:
                n = len(self.coder._encode_single_piece(p))
                if len(p) <= LONGEST:
                    known[p] = n
            out.append(n)
        return out


_OWN: dict[str, Counter] = {}


def counter_of(vocabulary: bytes) -> Counter:
    """This process's counter for a vocabulary; one vocabulary at a time."""
    name = hashlib.sha256(vocabulary).hexdigest()
    if name not in _OWN:
        _OWN.clear()
        _OWN[name] = Counter(vocabulary)
    return _OWN[name]


class Leaf:
    """A part of the text with its pre-tokens' sizes and token counts."""

    __slots__ = ("text", "sizes", "counts")

    def __init__(self, text: str, sizes: np.ndarray, counts: np.ndarray):
        self.text, self.sizes, self.counts = text, sizes, counts


class CountTree:
    """A text in leaves of pre-tokens and a segment tree of character and token sums."""

    def __init__(self, counter: Counter, text: str):
        self.counter, self.encoded = counter, 0
        self.leaves = self._cut(counter.cut.findall(text))
        self._build()

    def _cut(self, pretokens: list[str]) -> list[Leaf]:
        sizes, counts = np.fromiter(map(len, pretokens), np.int64, len(pretokens)), np.array(self.counter.counts(pretokens), np.int64)
        return [Leaf("".join(pretokens[a : a + LEAF]), sizes[a : a + LEAF], counts[a : a + LEAF]) for a in range(0, len(pretokens), LEAF)] or [Leaf("", sizes, counts)]

    @property
    def text(self) -> str:
        return "".join(leaf.text for leaf in self.leaves)

    @property
    def size(self) -> int:
        return int(self.sums[0, 1])

    def _build(self) -> None:
        self.width = 1 << max(0, (len(self.leaves) - 1).bit_length())
        self.sums = np.zeros((2, 2 * self.width), np.int64)
        self.sums[0, self.width : self.width + len(self.leaves)] = [len(leaf.text) for leaf in self.leaves]
        self.sums[1, self.width : self.width + len(self.leaves)] = [int(leaf.counts.sum()) for leaf in self.leaves]
        width = self.width
        while width > 1:
            width //= 2
            self.sums[:, width : 2 * width] = self.sums[:, 2 * width : 4 * width : 2] + self.sums[:, 2 * width + 1 : 4 * width : 2]

    @property
    def tokens(self) -> int:
        return int(self.sums[1, 1])

    def _set(self, at: int, leaf: Leaf) -> None:
        self.leaves[at] = leaf
        i = self.width + at
        self.sums[:, i] = len(leaf.text), leaf.counts.sum()
        while i > 1:
            i //= 2
            self.sums[:, i] = self.sums[:, 2 * i] + self.sums[:, 2 * i + 1]

    def _leaf_at(self, char: int) -> tuple[int, int]:
        """The leaf that holds a character (the last one for the end) and where it begins."""
        i, begin = 1, 0
        while i < self.width:
            left = int(self.sums[0, 2 * i])
            if char < begin + left or not self.sums[0, 2 * i + 1]:
                i = 2 * i
            else:
                begin += left
                i = 2 * i + 1
        return i - self.width, begin

    def edit(self, start: int, end: int, new: str) -> None:
        """Replace the characters from ``start`` to ``end``."""
        start = min(max(start, 0), self.size)
        end = min(max(end, start), self.size)
        first, begin = self._leaf_at(max(start - 1, 0))
        while first and (k := int(np.searchsorted(np.cumsum(self.leaves[first].sizes), start - begin, side="left"))) < 2:
            first -= 1  # the pre-token before the touched ones is in a leaf before; empty leaves are passed over
            begin -= len(self.leaves[first].text)
        head = self.leaves[first]
        bounds = begin + np.concatenate([[0], np.cumsum(head.sizes)])
        k = max(int(np.searchsorted(bounds, start, side="left")) - 2, 0)  # pre-tokens before this one end clear of the edit
        # the old text from ``begin`` on, leaf after leaf as it is needed, and its pre-tokens' bounds
        last, upto = first, begin + len(head.text)
        parts, ends = [head.text], [bounds[1:]]

        def more() -> bool:
            nonlocal last, upto
            if last + 1 == len(self.leaves):
                return False
            last += 1
            leaf = self.leaves[last]
            parts.append(leaf.text)
            ends.append(upto + np.cumsum(leaf.sizes))
            upto += len(leaf.text)
            return True

        while upto <= end and more():
            pass
        shift = len(new) - (end - start)
        while True:
            old = "".join(parts)
            region = old[: start - begin] + new + old[end - begin :]
            after = np.concatenate(ends)
            kept = set((after[after >= end] + shift - begin).tolist())
            place, sizes = int(bounds[k]) - begin, []
            least = start + len(new) - begin
            whole = last + 1 == len(self.leaves)
            # a cut at the region's end may look at what follows, so it counts only where nothing does
            while place < len(region) and not (place in kept and place >= least and (place < len(region) or whole)):
                m = self.counter.cut.match(region, place)
                sizes.append(m.end() - place)
                place = m.end()
            if whole or (place < len(region) and place in kept and place >= least):
                break
            for _ in range(max(1, last - first)):  # twice as many leaves
                more()
        self.encoded += len(sizes)
        texts, at = [], int(bounds[k]) - begin
        for s in sizes:
            texts.append(region[at : at + s])
            at += s
        counts = np.concatenate([leaf.counts for leaf in self.leaves[first : last + 1]])
        every = np.concatenate([leaf.sizes for leaf in self.leaves[first : last + 1]])
        rest = (after + shift - begin > place) & (after >= end)
        new_sizes = np.concatenate([every[:k], np.array(sizes, np.int64), every[rest]])
        new_counts = np.concatenate([counts[:k], np.array(self.counter.counts(texts), np.int64), counts[rest]])
        if len(new_sizes) > 4 * LEAF or last - first > 64:  # too much in one leaf: cut anew
            at = np.concatenate([[0], np.cumsum(new_sizes)])
            self.leaves[first : last + 1] = [Leaf(region[at[a] : at[min(a + LEAF, len(new_sizes))]], new_sizes[a : a + LEAF], new_counts[a : a + LEAF]) for a in range(0, max(len(new_sizes), 1), LEAF)]
            self._build()
            return
        self._set(first, Leaf(region, new_sizes, new_counts))
        none = np.zeros(0, np.int64)
        for i in range(first + 1, last + 1):
            self._set(i, Leaf("", none, none))


_NUMBER = regex.compile(r"[0-9]{6,}")


def redactions(text: str) -> list[tuple[int, int, str]]:
    """The edits of the registered query: long digit runs give way to a mark, a line is put in front and a line end behind."""
    edits = [(m.start(), m.end(), "<number>") for m in _NUMBER.finditer(text)][::-1]
    return [*edits, (0, 0, "# text\n"), (1 << 62, 1 << 62, "\n")]


def _run(vocabulary, edits_of):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = counter_of(vocabulary.value)
        for batch in (whole.slice(a, ROWS) for whole in batches for a in range(0, whole.num_rows, ROWS)):
            rows: list[list[int]] = [[], [], [], [], []]
            for text in batch.column("text").to_pylist():
                tree = CountTree(counter, text or "")
                before, pretokens = tree.tokens, sum(len(leaf.sizes) for leaf in tree.leaves)
                edits = edits_of(text or "")
                for e in edits:
                    tree.edit(*e)
                for i, v in enumerate((before, pretokens, len(edits), tree.tokens, tree.encoded)):
                    rows[i].append(v)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *[pa.array(r, pa.int64()) for r in rows]], names=["doc_id", "n_tokens", "n_pretokens", "n_edits", "n_tokens_after", "n_reencoded"])

    return run


def counted(docs: DataFrame, edits_of=redactions, vocabulary_path: str = VOCABULARY) -> DataFrame:
    """(doc_id, n_tokens, n_pretokens, n_edits, n_tokens_after, n_reencoded) for every row of ``docs``."""
    vocabulary = docs.sparkSession.sparkContext.broadcast(Path(vocabulary_path).read_bytes())
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_run(vocabulary, edits_of), "doc_id long, n_tokens long, n_pretokens long, n_edits long, n_tokens_after long, n_reencoded long")


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return counted(table(spark, sf_dir, "documents"))
