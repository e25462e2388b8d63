"""Benchmark decontamination by suffix arrays over the training text.

Training rows are cut into shards of consecutive texts. Each shard's words become numbers in the
benchmark's vocabulary, and a sparse suffix array is built over every position from which a
benchmark window could start, i.e. where at least as many words in a row are in that vocabulary
as the shortest window has. Each benchmark suffix is then binary-searched in the array: the
matching suffixes are one interval, whose entries are the verbatim occurrences and their places.
Neighbouring occurrences on one diagonal join to longest matches.

Suffixes are compared to the depth of a window, which is what decides a hit.

The training table is read once and never shuffled. The benchmark is the query side: tasks build
it into blocks of at most ``block_bytes`` of text (about eight times that when built; an item longer
than that is a block of its own), which are written to the shared folder. The driver holds one block at a
time and sends it to the executors, one pass over the training table for each; the blocks' results
are merged per row.

Defined results: a null or empty text has no words, no hits and is not contaminated; an item
without words has no window; an item with a null id hits like any other and counts as one item, but its
id is left out of the digest; rows that repeat an item's id count once; repeated rows and ties are judged each by itself; extra columns are
ignored; an empty benchmark hits nothing.
"""

from __future__ import annotations

import hashlib
import pickle
from collections.abc import Iterator
from functools import cached_property, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .runtime import BROADCAST_ROWS, materialise, table
from .textcore import U64, chunks, find_words

WINDOW = 13
SHARD_WORDS = 1 << 18
BLOCK_BYTES = 4 << 20

MATCHES = "row_id long, doc_id long, n_words long, starts array<int>, lengths array<int>, items array<long>, item_starts array<int>"
VERDICT = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean"


class QueryBlock:
    """Distinct windows of some benchmark items as sortable keys over the items' vocabulary, with where they come from."""

    def __init__(self, item_ids: list[int | None], texts: list[str | None], window: int = WINDOW):
        hashes, ptr = [np.zeros(0, U64)], [0]
        for _, _, buf, offs in chunks(pa.array(texts, pa.large_string())):
            w = find_words(buf, offs, "alnum")
            hashes.append(w.hash)
            ptr += (ptr[-1] + w.ptr[1:]).tolist()
        words, at = np.concatenate(hashes), np.array(ptr, np.int64)
        self.item_ids = list(item_ids)
        self.vocabulary, ids = np.unique(words, return_inverse=True)
        self.bits = max(1, int(len(self.vocabulary) + 1).bit_length())
        self.per_key = 63 // self.bits
        self.keys = -(-window // self.per_key)
        count = np.diff(at)
        size = np.minimum(count, window)
        each = np.where(count > 0, count - size + 1, 0)  # windows of each item
        item = np.repeat(np.arange(len(count)), each)
        start = np.arange(len(item)) - np.repeat(np.cumsum(each) - each, each)
        low = np.zeros((len(item), 8 * self.keys), np.uint8)
        for a in range(0, len(item), 1 << 16):
            part = slice(a, a + (1 << 16))
            place = (at[item[part]] + start[part])[:, None] + np.arange(self.keys * self.per_key)
            inside = np.arange(self.keys * self.per_key) < size[item[part]][:, None]
            low[part] = self.pack(np.where(inside, ids[np.minimum(place, len(ids) - 1)] + 1, 0))
        _, first, which = np.unique(_as_bytes(low), return_index=True, return_inverse=True)
        order = np.argsort(which, kind="stable")
        self.low, self.sizes = low[first], size[item[first]]
        self.shortest = int(self.sizes.min()) if len(self.sizes) else 0
        self.bounds = np.searchsorted(which[order], np.arange(len(first) + 1))
        self.items, self.starts = item[order].astype(np.int32), start[order].astype(np.int32)

    @cached_property
    def ranges(self) -> tuple[np.ndarray, np.ndarray]:
        """The smallest and the largest key that begin with each window, comparable; worked out where they are used."""
        masks = np.zeros((self.keys * self.per_key + 1, self.keys * self.per_key), np.int64)
        for n in range(len(masks)):
            masks[n, n:] = (1 << self.bits) - 1
        return _as_bytes(self.low), _as_bytes(self.low | self.pack(masks)[self.sizes])

    def origins(self, which: int) -> list[tuple[int | None, int]]:
        """(item id, first word) of every item place that has a window."""
        own = slice(self.bounds[which], self.bounds[which + 1])
        return [(self.item_ids[i], a) for i, a in zip(self.items[own].tolist(), self.starts[own].tolist(), strict=True)]

    def pack(self, ids: np.ndarray) -> np.ndarray:
        """Rows of word numbers to byte strings in the same order."""
        out = np.zeros((len(ids), self.keys), np.uint64)
        for k in range(self.keys):
            for j in range(self.per_key):
                out[:, k] = (out[:, k] << np.uint64(self.bits)) | ids[:, k * self.per_key + j].astype(np.uint64)
        return np.ascontiguousarray(out.astype(">u8")).view(np.uint8).reshape(len(ids), 8 * self.keys)


def _as_bytes(rows: np.ndarray) -> np.ndarray:
    """Byte rows as one comparable column; a closing byte keeps trailing zeros significant."""
    closed = np.ones((len(rows), rows.shape[1] + 1), np.uint8)
    closed[:, :-1] = rows
    return closed.view(f"S{closed.shape[1]}").ravel()


class Shard:
    """Consecutive texts and the sparse suffix array over their words."""

    def __init__(self, block: QueryBlock, words: np.ndarray, ptr: np.ndarray):
        self.block, self.ptr = block, ptr
        vocabulary = block.vocabulary
        at = np.minimum(np.searchsorted(vocabulary, words), max(len(vocabulary) - 1, 0))
        ids = np.where(vocabulary[at] == words, at + 1, 0) if len(vocabulary) else np.zeros(len(words), np.int64)
        stop = np.zeros(len(ids) + 1, bool)
        stop[:-1] = ids == 0
        stop[ptr] = True  # each text ends what the one before it began
        stops = np.flatnonzero(stop)
        upto = stops[np.searchsorted(stops, np.arange(len(ids)), side="right")] if len(ids) else stops[:0]
        starts = np.flatnonzero((ids > 0) & (upto - np.arange(len(ids)) >= block.shortest)) if block.shortest else np.zeros(0, np.int64)
        depth = block.keys * block.per_key
        padded = np.concatenate([ids, np.zeros(depth, ids.dtype)])
        rows = np.zeros((len(starts), depth), np.int64)
        left = upto[starts] - starts
        for k in range(depth):
            rows[:, k] = np.where(left > k, padded[starts + k], 0)
        keys = _as_bytes(block.pack(rows)) if len(starts) else np.zeros(0, "S1")
        order = np.argsort(keys, kind="stable")
        self.suffixes, self.keys = starts[order], keys[order]

    def occurrences(self) -> tuple[np.ndarray, np.ndarray]:
        """(word position, window number) of every verbatim occurrence of every window."""
        b = self.block
        if not len(b.sizes) or not len(self.keys):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        lo = np.searchsorted(self.keys, b.ranges[0], side="left")
        hi = np.searchsorted(self.keys, b.ranges[1], side="right")
        n = np.maximum(hi - lo, 0)
        which = np.repeat(np.arange(len(n)), n)
        at = np.repeat(lo, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        return self.suffixes[at], which


def _digest(items) -> str:
    return hashlib.sha256(",".join(sorted(str(i) for i in items if i is not None)).encode()).hexdigest()


def _shards(batches: Iterator[pa.RecordBatch], shard_words: int) -> Iterator[tuple[list, np.ndarray, np.ndarray]]:
    """(row numbers and ids, word hashes, text bounds) of consecutive texts of about shard_words words."""
    rows, parts, counts, size = [], [], [], 0
    for batch in batches:
        ids = list(zip(*(batch.column(c).to_pylist() for c in range(batch.num_columns - 1)), strict=True))
        for lo, hi, buf, offs in chunks(batch.column(batch.num_columns - 1)):
            w = find_words(buf, offs, "alnum")
            rows += ids[lo:hi]
            parts.append(w.hash)
            counts.append(w.count)
            size += len(w.hash)
            if size >= shard_words:
                yield rows, np.concatenate(parts), np.concatenate([[0], np.cumsum(np.concatenate(counts))])
                rows, parts, counts, size = [], [], [], 0
    if rows:
        yield rows, np.concatenate(parts), np.concatenate([[0], np.cumsum(np.concatenate(counts))])


def _pairs(shard: Shard, where: np.ndarray, which: np.ndarray) -> tuple[np.ndarray, list[int], list[int]]:
    """Occurrences with the items and item positions of their windows: (occurrence, item, item start)."""
    index, items, starts = [], [], []
    for k, w in enumerate(which):
        for item, at in shard.block.origins(w):
            index.append(k)
            items.append(item)
            starts.append(at)
    return np.array(index, np.int64), items, starts


def _verdicts(block, shard_words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = block.value
        none = _digest([])
        for rows, words, ptr in _shards(batches, shard_words):
            shard = Shard(own, words, ptr)
            where, which = shard.occurrences()
            marks = np.zeros(len(words) + 1, np.int64)
            np.add.at(marks, where, 1)
            np.add.at(marks, where + own.sizes[which], -1)
            hit = np.concatenate([[0], np.cumsum(np.cumsum(marks[:-1]) > 0)])
            n_hit = hit[ptr[1:]] - hit[ptr[:-1]]
            doc = np.searchsorted(ptr, where, side="right") - 1
            found: dict[int, set[int | None]] = {}
            for d, w in np.unique(np.stack([doc, which], 1), axis=0) if len(doc) else ():
                found.setdefault(int(d), set()).update(i for i, _ in own.origins(w))
            n_words = np.diff(ptr)
            digests = [_digest(found[d]) if d in found else none for d in range(len(rows))]
            yield pa.RecordBatch.from_arrays(
                [pa.array([r[0] for r in rows], pa.int64()), pa.array(n_words, pa.int64()), pa.array(n_hit, pa.int64()), pa.array([len(found.get(d, ())) for d in range(len(rows))], pa.int64()), pa.array(digests), pa.array((n_hit > 0) & (20 * n_hit >= n_words))],
                names=["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"],
            )

    return run


def _matches(block, shard_words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = block.value
        for rows, words, ptr in _shards(batches, shard_words):
            shard = Shard(own, words, ptr)
            where, which = shard.occurrences()
            out: list[list] = [[], [], [], []]
            index, items, item_starts = _pairs(shard, where, which)
            doc = np.searchsorted(ptr, where, side="right") - 1
            runs: dict[int, list[tuple[int, int, int, int]]] = {}
            by_diagonal = sorted(zip(doc[index].tolist(), items, (where[index] - np.array(item_starts, np.int64)).tolist(), where[index].tolist(), own.sizes[which[index]].tolist(), item_starts, strict=True), key=lambda x: (x[0], x[1] is None, x[1] or 0, *x[2:])) if len(index) else []
            last = None
            for d, item, diagonal, at, size, i_at in by_diagonal:
                if last and last[:3] == (d, item, diagonal) and at <= runs[d][-1][0] + runs[d][-1][1]:
                    s, _, i, a = runs[d][-1]
                    runs[d][-1] = (s, at + size - s, i, a)
                else:
                    runs.setdefault(d, []).append((at, size, item, i_at))
                last = (d, item, diagonal)
            for d in range(len(rows)):
                own_runs = sorted(((s - int(ptr[d]), n, i, a) for s, n, i, a in runs.get(d, [])), key=lambda x: (*x[:2], x[2] is None, x[2] or 0, x[3]))
                for k in range(4):
                    out[k].append([x[k] for x in own_runs])
            yield pa.RecordBatch.from_arrays(
                [pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()), pa.array(np.diff(ptr), pa.int64()), pa.array(out[0], pa.list_(pa.int32())), pa.array(out[1], pa.list_(pa.int32())), pa.array(out[2], pa.list_(pa.int64())), pa.array(out[3], pa.list_(pa.int32()))],
                names=["row_id", "doc_id", "n_words", "starts", "lengths", "items", "item_starts"],
            )

    return run


def _build(block_bytes: int, window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def block() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([pickle.dumps(QueryBlock(ids, texts, window))], pa.large_binary()).cast(pa.binary())], names=["block"])

        ids, texts, size = [], [], 0
        for batch in batches:
            for item, value in zip(batch.column("item_id").to_pylist(), batch.column("text"), strict=True):
                text = value.as_py() or ""
                if ids and size + len(text) > block_bytes:
                    yield block()
                    ids, texts, size = [], [], 0
                ids.append(item)
                texts.append(text)
                size += len(text)
        if ids:
            yield block()

    return run


def query_blocks(benchmark: DataFrame, block_bytes: int = BLOCK_BYTES, window: int = WINDOW) -> DataFrame:
    """(block): the benchmark in blocks of at most about ``block_bytes`` of text (or one longer item), built in tasks."""
    total = benchmark.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), "text").repartition(max(1, -(-total // block_bytes)))
    return materialise(items.mapInArrow(_build(block_bytes, window), "block binary"), "blocks")


def _sent(spark: SparkSession, blocks: DataFrame) -> Iterator:
    """The blocks as broadcast variables, one after another; the driver holds one at a time."""
    for row in blocks.toLocalIterator():
        yield spark.sparkContext.broadcast(pickle.loads(row.block))


def _found(numbered: DataFrame, blocks: DataFrame, shard_words: int) -> DataFrame:
    """The matches of all rows of ``numbered`` (row_id, doc_id, text), one row for each and block."""
    parts = []
    for block in _sent(numbered.sparkSession, blocks):
        parts.append(materialise(numbered.mapInArrow(_matches(block, shard_words), MATCHES), "matches"))
        block.unpersist()
    return reduce(DataFrame.unionByName, parts)


def longest_matches(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, shard_words: int = SHARD_WORDS, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Longest verbatim matches of at least a window: (doc_id, word_start, n_words, item_id, item_start)."""
    numbered = docs.select(F.lit(0).cast("long").alias("row_id"), F.col("doc_id").cast("long").alias("doc_id"), "text")
    found = _found(numbered, query_blocks(benchmark, block_bytes, window), shard_words)
    found = found.select("doc_id", F.explode(F.arrays_zip("starts", "lengths", "items", "item_starts")).alias("m"))
    return found.select("doc_id", F.col("m.starts").alias("word_start"), F.col("m.lengths").alias("n_words"), F.col("m.items").alias("item_id"), F.col("m.item_starts").alias("item_start"))


def _merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out = []
        for r in batch.to_pylist():
            hit, upto = 0, 0
            for a, n in sorted(zip((x for s in r["starts"] for x in s), (x for s in r["lengths"] for x in s), strict=True)):
                hit += max(0, a + n - max(a, upto))
                upto = max(upto, a + n)
            items = {x for s in r["items"] for x in s}
            out.append({"row_id": r["row_id"], "doc_id": r["doc_id"], "n_words": r["n_words"], "n_hit": hit, "n_items": len(items), "items_sha256": _digest(items), "contaminated": hit > 0 and 20 * hit >= r["n_words"]})
        yield pa.RecordBatch.from_pylist(out, pa.schema([("row_id", pa.int64()), ("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("n_items", pa.int64()), ("items_sha256", pa.string()), ("contaminated", pa.bool_())]))


def _by_blocks(numbered: DataFrame, blocks: DataFrame, shard_words: int) -> DataFrame:
    """Verdicts with their row numbers where the benchmark is more than one block."""
    every = _found(numbered, blocks, shard_words)
    gathered = every.groupBy("row_id").agg(F.first("doc_id").alias("doc_id"), F.first("n_words").alias("n_words"), *[F.collect_list(c).alias(c) for c in ("starts", "lengths", "items")])
    return gathered.mapInArrow(_merged, f"row_id long, {VERDICT}")


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, shard_words: int = SHARD_WORDS, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """One row per row of ``docs``: words, words inside benchmark windows, items, verdict."""
    spark = docs.sparkSession
    blocks = query_blocks(benchmark, block_bytes, window)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    n = blocks.count()
    if n <= 1:
        block = next(_sent(spark, blocks)) if n else spark.sparkContext.broadcast(QueryBlock([], [], window))
        return texts.mapInArrow(_verdicts(block, shard_words), VERDICT)
    numbered = materialise(texts.select(F.monotonically_increasing_id().alias("row_id"), "doc_id", "text"), "numbered")
    return _by_blocks(numbered, blocks, shard_words).drop("row_id")


def _clean(block):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = block.value
        for batch in batches:
            keep = np.ones(batch.num_rows, bool)
            for lo, hi, buf, offs in chunks(batch.column("text")):
                w = find_words(buf, offs, "alnum")
                marks = np.zeros(len(w.hash) + 1, np.int64)
                where, which = Shard(own, w.hash, w.ptr).occurrences()
                np.add.at(marks, where, 1)
                np.add.at(marks, where + own.sizes[which], -1)
                hit = np.concatenate([[0], np.cumsum(np.cumsum(marks[:-1]) > 0)])
                n_hit = hit[w.ptr[1:]] - hit[w.ptr[:-1]]
                keep[lo:hi] = (n_hit == 0) | (20 * n_hit < w.count)
            yield batch.filter(pa.array(keep))

    return run


def clean(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The rows of ``docs``, all columns, that are not contaminated; with one block each batch is one shard."""
    spark = docs.sparkSession
    blocks = query_blocks(benchmark, block_bytes, window)
    n = blocks.count()
    if n == 0:
        return docs
    if n == 1:
        return docs.mapInArrow(_clean(next(_sent(spark, blocks))), docs.schema)
    own = materialise(docs.select(F.monotonically_increasing_id().alias("corpus_row_number"), F.struct(*[docs[c] for c in docs.columns]).alias("kept_row")), "numbered")
    numbered = own.select(F.col("corpus_row_number").alias("row_id"), F.col("kept_row.doc_id").cast("long").alias("doc_id"), F.col("kept_row.text").alias("text"))
    gone = materialise(_by_blocks(numbered, blocks, SHARD_WORDS).filter("contaminated").select(F.col("row_id").alias("corpus_row_number")), "gone")
    side = F.broadcast(gone) if gone.count() <= BROADCAST_ROWS else gone
    return own.join(side, "corpus_row_number", "left_anti").select("kept_row.*")


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def _words_sql(text: str) -> str:
    return rf"list_filter(regexp_split_to_array(translate(coalesce({text}, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '')"


ORACLE = f"""
WITH d AS (SELECT doc_id, {_words_sql('text')} AS w FROM documents),
b AS (SELECT item_id, {_words_sql('text')} AS w FROM benchmark),
bw AS (SELECT item_id, n, unnest(list_transform(range(1, len(w) - n + 2), lambda i: array_to_string(w[i:i + n - 1], ' '))) AS win
       FROM (SELECT item_id, w, least(13, len(w)) AS n FROM b WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT doc_id, n, unnest(range(1, len(w) - n + 2)) AS i, unnest(list_transform(range(1, len(w) - n + 2), lambda i: array_to_string(w[i:i + n - 1], ' '))) AS win
       FROM d, sizes WHERE len(w) >= n),
m AS (SELECT dw.doc_id, dw.i, dw.n, bw.item_id FROM dw JOIN bw USING (n, win)),
h AS (SELECT doc_id, count(DISTINCT p)::BIGINT AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM (SELECT DISTINCT doc_id, i, n FROM m)) GROUP BY doc_id),
t AS (SELECT doc_id, count(*)::BIGINT AS n_items, string_agg(s, ',' ORDER BY s) AS items FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS s FROM m) GROUP BY doc_id)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(h.n_hit, 0) AS n_hit, coalesce(t.n_items, 0) AS n_items,
  sha256(coalesce(t.items, '')) AS items_sha256, coalesce(h.n_hit, 0) > 0 AND 20 * coalesce(h.n_hit, 0) >= len(d.w) AS contaminated
FROM d LEFT JOIN h USING (doc_id) LEFT JOIN t USING (doc_id)
"""
