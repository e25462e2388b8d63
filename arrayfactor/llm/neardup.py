"""Near-duplicate groups by an LSH forest over MinHash signatures.

Each text becomes the set of its distinct shingles and a signature of minima under
``TREES * STEP`` hash functions. Tree t orders all texts by the signature rotated to its own first
hash; texts that agree on a longer prefix stand closer together.

1. Texts with equal sets are one node (verified by size and two independent sums over the set).
2. Neighbours: in each sorted order, a node and the next one after it are a candidate if their
   common prefix is at least ``STEP`` hashes. Of its neighbours over all trees each node keeps the
   ones with the longest prefixes in total. Since the sort is by the whole key, a crowded region is
   refined to as much depth as it takes to tell its members apart, and it splits over many tasks.
3. Candidates are confirmed on full sets; confirmed links give provisional components.
4. The rest: all pairs that share a region (a prefix of ``STEP`` hashes in any tree), lie in
   different provisional components and could by their sizes reach the threshold are compared by
   signature; the clusters of alike ones are then compared on full sets. Both work on pairs of blocks
   of bounded size with matrix operations and put out spanning forests, never all pairs; no region
   is too large and no partner is dropped.

A pair at similarity s shares no region with probability (1 - s^3)^20: 6e-7 at 0.8, and the
signature test then loses about 1e-6. Links are confirmed on full sets, so none is false.

Nodes have numbers of their own, so ids play no part but in naming components and survivors.

Defined results: null or empty text has no shingles, is linked with nothing and is kept; a text
of fewer words than a shingle is one shingle; rows that repeat an id and text share the result; an
id that stands on several texts is a node for each set, and each row has the component of its own
text; a null id links nothing, gets a null component and is kept; an empty table gives an empty
result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .components import components, with_group
from .runtime import materialise, one_of_each, release, table, text_digest
from .textcore import U64, chunks, find_words, mix64, ngrams, stream

STEP, TREES, DEPTH = 3, 20, 8
HASHES = STEP * TREES
NEIGHBOURS = 2
BLOCK = 512
_ODD = (stream(101, HASHES) >> U64(32)).astype(np.uint32) | np.uint32(1)
_ADD = (stream(202, HASHES) >> U64(32)).astype(np.uint32)


def shingle_sets(texts: pa.Array, size: int) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    for _, _, buf, offs in chunks(texts):
        w = find_words(buf, offs, "space")
        grams, at = ngrams(w.hash, w.ptr, size)
        own = np.searchsorted(at, w.ptr)
        for i, n in enumerate(w.count):
            if n >= size:
                yield np.unique(grams[own[i] : own[i + 1]])
            elif n:  # the whole sequence, told from other lengths by a mark
                whole, _ = ngrams(np.append(w.hash[w.ptr[i] : w.ptr[i + 1]], U64(n)), np.array([0, n + 1]), int(n) + 1)
                yield whole
            else:
                yield np.zeros(0, U64)


def signature(grams: np.ndarray) -> np.ndarray:
    low = np.full(HASHES, 0xFFFFFFFF, np.uint32)
    small = (grams >> U64(32)).astype(np.uint32)
    with np.errstate(over="ignore"):
        for a in range(0, len(small), 4096):
            np.minimum(low, (np.multiply.outer(_ODD, small[a : a + 4096]) + _ADD[:, None]).min(axis=1), out=low)
    return low


def set_sums(grams: np.ndarray) -> tuple[int, int]:
    """Two independent sums over a set; with its size they stand for it."""
    if not len(grams):
        return 0, 0
    with np.errstate(over="ignore"):
        return int(mix64(grams + U64(7)).sum().view(np.int64)), int(np.bitwise_xor.reduce(mix64(grams ^ U64(0x5555))).view(np.int64))


def _signatures(size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, one, two, sigs = [], [], [], []
            for grams in shingle_sets(batch.column("text"), size):
                n.append(len(grams))
                a, b = set_sums(grams)
                one.append(a)
                two.append(b)
                sigs.append(signature(grams).astype(">u4").tobytes() if len(grams) else None)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("digest"), pa.array(n, pa.int64()), pa.array(one, pa.int64()), pa.array(two, pa.int64()), pa.array(sigs, pa.binary())], names=["doc_id", "digest", "n_shingles", "set_a", "set_b", "sig"])

    return run


def _sets(size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = batch.column("set_a").to_pylist(), batch.column("set_b").to_pylist()
            sets = list(shingle_sets(batch.column("text"), size))
            own = pa.array([set_sums(g) == (x, y) for g, x, y in zip(sets, a, b, strict=True)], pa.bool_())  # an id may stand on other texts as well
            yield pa.RecordBatch.from_arrays([batch.column("node").filter(own), pa.array([g.tobytes() for g in sets], pa.binary()).filter(own)], names=["node", "grams"])

    return run


def _adjacent(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Neighbours in one sorted stretch of (tree, order, node): (a, b, lcp)."""
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        tree = batch.column("tree").to_numpy(zero_copy_only=False)
        node = batch.column("node").to_numpy(zero_copy_only=False)
        keys = np.frombuffer(b"".join(batch.column("order").to_pylist()), ">u4").reshape(len(node), DEPTH)
        if last is not None:
            tree, node, keys = np.append(last[0], tree), np.append(last[1], node), np.concatenate([last[2], keys])
        lcp = np.cumprod(keys[1:] == keys[:-1], axis=1).sum(axis=1)
        ok = (lcp >= STEP) & (tree[1:] == tree[:-1]) & (node[1:] != node[:-1])
        a, b = node[:-1][ok], node[1:][ok]
        yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b)), pa.array(lcp[ok].astype(np.int64))], names=["a", "b", "lcp"])
        last = tree[-1:], node[-1:], keys[-1:]


def _confirm(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            one, two = batch.column("grams_a").to_pylist(), batch.column("grams_b").to_pylist()
            ok = np.zeros(len(one), bool)
            for i, (x, y) in enumerate(zip(one, two, strict=True)):
                x, y = np.frombuffer(x, U64), np.frombuffer(y, U64)
                if 100 * min(len(x), len(y)) < percent * max(len(x), len(y)):
                    continue
                both = np.sort(np.concatenate([x, y]), kind="stable")
                shared = int((both[1:] == both[:-1]).sum())
                ok[i] = 100 * shared >= percent * (len(x) + len(y) - shared)
            keep = pa.array(ok)
            yield pa.RecordBatch.from_arrays([batch.column("a").filter(keep), batch.column("b").filter(keep)], names=["a", "b"])

    return run


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Runs of equal first columns of a sorted stream; a run is a block pair, so of bounded length."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        key = batch.column(0).to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero(key[1:] != key[:-1]) + 1).tolist(), len(key)]
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            piece = batch.slice(a, b - a)
            if held and held[-1].column(0)[0] != piece.column(0)[0]:
                yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
                held = []
            held.append(piece)
    if held:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def forest(joined: np.ndarray) -> list[tuple[int, int]]:
    """Edges of a spanning forest of a symmetric boolean matrix."""
    left, edges = joined.any(axis=1), []
    while left.any():
        front = [int(np.argmax(left))]
        left[front] = False
        while front:
            at = front.pop()
            new = np.flatnonzero(joined[at] & left)
            left[new] = False
            edges += [(at, int(x)) for x in new]
            front += new.tolist()
    return edges


def _edges(found: Iterator[tuple[np.ndarray, list[tuple[int, int]]]]) -> Iterator[pa.RecordBatch]:
    a: list[int] = []
    b: list[int] = []
    for node, edges in found:
        for x, y in edges:
            a.append(min(int(node[x]), int(node[y])))
            b.append(max(int(node[x]), int(node[y])))
        if len(a) > 10_000:
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])
            a, b = [], []
    yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])


def _columns(block: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Nodes of a block, which of its pairs are open: of different components, with sizes that allow a link."""
    node, root, n = (block.column(c).to_numpy(zero_copy_only=False) for c in ("node", "root", "n_shingles"))
    return node, root, n, root[:, None] != root[None, :]


def _alike(percent: int):
    """Spanning forests of the pairs of a block whose signatures may belong to linked sets."""
    least = HASHES * percent // 100 - 5 * int(np.ceil(np.sqrt(HASHES * percent * (100 - percent)) / 100)) + 4

    def found(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, list[tuple[int, int]]]]:
        for block in _groups(batches):
            node, _, n, open_ = _columns(block)
            open_ &= 100 * np.minimum(n[:, None], n[None, :]) >= percent * np.maximum(n[:, None], n[None, :])
            if not open_.any():
                continue
            sig = np.frombuffer(b"".join(block.column("sig").to_pylist()), np.uint32).reshape(-1, HASHES)
            agree = np.zeros(open_.shape, np.int16)
            for k in range(HASHES):
                agree += sig[:, k, None] == sig[None, :, k]
            yield node, forest(open_ & (agree >= least))

    return lambda batches: _edges(found(batches))


def _linked(percent: int):
    """Spanning forests of the pairs of a block whose full sets reach the threshold: exact overlaps by matrix product."""

    def found(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, list[tuple[int, int]]]]:
        for block in _groups(batches):
            node, _, n, open_ = _columns(block)
            if not open_.any():
                continue
            sets = [np.frombuffer(x, U64) for x in block.column("grams").to_pylist()]
            owner = np.repeat(np.arange(len(sets)), [len(x) for x in sets])
            _, code, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
            shared = count[code] > 1
            rank = np.cumsum(count > 1) - 1
            owner, code = owner[shared], rank[code[shared]]
            overlap = np.zeros(open_.shape, np.float32)
            for lo in range(0, int((count > 1).sum()), 4096):  # whole numbers below 2**24 are exact
                own = (code >= lo) & (code < lo + 4096)
                part = np.zeros((len(sets), 4096), np.float32)
                part[owner[own], code[own] - lo] = 1
                overlap += part @ part.T
            size = n[:, None] + n[None, :]
            yield node, forest(open_ & (100 * overlap >= percent * (size - overlap)))

    return lambda batches: _edges(found(batches))


def in_blocks(members: DataFrame, group: str, payload: str) -> DataFrame:
    """(key, node, root, n_shingles, payload) sorted by block pair, so that every two members of a group meet.

    Members of a group of n are dealt to ceil(n / BLOCK) blocks by hash; every pair of blocks is a
    unit of work of bounded size, whatever the group's size.
    """
    sized = with_group(members, group, "node", blocks=F.ceil(F.count("*") / BLOCK).cast("int"))
    own = F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")
    dealt = sized.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    key = F.xxhash64(group, F.least("own", "other"), F.greatest("own", "other"))
    return dealt.select(key.alias("key"), "node", "root", "n_shingles", payload).repartition("key").sortWithinPartitions("key")


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets reach the threshold."""
    one = sets.select(F.col("node").alias("a"), F.col("grams").alias("grams_a"))
    two = sets.select(F.col("node").alias("b"), F.col("grams").alias("grams_b"))
    return pairs.join(one, "a").join(two, "b").select("a", "b", "grams_a", "grams_b").mapInArrow(_confirm(percent), "a long, b long")


def _judged(docs: DataFrame, shingle: int, percent: int) -> DataFrame:
    """(doc_id, digest, n_shingles, component_id, root) for every row of ``docs`` (doc_id, text); no root where nothing can be linked."""
    spark = docs.sparkSession
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    signed = materialise(texts.select("doc_id", text_digest(F.col("text")).alias("digest"), "text").mapInArrow(_signatures(shingle), "doc_id long, digest binary, n_shingles long, set_a long, set_b long, sig binary"), "signed")
    key = ["n_shingles", "set_a", "set_b"]
    # one node for each distinct set
    nodes = materialise(signed.filter("n_shingles > 0 and doc_id is not null").groupBy(*key).agg(F.min("doc_id").alias("first_id"), F.min("sig").alias("sig")).withColumn("node", F.monotonically_increasing_id()), "nodes")
    order = F.concat("sig", F.expr(f"substring(sig, 1, {4 * DEPTH})"))
    trees = nodes.select("node", F.explode(F.array(*[F.struct(F.lit(t).alias("tree"), order.substr(4 * STEP * t + 1, 4 * DEPTH).alias("order")) for t in range(TREES)])).alias("x")).select("node", "x.tree", "x.order")
    stretch = trees.repartitionByRange("tree", "order").sortWithinPartitions("tree", "order", "node")
    near = stretch.mapInArrow(_adjacent, "a long, b long, lcp long").groupBy("a", "b").agg(F.sum("lcp").alias("lcp"))
    near = materialise(near, "neighbours")
    # each node's closest neighbours; it has two in a tree at most
    ends = near.select(F.col("a").alias("node"), "a", "b", "lcp").unionByName(near.select(F.col("b").alias("node"), "a", "b", "lcp"))
    best = ends.withColumn("place", F.row_number().over(Window.partitionBy("node").orderBy(F.desc("lcp"), "a", "b"))).filter(F.col("place") <= NEIGHBOURS).select("a", "b").distinct()
    # full sets of the nodes that share a region with another
    place = trees.select("node", F.xxhash64("tree", F.expr(f"substring(order, 1, {4 * STEP})")).alias("region"))
    members = materialise(with_group(place, "region", "node", "n > 1", n=F.count("*")).select("node", "region"), "members")
    active = members.select("node").distinct().join(nodes.select("node", F.col("first_id").alias("doc_id"), "set_a", "set_b"), "node")
    sets = texts.join(active.hint("shuffle_hash"), "doc_id").select("node", "set_a", "set_b", "text").mapInArrow(_sets(shingle), "node long, grams binary")
    if signed.filter("doc_id is not null").groupBy("doc_id").count().filter("count > 1").limit(1).count():
        sets = sets.dropDuplicates(["node"])  # rows that repeat an id and its text
    sets = materialise(sets, "sets")
    links = materialise(_confirmed(best, sets, percent), "links")
    first = materialise(components(links, "first"), "roots")
    # all other pairs of a region that could join two provisional components: first by signature, ...
    comp = members.join(first, "node", "left").select("node", "region", F.coalesce("root", "node").alias("root"))
    mixed = with_group(comp, "region", "node", "low != high", low=F.min("root"), high=F.max("root")).select("node", "region", "root")
    rest = mixed.join(nodes.select("node", "n_shingles", "sig"), "node")
    alike = materialise(in_blocks(rest, "region", "sig").mapInArrow(_alike(percent), "a long, b long"), "alike")
    # ... then, among the members of each cluster of alike signatures, on full sets
    cluster = components(alike, "clusters").withColumnRenamed("root", "cluster")
    close = cluster.join(first, "node", "left").select("node", "cluster", F.coalesce("root", "node").alias("root")).join(nodes.select("node", "n_shingles"), "node").join(sets, "node")
    more = materialise(in_blocks(close, "cluster", "grams").mapInArrow(_linked(percent), "a long, b long"), "more")
    last = components(links.unionByName(more), "last") if more.limit(1).count() else first
    rooted = nodes.join(last, "node", "left").select(*key, "first_id", F.coalesce("root", "node").alias("root"))
    group = with_group(rooted, "root", "first_id", component_id=F.min("first_id")).drop("first_id")
    release(spark, sets)
    out = signed.select("doc_id", "digest", *key).join(group, key, "left")
    alone = F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id"))
    return out.select("doc_id", "digest", "n_shingles", alone.alias("component_id"), F.when(F.col("doc_id").isNotNull(), F.col("root")).alias("root"))


def near_duplicates(docs: DataFrame, shingle: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row of ``docs`` (doc_id, text)."""
    kept = F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True))
    return _judged(docs, shingle, percent).select("doc_id", "n_shingles", "component_id", kept.alias("kept"))


def surviving_rows(docs: DataFrame, shingle: int = 5, percent: int = 80) -> DataFrame:
    """The rows of ``docs`` that stay: of each group the row with the least id, and of its texts the least by digest.

    Rows without shingles or without an id are no one's copies and all stay, but for rows that repeat both id and text.
    """
    judged = materialise(_judged(docs, shingle, percent).select("doc_id", "digest", "root"), "judged")
    best = judged.filter("root is not null").groupBy("root").agg(F.min(F.struct("doc_id", "digest")).alias("best")).select("best.*", F.lit(True).alias("stays"))
    kept = F.col("root").isNull() | F.coalesce("stays", F.lit(False))
    return one_of_each(docs, judged.join(best, ["doc_id", "digest"], "left").select("doc_id", "digest", kept.alias("kept")))


def op5_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), shingle=4, percent=80)


ORACLE = r"""
WITH RECURSIVE d AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS MATERIALIZED (SELECT doc_id, hash(g) AS g, n FROM (SELECT doc_id, unnest(l) AS g, len(l) AS n FROM (SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')]
   ELSE list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' ')) END) AS l FROM d))),
size AS (SELECT doc_id, count(*)::BIGINT AS n FROM s GROUP BY doc_id),
-- a prefix filter: linked sets share one of their first n - ceil(0.8 n) + 1 shingles in any common order
p AS MATERIALIZED (SELECT doc_id, g FROM (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY g) AS k FROM s) WHERE k <= n - (80 * n + 99) // 100 + 1),
c AS MATERIALIZED (SELECT DISTINCT a.doc_id AS a, b.doc_id AS b FROM p a JOIN p b ON a.g = b.g AND a.doc_id < b.doc_id),
l AS MATERIALIZED (SELECT a, b FROM (SELECT c.a, c.b, count(*) AS i FROM c JOIN s x ON x.doc_id = c.a JOIN s y ON y.doc_id = c.b AND y.g = x.g GROUP BY c.a, c.b) JOIN size m ON m.doc_id = a JOIN size k ON k.doc_id = b WHERE 100 * i >= 80 * (m.n + k.n - i)),
e AS MATERIALIZED (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
reach(doc_id, other) AS (SELECT DISTINCT a, a FROM e UNION SELECT r.doc_id, e.b FROM reach r JOIN e ON e.a = r.other)
SELECT d.doc_id, coalesce(size.n, 0)::BIGINT AS n_shingles, coalesce(m.c, d.doc_id) AS component_id, coalesce(m.c, d.doc_id) = d.doc_id AS kept
FROM d LEFT JOIN size USING (doc_id) LEFT JOIN (SELECT doc_id, min(other) AS c FROM reach GROUP BY doc_id) m USING (doc_id)
"""
