"""Secret scan with a trigram index, in DataFrame functions only.

1. Each rule's regular expression is analysed into a Boolean query over trigrams that every match
   must contain (case folded): literal runs give conjunctions, alternatives disjunctions. A rule
   without mandatory trigrams has no query.
2. The index has, for each trigram that a query names and each block of 32,768 rows, a bitmap of
   the rows whose text contains it. Rows are numbered by their place in their file, which
   is dense whatever the ids are; a table that is not files is written once first. Queries are evaluated on the postings: bitmaps of a conjunction are
   intersected, those of its alternatives united.
3. Rules verify their candidates by their regular expression, leftmost and without overlap; rules
   without a query scan every text. Both happen in one pass over the table, which is joined to the
   candidates' bitmaps by block. Those take an eighth of a byte for each text and rule: they are
   broadcast where their size, checked after they are written, is small, and otherwise joined by
   a shuffle. Offsets are code points; they come from the lengths of matches and what lies between.

Defined results: null counts as empty text; ids play no part; repeated rows are indexed and verified
each by itself; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import reduce

from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .runtime import materialise, table

BROADCAST_BYTES = 64 << 20


@dataclass(frozen=True)
class Rule:
    kind: str
    pattern: str
    group: int = 0  # whose length counts
    least: int = 1
    base: bool = False


# fixed values: the three base rules, then wordings of well-known token formats
RULES = [
    Rule("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6, True),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 20, True),
    Rule("hex", r"[0-9a-f]{24,}", 0, 24, True),
    Rule("github", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("slack", r"xox[abpr]-[A-Za-z0-9-]{10,}"),
    Rule("stripe", r"[rs]k_live_[A-Za-z0-9]{16,}"),
    Rule("google", r"AIza[A-Za-z0-9_-]{35,}"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
    Rule("pem", r"-----BEGIN (?:RSA |EC |DSA |OPENSSH )?PRIVATE KEY-----"),
]

Query = frozenset  # of frozensets of trigrams: any of these, all of each; {frozenset()} is "no condition"
ANY: Query = frozenset([frozenset()])


def _tidy(q: set[frozenset[str]]) -> Query:
    """Without alternatives that another one contains."""
    return frozenset(c for c in q if not any(d < c for d in q))


def _both(a: Query, b: Query) -> Query:
    return _tidy({x | y for x in a for y in b})


def _literal(strings: set[str]) -> Query:
    return _tidy({frozenset(s[i : i + 3] for i in range(len(s) - 2)) for s in strings})


def trigram_query(pattern: str, limit: int = 64) -> Query:
    """The trigrams, case folded, that any match of ``pattern`` must contain."""
    parser = re._parser  # the regular expression's syntax tree

    def exact_of(op, arg) -> set[str] | None:
        """All strings that an element can match, if they are few."""
        name = str(op)
        if name == "LITERAL":
            return {chr(arg).lower()}
        if name == "IN" and all(str(o) == "LITERAL" for o, _ in arg) and len(arg) <= 8:
            return {chr(a).lower() for _, a in arg}
        if name == "SUBPATTERN":
            return sequence(arg[3])[0]
        if name == "BRANCH":
            parts = [sequence(x)[0] for x in arg[1]]
            return None if any(p is None for p in parts) else set().union(*parts)
        if name == "MAX_REPEAT" and arg[1] <= 1:
            inner = sequence(arg[2])[0]
            return None if inner is None else inner | ({""} if arg[0] == 0 else set())
        return None

    def query_of(op, arg) -> Query:
        name = str(op)
        if name == "SUBPATTERN":
            return sequence(arg[3])[1]
        if name == "BRANCH":
            return _tidy(set().union(*(sequence(x)[1] for x in arg[1])))
        if name == "MAX_REPEAT" and arg[0] >= 1:
            return sequence(arg[2])[1]
        return ANY

    def sequence(items) -> tuple[set[str] | None, Query]:
        """(all strings if few, the query) of a run of elements."""
        run, query, whole = {""}, ANY, True
        for op, arg in items:
            exact = exact_of(op, arg)
            if exact is not None and len(run) * len(exact) <= limit:
                run = {a + b for a in run for b in exact}
            else:
                query = _both(query, _literal(run))
                query, run, whole = (_both(query, query_of(op, arg)), {""}, False) if exact is None else (query, set(exact), False)
        return (run if whole else None), _both(query, _literal(run))

    return sequence(parser.parse(pattern))[1]


def _quoted(s: str) -> str:
    return "'" + s.replace("\\", "\\\\").replace("'", "\\'") + "'"


def numbered(docs: DataFrame) -> DataFrame:
    """(doc_id, text, file, block, bit): every row's dense place, by its number in its file."""
    try:
        rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.col("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("row"))
    except AnalysisException:  # not read from Parquet files
        return numbered(materialise(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), "rows"))
    return rows.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), "file", F.bitmap_bucket_number(F.col("row") + 1).alias("block"), F.bitmap_bit_position(F.col("row") + 1).alias("bit"))


def build_index(rows: DataFrame, trigrams: list[str]) -> DataFrame:
    """(trigram, file, block, ids): bitmaps of the rows whose text contains the trigram, over all rows."""
    folded = rows.select("file", "block", "bit", F.lower("text").alias("folded"))
    present = F.array_compact(F.array(*[F.when(F.contains("folded", F.lit(t)), F.lit(t)) for t in trigrams]))
    posting = folded.select("file", "block", "bit", F.explode(present).alias("trigram"))
    return posting.groupBy("trigram", "file", "block").agg(F.bitmap_construct_agg("bit").alias("ids"))


def candidates(index: DataFrame, queries: dict[str, Query]) -> DataFrame:
    """(file, block, one bitmap column for each rule): the Boolean queries evaluated on the postings."""
    spark = index.sparkSession
    rows = [f"({_quoted(kind)}, {n}, {len(c)}, {_quoted(t)})" for kind, q in queries.items() for n, c in enumerate(sorted(map(sorted, q))) for t in c]
    wanted = spark.sql(f"SELECT * FROM VALUES {', '.join(rows)} AS q(kind, clause, needs, trigram)")
    clauses = index.join(F.broadcast(wanted), "trigram").groupBy("kind", "clause", "needs", "file", "block").agg(F.bitmap_and_agg("ids").alias("ids"), F.count("*").alias("n")).filter("n = needs")
    united = clauses.groupBy("kind", "file", "block").agg(F.bitmap_or_agg("ids").alias("ids"))
    return united.groupBy("file", "block").agg(*[F.max(F.when(F.col("kind") == k, F.col("ids"))).alias(f"in_{k}") for k in queries])


def _has(bitmap: Column, position: Column) -> Column:
    """Whether a bitmap column has the bit; null bitmaps have none."""
    byte = F.conv(F.hex(F.substring(bitmap, (F.floor(position / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    return F.coalesce(F.getbit(byte, F.pmod(position, F.lit(8)).cast("int")) == 1, F.lit(False))


SPANS = "array<struct<start:int,rank:int,end:int,kind:string,base:boolean>>"
STEP = 256


def _parts(lengths: Column) -> Column:
    return F.transform(F.sequence(F.lit(0), F.floor((F.size(lengths) - 1) / STEP).cast("int")), lambda c: F.slice(lengths, c * STEP + 1, F.lit(STEP)))


def _running(x: Column) -> Column:
    """Zero, then the running totals of an array of whole numbers."""
    return F.aggregate(x, F.array(F.lit(0)), lambda a, v: F.concat(a, F.array(F.element_at(a, -1) + v)))


def with_spans(rows: DataFrame, rules: list[Rule], open_: dict[str, Column]) -> DataFrame:
    """``rows`` (with ``text``) and the rules' spans: leftmost, without overlap, failing ones dropped.

    Offsets are running totals of the lengths of matches and of what lies between, taken in two
    levels (within and over stretches of ``STEP``), so that a text with very many matches stays
    cheap. Each step is a projection of its own, so that no regular expression runs twice.
    """
    keep = rows.columns
    found = {r.kind: F.when(open_[r.kind], F.regexp_extract_all("text", F.lit(r.pattern), F.lit(0))) for r in rules}
    counted = {r.kind: F.when(open_[r.kind], F.regexp_extract_all("text", F.lit(r.pattern), F.lit(r.group))) for r in rules if r.group}
    gaps = {r.kind: F.when(open_[r.kind], F.split("text", r.pattern, -1)) for r in rules}
    rows = rows.select(*keep, *[c.alias(f"m_{k}") for k, c in found.items()], *[c.alias(f"c_{k}") for k, c in counted.items()], *[c.alias(f"p_{k}") for k, c in gaps.items()])
    kinds = [r.kind for r in rules]
    matched = [f"{x}_{k}" for k in kinds for x in "mc" if x == "m" or k in counted]
    gap = lambda k: F.transform(F.slice(f"p_{k}", F.lit(1), F.size(f"m_{k}")), F.length)
    rows = rows.select(*keep, *matched, *[gap(k).alias(f"g_{k}") for k in kinds])
    rows = rows.select(*keep, *matched, *[f"g_{k}" for k in kinds], *[_parts(F.zip_with(f"g_{k}", f"m_{k}", lambda p, m: p + F.length(m))).alias(f"l_{k}") for k in kinds])
    heads = lambda k: _running(F.transform(f"l_{k}", lambda x: F.aggregate(x, F.lit(0), lambda a, v: a + v)))
    rows = rows.select(*keep, *matched, *[f"g_{k}" for k in kinds], *[f"l_{k}" for k in kinds], *[heads(k).alias(f"h_{k}") for k in kinds])
    before = lambda k: F.flatten(F.transform(f"l_{k}", lambda x, c: F.transform(F.slice(_running(x), F.lit(1), F.size(x)), lambda v: v + F.get(f"h_{k}", c))))
    rows = rows.select(*keep, *matched, *[f"g_{k}" for k in kinds], *[before(k).alias(f"b_{k}") for k in kinds])

    def spans(rank: int, r: Rule) -> Column:
        k = r.kind
        zipped = F.arrays_zip(F.col(f"b_{k}").alias("b"), F.col(f"g_{k}").alias("g"), F.col(f"m_{k}").alias("m"), F.col(f"c_{k}" if r.group else f"m_{k}").alias("c"))
        good = F.filter(zipped, lambda x: F.length(x["c"]) >= r.least)
        made = F.transform(good, lambda x: F.struct((x["b"] + x["g"]).alias("start"), F.lit(rank).alias("rank"), (x["b"] + x["g"] + F.length(x["m"])).alias("end"), F.lit(k).alias("kind"), F.lit(r.base).alias("base")))
        return F.coalesce(made, F.array().cast(SPANS))

    return rows.select(*keep, F.array_sort(F.concat(*[spans(i, r) for i, r in enumerate(rules)])).alias("spans"))


def scan(docs: DataFrame, rules: list[Rule] = RULES) -> DataFrame:
    """One row per row of ``docs``: doc_id and its spans (start, rank, end, kind, base) in order."""
    queries = {r.kind: q for r in rules if ANY != (q := trigram_query(r.pattern))}
    trigrams = sorted({t for q in queries.values() for c in q for t in c})
    rows = numbered(docs)
    found = materialise(candidates(build_index(rows, trigrams), queries), "candidates")
    small = found.count() * len(queries) * 4096 <= BROADCAST_BYTES
    rows = rows.join(F.broadcast(found) if small else found, ["file", "block"], "left")
    flag = lambda r: _has(F.col(f"in_{r.kind}"), F.col("bit")) if r.kind in queries else F.col("text").rlike(r.pattern)
    rows = rows.select("doc_id", "text", *[flag(r).alias(f"open_{r.kind}") for r in rules])
    return with_spans(rows, rules, {r.kind: F.col(f"open_{r.kind}") for r in rules}).select("doc_id", "spans")


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")


def op8_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = scan(table(spark, sf_dir, "documents"))
    base = F.filter("spans", lambda x: x["base"])
    count = lambda kind: F.size(F.filter("spans", lambda x: x["kind"] == kind)).cast("long")
    return rows.select("doc_id", count("assign").alias("n_assign"), count("access").alias("n_access"), count("hex").alias("n_hex"), F.sha2(_joined(base), 256).alias("base_sha256"), _joined(F.col("spans")).alias("spans"))
