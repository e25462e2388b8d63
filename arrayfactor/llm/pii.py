"""Personal data by bootstrapped contextual extraction.

1. Seeds: well-formed identifiers (four kinds, fixed patterns) are found in every text.
2. Patterns: the words before an identifier (one and two of them, case folded, with punctuation) are
   lexical patterns. An identifier or candidate before it counts as one word that names its kind, and
   nothing beyond it is looked at, so all contexts of a text together cost its length; a text's beginning
   is a word of its own. A word longer than ``WORD`` characters stands as its beginning and a digest. Candidates are tokens of an identifier's looser shape, seeds among them; each
   occurrence joins an instance (kind and normalised content) to its patterns. Edges are counted
   over all texts; occurrences in one text count once.
3. Scores: Spark iterates over the graph. A pattern's confidence is the count-weighted mean
   confidence of its instances, shrunk towards zero by a prior; an instance's confidence is its
   patterns' count-weighted mean. Seeds stay at one.
4. Discovery: all patterns of confidence ``CONFIDENT`` or more mark candidates that they precede as
   identifiers; rare patterns are held back by the prior alone. Base spans all stay. The patterns go to the
   tasks where their checked size is at most ``PATTERN_BYTES``; beyond it the candidates' contexts are joined
   to them, with the same spans.

Texts are read twice and never shuffled; only edges are.

All searches are linear in the text, whatever it holds: addresses are looked for from their at sign
outwards, and the other shapes have bounded or possessive runs.

Defined results: null counts as empty; repeated rows get equal spans; ids play no part; extra columns
are ignored; without any identifier there are no patterns and no added spans.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left, bisect_right
from collections.abc import Iterator
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .runtime import materialise, table

KINDS = ("email", "ip", "card", "phone")
ROUNDS = 4
PATTERN_BYTES = 32_000_000  # of confident patterns that may go to every task
PATTERN_COST = 150  # bytes of one pattern besides its characters
SALTS = 16
CONFIDENT = 0.7
WORD = 40
PRIOR = 3.0

# fixed values: the base patterns; the guards in front change no match, they only stop rescans
_RUN = re.compile(r"[A-Za-z0-9._%+@-]*@[A-Za-z0-9._%+@-]*")
_EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
_CARD = re.compile(r"[0-9]([\x20-]?[0-9]){11,}+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
# looser shapes of the same kinds, for candidates; an address is found by its at mark
_LOOSE = {
    "ip": re.compile(r"(?<![0-9.:])(?:[0-9A-Fa-f]{1,4}:){5,7}[0-9A-Fa-f]{1,4}(?![0-9A-Fa-f:])"),
    "card": re.compile(r"(?<![0-9])[0-9]{4}(?:[.\x20-]?[0-9]{4}){2}[.\x20-]?[0-9]{1,7}(?![0-9])"),
    "phone": re.compile(r"(?<![0-9+])(?:\(?[0-9]{3}\)?[\x20.-]?)[0-9]{3}[.-][0-9]{4}(?![0-9])"),
}
_AT = re.compile(r"\(at\)|\[at\]| at ")
_DOMAIN = re.compile(r" ?[A-Za-z0-9-]++(?: ?(?:\(dot\)|\[dot\]| dot |\.) ?[A-Za-z0-9-]++)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")


def _luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if i % 2 == 0 else (2 * d if d < 5 else 2 * d - 9)
    return total % 10 == 0


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def _runs_with_at(text: str) -> Iterator[tuple[int, int]]:
    """Stretches of address characters around each at sign; no address reaches beyond its stretch."""
    at, upto = text.find("@"), 0
    allowed = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-@")
    while at >= 0:
        a, b = at, at + 1
        while a > upto and text[a - 1] in allowed:
            a -= 1
        while b < len(text) and text[b] in allowed:
            b += 1
        yield a, b
        upto = b
        at = text.find("@", b)


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of the well-formed identifiers, leftmost and without overlap in each kind."""
    out = []
    for a, b in _runs_with_at(text):
        out += [(a + m.start(), 0, a + m.end()) for m in _EMAIL.finditer(text[a:b])]
    for m in _IP.finditer(text):
        if all(int(p) <= 255 for p in m.group().split(".") if len(p.lstrip("0")) <= 3) and all(len(p.lstrip("0")) <= 3 for p in m.group().split(".")):
            out.append((m.start(), 1, m.end()))
    for m in _CARD.finditer(text):
        d = _digits(m.group())
        if 12 <= len(d) <= 19 and _luhn(d):
            out.append((m.start(), 2, m.end()))
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 9 <= len(_digits(m.group())) <= 15:
                out.append((m.start(), 3, m.end()))
    return sorted(out)


def _loose_addresses(text: str) -> Iterator[tuple[int, int]]:
    """Addresses with a spelt-out at mark, leftmost and without overlap; no character is walked over twice."""
    upto = 0
    for m in _AT.finditer(text):
        end = m.start()
        if end > upto and text[end - 1] == " ":
            end -= 1
        begin = end
        while begin > upto and text[begin - 1] in _LOCAL:
            begin -= 1
        domain = _DOMAIN.match(text, m.end()) if begin < end else None
        if domain:
            yield begin, domain.end()
            upto = domain.end()


def candidate_spans(text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """Looser shapes that no base span touches."""
    out = [(a, 0, b) for a, b in _loose_addresses(text)]
    for k, kind in enumerate(KINDS):
        if kind in _LOOSE and not (kind == "ip" and text.count(":") < 5):
            out += [(m.start(), k, m.end()) for m in _LOOSE[kind].finditer(text)]
    if not out:
        return out
    starts, reach = [a for a, _, _ in base], list(accumulate((b for _, _, b in base), max))
    clear = lambda a, b: not (n := bisect_left(starts, b)) or reach[n - 1] <= a
    return sorted(s for s in out if clear(s[0], s[2]))


def _word(w: str) -> str:
    w = w.lower()
    return w if len(w) <= WORD else f"{w[: WORD // 2]}~{hashlib.blake2b(w.encode(), digest_size=8).hexdigest()}"


def contexts(text: str, spans: list[tuple[int, int, int]], every: list[tuple[int, int, int]]) -> list[list[str]]:
    """For each of ``spans`` the one and two words before it; ``every`` holds all spans of the text."""
    ends = sorted((b, k) for _, k, b in every)
    out = []
    for a, _, _ in spans:
        n = bisect_right(ends, (a, len(KINDS)))
        begin, mark = (ends[n - 1][0], f"<{KINDS[ends[n - 1][1]]}>") if n else (0, "^")
        before = [mark, *map(_word, text[begin:a].rsplit(None, 2)[-2:])][-2:]
        out.append([" ".join(before[-n:]) for n in (1, 2) if len(before) >= n])
    return out


def _instance(kind: int, text: str) -> str:
    content = "".join(text.lower().split()) if kind == 0 else "".join(c for c in text.lower() if c.isalnum())
    return hashlib.blake2b(content.encode(), digest_size=8).hexdigest()


def _edges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(kind, pattern, instance, seed) of each text's occurrences, each once."""
    for batch in batches:
        rows: list[tuple[int, str, str, bool]] = []
        for text in batch.column("text").to_pylist():
            if text:
                base = base_spans(text)
                loose = candidate_spans(text, base)
                own = {(k, p, _instance(k, text[a:b]), seed) for spans, seed in ((base, True), (loose, False)) for (a, k, b), ps in zip(spans, contexts(text, spans, base + loose), strict=True) for p in ps}
                rows += sorted(own)
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int32(), pa.string(), pa.string(), pa.bool_()))], names=["kind", "pattern", "instance", "seed"])


def score_patterns(edges: DataFrame, rounds: int = ROUNDS) -> DataFrame:
    """(kind, pattern, n, confidence) from the graph of (kind, pattern, instance, seed, n)."""
    instances = edges.groupBy("kind", "instance").agg(F.max("seed").alias("seed")).select("kind", "instance", "seed", F.col("seed").cast("double").alias("trust"))
    patterns = None
    for _ in range(rounds):
        patterns = edges.join(instances.select("kind", "instance", "trust"), ["kind", "instance"]).groupBy("kind", "pattern").agg(F.sum("n").alias("n"), (F.sum(F.col("n") * F.col("trust")) / (F.sum("n") + PRIOR)).alias("confidence"))
        patterns = materialise(patterns, "patterns")
        means = edges.join(patterns.select("kind", "pattern", "confidence"), ["kind", "pattern"]).groupBy("kind", "instance").agg(F.max("seed").alias("seed"), (F.sum(F.col("n") * F.col("confidence")) / F.sum("n")).alias("mean"))
        instances = materialise(means.select("kind", "instance", "seed", F.when(F.col("seed"), 1.0).otherwise(F.col("mean")).alias("trust")), "instances")
    return patterns


def confident_patterns(docs: DataFrame, rounds: int = ROUNDS) -> DataFrame:
    """(kind, pattern) of every pattern good enough to discover identifiers."""
    edges = materialise(docs.select("text").mapInArrow(_edges, "kind int, pattern string, instance string, seed boolean").groupBy("kind", "pattern", "instance").agg(F.max("seed").alias("seed"), F.count("*").alias("n")), "edges")
    return materialise(score_patterns(edges, rounds).filter(F.col("confidence") >= CONFIDENT).select("kind", "pattern"), "confident")


def _by_kind(patterns: DataFrame) -> dict[int, set[str]]:
    """Patterns as sets; only for sizes that were checked."""
    out: dict[int, set[str]] = {}
    for r in patterns.collect():
        out.setdefault(r.kind, set()).add(r.pattern)
    return out


def discovered(text: str, base: list[tuple[int, int, int]], patterns: dict[int, set[str]]) -> list[tuple[int, int, int]]:
    if not patterns:
        return []
    loose = candidate_spans(text, base)
    return [s for s, ps in zip(loose, contexts(text, loose, base + loose), strict=True) if s[1] in patterns and any(p in patterns[s[1]] for p in ps)]


def _joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in sorted(spans))


def _extract(patterns):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts: list[list[int]] = [[], [], [], []]
            digests, joined = [], []
            for text in batch.column("text").to_pylist():
                text = text or ""
                base = base_spans(text)
                for k in range(4):
                    counts[k].append(sum(s[1] == k for s in base))
                digests.append(hashlib.sha256(_joined(base).encode()).hexdigest())
                joined.append(_joined(base + discovered(text, base, patterns.value)))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *[pa.array(c, pa.int64()) for c in counts], pa.array(digests, pa.string()), pa.array(joined, pa.string())], names=["doc_id", *[f"n_{k}" for k in KINDS], "base_sha256", "spans"])

    return run


ROWS = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string"
SPANS = "array<struct<start:int,kind:int,end:int>>"


def _candidates(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each row's number, its base results, its base spans and its candidates with their contexts."""
    fields = [("start", pa.int32()), ("kind", pa.int32()), ("end", pa.int32())]
    span, seen = pa.list_(pa.struct(fields)), pa.list_(pa.struct([*fields, ("patterns", pa.list_(pa.string()))]))
    for batch in batches:
        counts: list[list[int]] = [[], [], [], []]
        digests, found, loose = [], [], []
        for text in batch.column("text").to_pylist():
            text = text or ""
            base = base_spans(text)
            for k in range(4):
                counts[k].append(sum(s[1] == k for s in base))
            digests.append(hashlib.sha256(_joined(base).encode()).hexdigest())
            found.append([{"start": a, "kind": k, "end": b} for a, k, b in base])
            own = candidate_spans(text, base)
            loose.append([{"start": a, "kind": k, "end": b, "patterns": ps} for (a, k, b), ps in zip(own, contexts(text, own, base + own), strict=True)])
        yield pa.RecordBatch.from_arrays([batch.column("row_id"), batch.column("doc_id"), *[pa.array(c, pa.int64()) for c in counts], pa.array(digests, pa.string()), pa.array(found, span), pa.array(loose, seen)], names=["row_id", "doc_id", *[f"n_{k}" for k in KINDS], "base_sha256", "base", "loose"])


def _extract_by_join(docs: DataFrame, patterns: DataFrame) -> DataFrame:
    """As with broadcast patterns, for any number of them: candidates meet patterns by (kind, pattern, salt).

    Contexts of one wording are dealt over ``SALTS`` tasks, so a frequent one is not one task's work.
    """
    rows = docs.select(F.monotonically_increasing_id().alias("row_id"), F.col("doc_id").cast("long").alias("doc_id"), "text")
    rows = materialise(rows.mapInArrow(_candidates, f"row_id long, {ROWS}, base {SPANS}, loose array<struct<start:int,kind:int,end:int,patterns:array<string>>>"), "candidates")
    at = rows.select("row_id", F.explode("loose").alias("c")).select("row_id", "c.start", "c.kind", "c.end", F.explode("c.patterns").alias("pattern")).withColumn("salt", F.pmod("row_id", F.lit(SALTS)).cast("int"))
    salted = patterns.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    hits = at.join(salted, ["kind", "pattern", "salt"], "left_semi").groupBy("row_id").agg(F.collect_set(F.struct("start", "kind", "end")).alias("found"))
    spans = F.array_sort(F.concat("base", F.coalesce("found", F.array().cast(SPANS))))
    name = F.array(*[F.lit(k) for k in KINDS])
    text = F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(name, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ",")
    return rows.join(hits, "row_id", "left").select("doc_id", *[f"n_{k}" for k in KINDS], "base_sha256", text.alias("spans"))


def extract(docs: DataFrame, patterns: dict[int, set[str]] | None = None, pattern_bytes: int = PATTERN_BYTES) -> DataFrame:
    """One row per row of ``docs``: counts of base identifiers, their digest, and all spans."""
    if patterns is None:
        good = confident_patterns(docs)
        size = good.agg(F.sum(F.octet_length("pattern") + PATTERN_COST)).first()[0] or 0
        if size > pattern_bytes:
            return _extract_by_join(docs, good)
        patterns = _by_kind(good)
    sent = docs.sparkSession.sparkContext.broadcast(patterns)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_extract(sent), f"{ROWS}, spans string")


def op1_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "documents"))
