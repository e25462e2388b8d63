"""SentencePiece encoding and decoding by weighted transducers.

Three machines are compiled from the model's file, once a worker process:

- the normaliser, from the model's own specification: an optional space in front, runs of spaces
  kept or shortened, spaces to the boundary sign (a specification with a character map is refused);
- the pieces, as states and arcs: a state is a common beginning of pieces, an arc reads one character,
  and a state where a piece ends puts out its number;
- byte fallback: a character that no piece is made of puts out its bytes' numbers.

Composed with an input, a state is a place in the text together with the piece that ends there, and
an arc is the next piece. The model here ranks merges, so an arc's weight is not a piece's score: it is zero
if merging the text of the two pieces, by the model's ranks, ends in just these two, and infinite
otherwise. A sequence of pieces is the model's encoding exactly if all neighbours satisfy this, so the
shortest path in the (min, +) semiring is the encoding; every prefix has exactly one of finite cost.

No piece spans two characters that stand side by side in no piece (such as a boundary sign after
another character), so an input is cut there and composed in segments. All new segments of up to ``LONGEST`` characters of a
few hundred texts are composed at once, place by place, with arrays; longer ones each by itself. Paths
are kept in two generations of at most ``KEPT_BYTES`` each (the older one goes when the younger is full),
for as long as the worker process lives. Decoding runs the machines backwards. The model's file is read on
the driver, from a path that is a parameter, and its bytes go to the tasks.

Defined results: null counts as empty; an empty text has no pieces and decodes to itself; a text with
the boundary sign itself decodes to a space there (``round_trip`` is false); texts of any length are
encoded whole; an empty table gives an empty result; repeated rows, ids and extra columns play no part.
"""

from __future__ import annotations

import hashlib
import re
from array import array
from collections.abc import Iterator
from math import inf
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .runtime import table

SIGN = "▁"
KEPT_BYTES = 56 << 20  # of paths in each generation
WEIGHTS = 1 << 20  # arcs whose weights are kept
LONGEST = 64
TABLE = 0x3000  # characters below it are looked up directly
FIRST = -(1 << 22)  # stands for "no piece before"; outputs are above it
OFFSET, WIDTH = 1 << 22, 1 << 24
ROWS = 256  # of a batch that are worked on at once
MODEL = "/opt/tokenizers/piece_bpe_32k.model"


class Kept:
    """A mapping bounded in bytes: two generations, the older of which is dropped."""

    def __init__(self, limit: int, each: int):
        self.limit, self.each, self.size, self.young, self.old = limit, each, 0, {}, {}

    def get(self, key):
        got = self.young.get(key)
        if got is None and (got := self.old.get(key)) is not None:
            self.put(key, got)
        return got

    def put(self, key, value) -> None:
        self.size += self.each + (len(value) if isinstance(value, bytes) else 0)  # both objects and the table's entry
        if self.size > self.limit:
            self.old, self.young, self.size = self.young, {}, 0
        self.young[key] = value


class PieceTransducer:
    """Normaliser, piece states and byte fallback of a merge-ranked model."""

    def __init__(self, model: bytes):
        import sentencepiece
        from sentencepiece import sentencepiece_model_pb2

        spec = sentencepiece_model_pb2.ModelProto.FromString(model)
        if spec.normalizer_spec.precompiled_charsmap or spec.trainer_spec.treat_whitespace_as_suffix or not spec.normalizer_spec.escape_whitespaces:
            raise ValueError("the normaliser of this model has a character map or marks spaces in another way")
        self.in_front = SIGN if spec.normalizer_spec.add_dummy_prefix else ""
        self.shorten = spec.normalizer_spec.remove_extra_whitespaces
        source = sentencepiece.SentencePieceProcessor(model_proto=model)
        self.size = size = source.vocab_size()
        self.rank: dict[str, float] = {}
        self.text: list[str] = [""] * size
        self.byte = [0] * 256
        self.surface: list[bytes] = [b""] * size
        self.arcs: list[dict[str, int]] = [{}]
        self.puts_out: list[int] = [-1]
        for i in range(size):
            piece = source.id_to_piece(i)
            if source.is_byte(i):
                value = int(piece[1:-1], 16)
                self.byte[value], self.surface[i] = i, bytes([value])
            elif source.is_unknown(i):
                self.surface[i] = " ⁇ ".encode()
            elif not source.is_control(i) and not source.is_unused(i):
                self.rank[piece], self.text[i] = -source.get_score(i), piece
                self.surface[i] = piece.replace(SIGN, " ").encode()
                self._add(piece, i)
        self.side_by_side = {p[i : i + 2] for p in self.rank for i in range(len(p) - 1)}
        self.alphabet = np.array(sorted({ord(c) for state in self.arcs for c in state}), np.int64)
        self.place = {chr(c): k for k, c in enumerate(self.alphabet.tolist())}
        arcs = sorted((state * len(self.place) + self.place[c], to) for state, own in enumerate(self.arcs) for c, to in own.items())
        self.arc_key, self.arc_to = (np.array(x, np.int64) for x in zip(*arcs, strict=True))
        self.out_of = np.array(self.puts_out, np.int64)
        self.letter = np.full(TABLE, len(self.alphabet), np.int32)
        self.letter[self.alphabet[self.alphabet < TABLE]] = np.flatnonzero(self.alphabet < TABLE)
        self.joins = np.zeros((len(self.alphabet) + 1, len(self.alphabet) + 1), bool)
        for pair in self.side_by_side:
            self.joins[self.place[pair[0]], self.place[pair[1]]] = True
        self.weight_key, self.weight_value = np.zeros(0, np.int64), np.zeros(0)
        self.paths = Kept(KEPT_BYTES, 250)

    def _add(self, piece: str, number: int) -> None:
        state = 0
        for c in piece:
            following = self.arcs[state].get(c)
            if following is None:
                following = self.arcs[state][c] = len(self.arcs)
                self.arcs.append({})
                self.puts_out.append(-1)
            state = following
        self.puts_out[state] = number

    def normalise(self, text: str) -> str:
        if self.shorten:
            text = re.sub(" +", " ", text.strip(" "))
        return self.in_front + text.replace(" ", SIGN) if text else ""

    def letters(self, code: np.ndarray) -> np.ndarray:
        """Places in the alphabet of characters; its length for others."""
        out = self.letter[np.minimum(code, TABLE - 1)]
        rare = np.flatnonzero(code >= TABLE - 1)
        if len(rare):
            at = np.minimum(np.searchsorted(self.alphabet, code[rare]), len(self.alphabet) - 1)
            out[rare] = np.where(self.alphabet[at] == code[rare], at, len(self.alphabet))
        return out

    def segments(self, text: str) -> list[str]:
        """A normalised text, cut where the two characters stand side by side in no piece."""
        if not text:
            return []
        own = self.letters(np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64))
        cuts = [0, *(np.flatnonzero(~self.joins[own[:-1], own[1:]]) + 1).tolist(), len(text)]
        return [text[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)]

    def merged(self, text: str) -> list[str]:
        """What merging by rank leaves of a short text."""
        parts, rank = list(text), self.rank
        while True:
            best, at = None, -1
            for i in range(len(parts) - 1):
                r = rank.get(parts[i] + parts[i + 1])
                if r is not None and (best is None or r < best):
                    best, at = r, i
            if at < 0:
                return parts
            parts[at : at + 2] = [parts[at] + parts[at + 1]]

    def piece(self, number: int) -> str:
        """The text of an arc's output; below zero it is a character of no piece."""
        return self.text[number] if number >= 0 else chr(-1 - number)

    def weight(self, before: int | None, number: int) -> float:
        """Of the arc that puts out ``number`` after ``before`` (or first, after nothing): zero or infinite."""
        a, b = "" if before is None else self.piece(before), self.piece(number)
        if not a or a[-1] + b[0] not in self.side_by_side:
            return 0.0 if self.merged(b) == [b] else inf
        return 0.0 if self.merged(a + b) == [a, b] else inf

    def shortest_path(self, text: str) -> list[int]:
        """Outputs on the path of least cost through a segment; a character of no piece is -1 less its code point.

        Places are settled from left to right, since every arc goes right; ``cost`` is a place's least
        cost so far and ``last`` the arc on it.
        """
        n, cost, last, came = len(text), [0.0] + [inf] * len(text), [0] * (len(text) + 1), [0] * (len(text) + 1)
        for start in range(n):
            if cost[start] == inf:
                continue
            before, state = last[start] if start else None, 0
            for at in range(start, n):
                state = -1 if state < 0 else self.arcs[state].get(text[at], -1)
                number = self.puts_out[state] if state >= 0 else -1
                if number < 0 and at == start:
                    number = -1 - ord(text[at])  # byte fallback
                elif state < 0:
                    break
                if cost[at + 1] > cost[start] and (number >= 0 or at == start):
                    w = cost[start] + self.weight(before, number)
                    if w < cost[at + 1]:
                        cost[at + 1], last[at + 1], came[at + 1] = w, number, start
        out, at = [], n
        while at:
            out.append(last[at])
            at = came[at]
        return out[::-1]

    def _weights(self, key: np.ndarray, before: np.ndarray, number: np.ndarray) -> np.ndarray:
        """Weights of many arcs; new ones are worked out once and kept."""
        at = np.minimum(np.searchsorted(self.weight_key, key), max(len(self.weight_key) - 1, 0))
        known = self.weight_key[at] == key if len(self.weight_key) else np.zeros(len(key), bool)
        if not known.all():
            new, first = np.unique(key[~known], return_index=True)
            pairs = zip(before[~known][first].tolist(), number[~known][first].tolist(), strict=True)
            value = np.array([self.weight(None if b == FIRST else b, c) for b, c in pairs])
            if len(self.weight_key) + len(new) > WEIGHTS:  # begin anew with what these arcs need
                old, one = np.unique(key[known], return_index=True)
                self.weight_key, self.weight_value = old, self.weight_value[at[known]][one]
            place = np.searchsorted(self.weight_key, new)
            self.weight_key, self.weight_value = np.insert(self.weight_key, place, new), np.insert(self.weight_value, place, value)
            at = np.searchsorted(self.weight_key, key)
        return self.weight_value[at]

    def shortest_paths(self, segments: list[str]) -> list[bytes]:
        """The same for many segments at once, as little-endian numbers: at each place all segments that reach it take their arcs together."""
        size = np.array([len(x) for x in segments], np.int64)
        order = np.argsort(-size, kind="stable")
        size = size[order]
        code = np.full((len(segments), int(size[0]) + 1), -1, np.int64)
        flat = np.frombuffer("".join([segments[i] for i in order]).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
        code[np.arange(code.shape[1]) < size[:, None]] = flat
        letter = np.full(code.shape, -1, np.int64)
        inside = np.arange(code.shape[1]) < size[:, None]
        own = self.letters(flat)
        letter[inside] = np.where(own < len(self.alphabet), own, -1)
        cost = np.full(code.shape, inf)
        cost[:, 0] = 0.0
        last, came = np.full(code.shape, FIRST), np.zeros(code.shape, np.int64)
        for start in range(code.shape[1] - 1):
            row = np.flatnonzero((size > start) & np.isfinite(cost[:, start]))
            state, at = np.zeros(len(row), np.int64), start
            while len(row):
                c = letter[row, at]
                key = state * len(self.alphabet) + c
                arc = np.minimum(np.searchsorted(self.arc_key, key), len(self.arc_key) - 1)
                goes = (c >= 0) & (self.arc_key[arc] == key)
                state = np.where(goes, self.arc_to[arc], 0)
                number = np.where(goes, self.out_of[state], -1)
                if at == start:  # byte fallback
                    number = np.where(number < 0, -1 - code[row, at], number)
                    takes = np.ones(len(row), bool)
                else:
                    takes = number >= 0
                takes &= cost[row, at + 1] > cost[row, start]
                if takes.any():
                    own, out = row[takes], number[takes]
                    before = last[own, start]
                    w = cost[own, start] + self._weights((before + OFFSET) * WIDTH + out + OFFSET, before, out)
                    better = w < cost[own, at + 1]
                    own = own[better]
                    cost[own, at + 1], last[own, at + 1], came[own, at + 1] = w[better], out[better], start
                at += 1
                goes &= size[row] > at
                row, state = row[goes], state[goes]
        # back along the arcs, all segments together: the k-th column holds the k-th last output
        row, end, columns = np.arange(len(size)), size, []
        while end.any():
            columns.append(np.where(end > 0, last[row, end], FIRST))
            end = np.where(end > 0, came[row, end], 0)
        paths = np.stack(columns[::-1], 1)
        real = paths != FIRST
        flat, bounds = paths[real].astype("<i4").tobytes(), [0, *(4 * np.cumsum(real.sum(1))).tolist()]
        fallback = set(np.flatnonzero((real & (paths < 0)).any(1)).tolist())
        found: list[bytes] = [b""] * len(segments)
        for k, i in enumerate(order.tolist()):
            found[i] = flat[bounds[k] : bounds[k + 1]] if k not in fallback else self._numbers(paths[k][real[k]].tolist())
        return found

    def _numbers(self, path: list[int]) -> bytes:
        if min(path) < 0:
            path = [x for number in path for x in ([number] if number >= 0 else [self.byte[b] for b in self.piece(number).encode()])]
        return array("i", path).tobytes()

    def encode_all(self, texts: list[str]) -> list[np.ndarray]:
        kept, own = self.paths, [self.segments(self.normalise(t)) for t in texts]
        here: dict[str, bytes | None] = {}
        for segments in own:
            for s in segments:
                if s not in here:
                    here[s] = kept.get(s)
        new = [s for s, path in here.items() if path is None]
        for low, high in ((0, 6), (6, 12), (12, LONGEST)):  # of like lengths, so that little of the arrays is padding
            short = [s for s in new if low < len(s) <= high]
            for s, path in zip(short, self.shortest_paths(short) if short else (), strict=True):
                here[s] = path
                kept.put(s, path)
        for s in new:
            if len(s) > LONGEST:
                here[s] = self._numbers(self.shortest_path(s))
        return [np.frombuffer(b"".join([here[s] for s in segments]), "<i4") for segments in own]

    def encode(self, text: str) -> np.ndarray:
        return self.encode_all([text])[0]

    def decode(self, ids: np.ndarray) -> str:
        surface = self.surface
        out = b"".join([surface[i] for i in ids.tolist()])
        return (out[1:] if self.in_front and out[:1] == b" " else out).decode("utf-8", errors="replace")


_OWN: dict[str, PieceTransducer] = {}


def transducer_of(model: bytes) -> PieceTransducer:
    """This process's machines for a model; one model at a time."""
    name = hashlib.sha256(model).hexdigest()
    if name not in _OWN:
        _OWN.clear()
        _OWN[name] = PieceTransducer(model)
    return _OWN[name]


def _run(model, with_ids: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        transducer = transducer_of(model.value)
        for batch in (whole.slice(a, ROWS) for whole in batches for a in range(0, whole.num_rows, ROWS)):
            n, digests, same, ids = [], [], [], []
            texts = [t or "" for t in batch.column("text").to_pylist()]
            for text, own in zip(texts, transducer.encode_all(texts), strict=True):
                n.append(len(own))
                digests.append(hashlib.sha256(own.tobytes()).hexdigest())
                same.append(transducer.decode(own) == text)
                if with_ids:
                    ids.append(own)
            columns = [batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(digests, pa.string()), pa.array(same, pa.bool_())]
            names = ["doc_id", "n_pieces", "ids_sha256", "round_trip"]
            if with_ids:
                bounds = np.concatenate([[0], np.cumsum(n)]).astype(np.int32)
                flat = np.concatenate(ids).astype(np.int32, copy=False) if ids else np.zeros(0, np.int32)
                columns.append(pa.ListArray.from_arrays(pa.array(bounds), pa.array(flat)))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(columns, names=names)

    return run


def encode(docs: DataFrame, model_path: str = MODEL, with_ids: bool = True) -> DataFrame:
    """(doc_id, n_pieces, ids_sha256, round_trip[, ids]) for every row; the digest is of little-endian 32-bit ids."""
    model = docs.sparkSession.sparkContext.broadcast(Path(model_path).read_bytes())
    schema = "doc_id long, n_pieces long, ids_sha256 string, round_trip boolean" + ", ids array<int>" * with_ids
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_run(model, with_ids), schema)


def decode(encoded: DataFrame, model_path: str = MODEL) -> DataFrame:
    """(doc_id, text) of rows with ``ids``; a null list decodes to an empty text."""
    model = encoded.sparkSession.sparkContext.broadcast(Path(model_path).read_bytes())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        transducer = transducer_of(model.value)
        for batch in batches:
            texts = [transducer.decode(np.array(x or [], np.int64)) for x in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return encoded.select(F.col("doc_id").cast("long").alias("doc_id"), "ids").mapInArrow(run, "doc_id long, text string")


def op6_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(table(spark, sf_dir, "documents"), with_ids=False)
