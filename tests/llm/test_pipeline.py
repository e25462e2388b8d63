"""The pipeline's stages against brute force on the small tables."""

from __future__ import annotations

import hashlib
import re

import sentencepiece

import corpus_pipeline
from arrayfactor.llm import pieces, toxicity

from .test_operators import SMALL, components


def words(text):
    lowered = (text or "").translate({c: c + 32 for c in range(65, 91)})
    return re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", lowered)


def contaminated(text, windows):
    w = words(text)
    hit = [False] * len(w)
    for i in range(len(w)):
        for n in {len(x) for x in windows}:
            if tuple(w[i : i + n]) in windows:
                hit[i : i + n] = [True] * n
    return any(hit) and 20 * sum(hit) >= len(w)


def test_stages_by_brute_force(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    labels = spark.read.parquet(f"{SMALL}/labels.parquet")
    left = {r.doc_id: r.text for r in docs.collect()}
    toxic = {r.doc_id for r in toxicity.judged(docs, labels).filter("predicted = 1").collect()}
    left = {i: t for i, t in left.items() if i not in toxic}
    first: dict = {}
    for i in sorted(left):
        first.setdefault(left[i] or "", i)
    left = {i: t for i, t in left.items() if first[t or ""] == i}
    comp = components(sorted(left.items()), 5, 80)
    left = {i: t for i, t in left.items() if comp[i][1] == i}
    windows = set()
    for r in spark.read.parquet(f"{SMALL}/benchmark.parquet").collect():
        w = words(r.text)
        n = min(13, len(w))
        windows |= {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if n else set()
    left = {i: t for i, t in left.items() if not contaminated(t, windows)}
    library = sentencepiece.SentencePieceProcessor(model_file=pieces.MODEL)
    got = corpus_pipeline.run(spark, SMALL).collect()
    assert sorted((r.doc_id, list(r.ids)) for r in got) == sorted((i, library.encode(t or "")) for i, t in left.items())
    assert all(len(r.ids_sha256) == len(hashlib.sha256(b"").hexdigest()) for r in got)
    assert [len(s) for s in corpus_pipeline.STAGES] == [2] * 5
