"""Toxicity by compression distance.

Two zstandard dictionaries are trained apart from each other, one on windows of toxic, one on windows of ordinary labelled documents,
by the same trainer with the same size and the same bounds. A document is cut into windows at spaces, every window
is compressed with both, and what the toxic dictionary saves against the ordinary one is the window's gain. The
sorted gains become features (greatest, mean of the three greatest, mean, upper tenth, numbers above thresholds), which a
logistic model, fitted on documents that taught neither dictionary, turns into a probability. The decision threshold applies
to that.

The windows of a slice of texts are compressed with one dictionary, then with the other, each by itself but all in one call.
Compression is by the optimal parser (``LEVEL``): the fast levels take the first match they meet, and gains are then mostly chance.

Learning uses only rows whose crc32(doc_id) mod 3 is not 1: at most ``TEACHERS`` documents a kind for the dictionaries and
``JUDGES`` (ordinary, toxic) for the calibration, disjoint by a hash of the id, the least ones by another (so the choice doesn't depend on
partitioning). A teacher of any length teaches, with at most ``TEACH_WINDOWS`` evenly spaced windows. Everything else covers all
rows and whole texts. Labels, language, source and id are no inputs of a score.

Defined results: a null text scores like an empty one; unlabelled, null or conflicting labels don't teach (a
document labelled both ways is left out); with no toxic or no ordinary teacher every score is the share of
toxic ones (0 without any); where the calibration lacks a kind, the teachers of the dictionaries calibrate; samples too few for the
trainer are the dictionary themselves.
"""

from __future__ import annotations

import math
from bisect import bisect_left
from collections.abc import Callable
from operator import sub

import numpy as np
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from concord.llm.rows import map_text
from concord.runtime import keep

WINDOW = 48
LEVEL = 15
DICTIONARY_BYTES = 1 << 17
SEGMENT, GRAM = 12, 6
TEACHERS, JUDGES, TEACH_WINDOWS = 4000, (3000, 1500), 256
#: Of ten parts of the ids, those that calibrate.
JUDGING = 3
GAINS = (2, 3, 4, 5, 6, 8, 10)
#: Windows that are compressed in one call, and distinct ones whose gains a task remembers (some 200 bytes each) before it begins anew.
TOGETHER, REMEMBERED = 1 << 16, 1 << 19
THRESHOLD = 0.7


def windows(text: str | None) -> list[bytes]:
    """The whole text in lower case, cut at the last space of each window's second half, or hard."""
    data = (text or "").lower().encode()
    out, at, n = [], 0, len(data)
    while at < n:
        end = at + WINDOW
        if end < n:
            space = data.rfind(b" ", at + WINDOW // 2, end)
            end = space if space > 0 else end
        out.append(data[at:end])
        at = end
    return out or [b""]


def spaced(found: list[bytes], most: int = TEACH_WINDOWS) -> list[bytes]:
    """At most so many of the windows, evenly spaced over the whole text."""
    return found if len(found) <= most else [found[k * len(found) // most] for k in range(most)]


def train_dictionary(samples: list[bytes]) -> bytes:
    """A zstandard dictionary of distinct windows. They are taken in the order of a hash, so that copies and long documents don't stand together."""
    mixed = sorted(set(samples), key=lambda w: (xxhash.xxh64_intdigest(w), w))
    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, mixed, k=SEGMENT, d=GRAM, steps=1).as_bytes()
    except zstandard.ZstdError:  # too few samples to train on: they are the dictionary
        return b"".join(mixed)[-DICTIONARY_BYTES:]


def compressed(content: bytes) -> Callable[[list[bytes]], list[int]]:
    """A function from windows to the lengths of their frames under a dictionary, each compressed by itself."""
    d = zstandard.ZstdCompressionDict(content or b"\n" * 8)
    d.precompute_compress(level=LEVEL)
    packer = zstandard.ZstdCompressor(level=LEVEL, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False)

    def lengths(found: list[bytes]) -> list[int]:
        out: list[int] = []
        for at in range(0, len(found), TOGETHER):
            some = found[at : at + TOGETHER]
            if "multi_compress_to_buffer" not in zstandard.backend_features or not any(some):  # it refuses to compress nothing
                out += [len(packer.compress(w)) for w in some]
                continue
            size = np.fromiter(map(len, some), np.uint64, len(some))
            places = np.column_stack([np.cumsum(size) - size, size])
            out += map(len, packer.multi_compress_to_buffer(zstandard.BufferWithSegments(b"".join(some), places.tobytes()), threads=1))
        return out

    return lengths


def summary(gains: list[int]) -> list[float]:
    """The features of a document from the gains of its windows."""
    gains = sorted(gains)
    n = len(gains)
    over = [n - bisect_left(gains, k) for k in GAINS]
    return [gains[-1], sum(gains[-3:]) / min(3, n), sum(gains) / n, math.log(n), gains[-1 - n // 10], over[2] / n, *map(math.log1p, over)]


def scorer(ordinary: bytes, toxic: bytes) -> Callable[[list[str | None]], list[list[float]]]:
    """A function from texts to their features. Of windows that repeat among the texts of a task each is compressed once, as long as they are remembered."""
    plain, marked = compressed(ordinary), compressed(toxic)
    gain: dict[bytes, int] = {}

    def features(texts: list[str | None]) -> list[list[float]]:
        if len(gain) > REMEMBERED:
            gain.clear()
        mine = [windows(t) for t in texts]
        found = list(dict.fromkeys(w for ws in mine for w in ws if w not in gain))
        # all windows with one dictionary, then all with the other: their tables would displace each other in the caches
        gain.update(zip(found, map(sub, plain(found), marked(found)), strict=True))
        return [summary([gain[w] for w in ws]) for ws in mine]

    return features


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.01, steps: int = 30) -> tuple[list[float], list[float], list[float]]:
    """(weights with intercept first, means, scales) of a ridge logistic model, by Newton steps."""
    mean, scale = x.mean(axis=0), x.std(axis=0) + 1e-9
    z = np.c_[np.ones(len(x)), (x - mean) / scale]
    w = np.zeros(z.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + ridge * np.eye(len(w)), z.T @ (p - y) + ridge * w)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w.tolist(), mean.tolist(), scale.tolist()


def _teachers(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, text, kind, judges) of the rows that teach. The ids are chosen from the labels alone, so no text is shuffled."""
    one = labels.where("toxic in (0, 1) and doc_id is not null").groupBy("doc_id").agg(F.min("toxic").alias("kind"), F.max("toxic").alias("high"))
    one = one.where((F.col("kind") == F.col("high")) & (F.crc32(F.col("doc_id").cast("string")) % 3 != 1)).withColumn("judges", F.pmod(F.xxhash64(F.lit("part"), "doc_id"), F.lit(10)) < JUDGING)
    ids = None
    for kind in (0, 1):
        for judges, bound in ((False, TEACHERS), (True, JUDGES[kind])):
            some = one.where((F.col("kind") == kind) & (F.col("judges") == judges)).orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound).select("doc_id", "kind", "judges")
            ids = some if ids is None else ids.unionByName(some)
    mine = docs.select(docs["doc_id"].alias("doc_id"), F.coalesce(docs["text"].cast("string"), F.lit("")).alias("text"))
    return mine.join(F.broadcast(ids), "doc_id").select("doc_id", "text", "kind", "judges")


def _told(rows: DataFrame, start: Callable, columns: str, bound: int) -> list:
    """At most ``bound`` rows of an operator on slices of teachers: ids that repeat may give more rows than ids."""
    return map_text(rows, start, columns, together=True).orderBy(F.hash("doc_id"), *[F.hash(c.split()[0]) for c in columns.split(", ")]).limit(bound).select(columns.split()[0]).collect()


def train(docs: DataFrame, labels: DataFrame) -> dict:
    """Dictionaries and calibration from bounded samples of teachers. Only windows of bounded number and features reach the driver."""
    rows = keep(_teachers(docs, labels))  # bounded, and asked for by kind and use: the documents are read once for all

    def cut():
        return lambda texts: [(spaced(windows(t)),) for t in texts]

    samples = {k: [r["w"] for r in _told(rows.where(f"kind = {k} and not judges"), cut, "w array<binary>", TEACHERS)] for k in (0, 1)}
    if not samples[0] or not samples[1]:
        n = {r["kind"]: r["count"] for r in rows.groupBy("kind").count().collect()}
        if not n.get(0) or not n.get(1):
            return {"share": 1.0 if n.get(1) else 0.0}
        samples = {k: samples[k] or [r["w"] for r in _told(rows.where(f"kind = {k}"), cut, "w array<binary>", TEACHERS)] for k in (0, 1)}
    ordinary, toxic = (train_dictionary([bytes(w) for ws in samples[k] for w in ws]) for k in (0, 1))
    held = docs.sparkSession.sparkContext.broadcast((ordinary, toxic))  # two dictionaries of fixed size

    def rate():
        features = scorer(*held.value)
        return lambda texts: [(x,) for x in features(texts)]

    judged = {k: [r["x"] for r in _told(rows.where(f"kind = {k} and judges"), rate, "x array<double>", JUDGES[k])] for k in (0, 1)}
    for k in (0, 1):
        if not judged[k]:
            judged[k] = [r["x"] for r in _told(rows.where(f"kind = {k}"), rate, "x array<double>", TEACHERS)]
    x = np.array(sorted(judged[1]) + sorted(judged[0]))
    y = np.array([1.0] * len(judged[1]) + [0.0] * len(judged[0]))
    return {"ordinary": ordinary, "toxic": toxic, "model": logistic(x, y)}


def toxicity(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """Score and decision for every whole text."""
    held = docs.sparkSession.sparkContext.broadcast(train(docs, labels))  # two dictionaries of fixed size and a few numbers

    def start():
        learnt = held.value
        if "share" in learnt:
            return lambda texts: [(learnt["share"], int(learnt["share"] >= threshold))] * len(texts)
        features = scorer(learnt["ordinary"], learnt["toxic"])
        (bias, *weights), means, scales = learnt["model"]

        def rated(x: list[float]) -> tuple:
            v = bias + sum([w * (f - m) / s for w, f, m, s in zip(weights, x, means, scales, strict=True)])
            score = 1 / (1 + math.exp(-max(-30.0, min(30.0, v))))
            return score, int(score >= threshold)

        return lambda texts: [rated(x) for x in features(texts)]

    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False))
    return map_text(docs, start, "score double, predicted int", together=True).select("doc_id", held_out.alias("held_out"), "score", "predicted")
