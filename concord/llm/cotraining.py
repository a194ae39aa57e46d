"""Quality classification by co-training of two views.

View one reads the text (shape, repetition, symbols), view two the page metadata (language, source, stated length). Both are
ridge logistic models. They learn first from labelled documents; then in each round the documents that one view is confident
about teach the other view as pseudo-labels, weighted so that they count together as much as the labelled ones. Last, a
logistic model over both views' log-odds, learnt from labelled documents, calibrates and combines them.

At most ``TEACHERS`` labelled documents (the least by a hash) teach, on the driver. Everything else covers all documents: a
pass over the text writes the features of every document to a shared table; scaling and each step on pseudo-labels
sum over that whole table, as one array per task that Spark adds up element by element, so only sums whose number the
features fix reach the driver. Documents whose crc32(doc_id) mod 5 is 0 are held out: where they are labelled, neither their labels nor
pseudo-labels of theirs teach; without a label they exchange pseudo-labels like all others.

Defined results: a null text is an empty one; null metadata has its own feature value; documents that are labelled
both ways teach nothing; without teachers of both kinds the score is 0.5 and everything is accepted; rows are
scored one by one, so ids may be null or repeat.
"""

from __future__ import annotations

import gc
import math
import re
import zlib
from collections import Counter
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from concord.llm.rows import no_cycle_search, slices
from concord.runtime import keep

ROUNDS, STEPS, EXCHANGE_STEPS = 2, 25, 3
TEACHERS = 10_000
SETTLED = 0.01
CONFIDENT = 0.95
RIDGE = 1.0
ACCEPT = 0.5
LANGUAGES, SOURCES = 8, 32
MARKS = re.compile(rb"[%&$#*@~^=<>{}\\]{2,}")
DIGITS, PUNCTUATION = b"0123456789", b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"


def content_features(text: str | None) -> list[float]:
    t = text or ""
    b, words, lines = t.encode(), t.split(), t.split("\n")
    n, m = max(1, len(b)), max(1, len(words))
    top = max(Counter(words).values(), default=0)
    return [
        math.log1p(len(b)), math.log1p(len(words)), len(t) / m, len(set(words)) / m, top / m,
        sum(map(eq, words, words[1:])) / m, sum(map(str.isupper, words)) / m, sum(map(str.istitle, words)) / m,
        (len(b) - len(b.translate(None, DIGITS))) / n, (len(b) - len(b.translate(None, PUNCTUATION))) / n,
        b.count(b"|") / m, b.count(b"!") / m, len(MARKS.findall(b)) / m, b.count(b".") / m,
        len(set(lines)) / len(lines), (len(b) - len(t)) / n, math.log1p(max(map(len, words), default=0)),
    ]


N_CONTENT = len(content_features(""))
N_METADATA = 3 + LANGUAGES + SOURCES


def metadata_features(lang: str | None, source: str | None, n_chars: int | None) -> list[float]:
    size = math.log1p(max(0, n_chars)) if n_chars is not None else 0.0
    out = [size, size * size / 10, float(n_chars is None), *([0.0] * (LANGUAGES + SOURCES))]
    if lang is not None:
        out[3 + zlib.crc32(lang.encode()) % LANGUAGES] = 1.0
    if source is not None:
        out[3 + LANGUAGES + zlib.crc32(source.encode()) % SOURCES] = 1.0
    return out


def _matrix(column: pa.Array, width: int) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), width)


def _features(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, held_out, x: features of both views, y: 1, 0 or null where a label may teach, kept: a label is held out) of every row."""

    def run(batches):
        with no_cycle_search():
            for piece in slices(batches):
                text, lang, source, size = (c.to_pylist() for c in piece.columns[1:])
                rows = [content_features(t) + metadata_features(a, s, n) for t, a, s, n in zip(text, lang, source, size, strict=True)]
                yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(rows, pa.list_(pa.float64()))], names=["doc_id", "x"])

    chosen = docs.select("doc_id", docs["text"].cast("string"), docs["lang"].cast("string"), docs["source"].cast("string"), docs["n_chars"].cast("long"))
    made = chosen.mapInArrow(run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, x array<double>")
    taught = labels.where("quality in (0, 1) and doc_id is not null").groupBy("doc_id").agg(F.min("quality").alias("low"), F.max("quality").alias("high"))
    taught = taught.where("low = high").select("doc_id", F.col("low").cast("double").alias("label"))
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False))
    joined = made.join(taught, "doc_id", "left").withColumn("held_out", held)
    return keep(joined.select("doc_id", "held_out", "x", F.when(~F.col("held_out"), F.col("label")).alias("y"), (F.col("held_out") & F.col("label").isNotNull()).alias("kept")))


def _sum(table: DataFrame, part, width: int) -> np.ndarray:
    """Sum over the table of ``part(x, y, kept)``, an array of ``width`` numbers per batch."""

    def run(batches):
        gc.collect()  # what earlier passes of this worker have left; passes are many and short
        total = np.zeros(width)
        for batch in batches:
            if batch.num_rows:
                x = _matrix(batch.column(0), N_CONTENT + N_METADATA)
                total += part(x, batch.column(1).to_numpy(zero_copy_only=False).astype(float), batch.column(2).to_numpy(zero_copy_only=False).astype(bool))
        yield pa.RecordBatch.from_arrays([pa.array([total.tolist()], pa.list_(pa.float64()))], names=["v"])

    each = table.select("x", "y", "kept").mapInArrow(run, "v array<double>")
    summed = each.select(F.posexplode("v").alias("k", "v")).groupBy("k").agg(F.sum("v").alias("v"))
    out = np.zeros(width)
    for r in summed.collect():  # ``width`` rows
        out[r["k"]] = r["v"]
    return out


def _sigmoid(v: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(v, -30, 30)))


def _moments(x: np.ndarray, y: np.ndarray, weight: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Loss, gradient and curvature of the weighted logistic loss, flat."""
    v = x @ w
    p = _sigmoid(v)
    loss = weight @ (np.logaddexp(0, v) - y * v)
    return np.concatenate([[loss], x.T @ (weight * (p - y)), ((x * (weight * p * (1 - p))[:, None]).T @ x).ravel()])


class Descent:
    """Newton's method with step halving: a step that has raised the loss is taken back by half, so few teachers cannot make it diverge."""

    def __init__(self, w: np.ndarray):
        self.w, self.base, self.step, self.loss = w, w, np.zeros_like(w), np.inf
        self.ridge = np.full(len(w), RIDGE)
        self.ridge[0] = 1e-6
        self.prior = w if len(w) == 3 else np.zeros_like(w)
        self.done = False

    def tell(self, flat: np.ndarray) -> None:
        """The sums at ``w``; moves ``w`` on."""
        d, off = len(self.w), self.w - self.prior
        loss = flat[0] + 0.5 * (self.ridge * off) @ off
        if loss <= self.loss + 1e-9:
            h = flat[1 + d :].reshape(d, d) + np.diag(self.ridge)
            self.base, self.loss, self.step = self.w, loss, -np.linalg.solve(h, flat[1 : 1 + d] + self.ridge * off)
        else:
            self.step = self.step / 2
        self.done = loss <= self.loss and np.abs(self.step).max() < SETTLED
        self.w = self.base + self.step


class Model:
    """Scaling, the weights of both views and of their combination."""

    def __init__(self, mean: np.ndarray, scale: np.ndarray):
        self.mean, self.scale = mean, scale
        self.w = [np.zeros(1 + N_CONTENT), np.zeros(1 + N_METADATA)]
        self.both = np.array([0.0, 0.5, 0.5])
        self.taught = False
        self.exchanged: list[tuple[int, int]] = []  # per round, the pseudo-labels that the content and the metadata view have got

    def views(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        z = np.clip((x - self.mean) / self.scale, -10, 10)
        one = np.ones((len(x), 1))
        return np.hstack([one, z[:, :N_CONTENT]]), np.hstack([one, z[:, N_CONTENT:]])

    def odds(self, x: np.ndarray) -> np.ndarray:
        """Columns: 1, log-odds of the content view, of the metadata view."""
        a, b = self.views(x)
        return np.column_stack([np.ones(len(x)), np.clip(a @ self.w[0], -15, 15), np.clip(b @ self.w[1], -15, 15)])

    def score(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Probability of good quality by the content, by the metadata and by both."""
        o = self.odds(x)
        return _sigmoid(o[:, 1]), _sigmoid(o[:, 2]), _sigmoid(o @ self.both)


def _teachers(table: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Features and labels of at most ``TEACHERS`` labelled rows, the least by a hash."""
    rows = table.where("y is not null").orderBy(F.xxhash64("doc_id", "x")).limit(TEACHERS).select("x", "y").toArrow()
    y = rows.column("y").to_numpy().astype(float)
    x = rows.column("x").combine_chunks() if len(y) else None
    return (_matrix(x, N_CONTENT + N_METADATA) if len(y) else np.zeros((0, N_CONTENT + N_METADATA))), y


def train(table: DataFrame) -> Model:
    d = N_CONTENT + N_METADATA
    s = _sum(table, lambda x, y, kept: np.concatenate([[len(x), (np.isnan(y) & ~kept).sum()], x.sum(axis=0), (x * x).sum(axis=0)]), 2 + 2 * d)
    n, free = max(1.0, s[0]), max(1.0, s[1])
    mean = s[2 : 2 + d] / n
    model = Model(mean, np.sqrt(np.maximum(s[2 + d :] / n - mean * mean, 1e-12)) + 1e-6)
    x, y = _teachers(table)
    if not (y == 1).any() or not (y == 0).any():
        return model
    model.taught = True
    views, one = model.views(x), np.ones(len(y))
    size = [len(_moments(v, y, one, w)) for v, w in zip(views, model.w, strict=True)]
    share = min(1.0, len(y) / free)  # pseudo-labels count together as much as the labels

    for round_ in range(ROUNDS + 1):
        teacher = Model(model.mean, model.scale)
        teacher.w = [w.copy() for w in model.w]
        ways = [Descent(w) for w in model.w]
        for _ in range(EXCHANGE_STEPS if round_ else STEPS):
            now = Model(model.mean, model.scale)
            now.w = [way.w for way in ways]

            def part(x, y, kept, teacher=teacher, now=now):
                """The other view's confident answers on documents that nobody has labelled, over all documents."""
                free = np.isnan(y) & ~kept
                said, seen, out = teacher.odds(x), now.views(x), []
                for k in (0, 1):
                    p = _sigmoid(said[:, 2 - k])
                    sure = free & ((p >= CONFIDENT) | (p <= 1 - CONFIDENT))
                    out += [_moments(seen[k], (p > 0.5).astype(float), np.where(sure, share, 0.0), now.w[k]), [sure.sum()]]
                return np.concatenate(out)

            pseudo = _sum(table, part, sum(size) + 2) if round_ else np.zeros(sum(size) + 2)
            ways[0].tell(pseudo[: size[0]] + _moments(views[0], y, one, now.w[0]))
            ways[1].tell(pseudo[size[0] + 1 : -1] + _moments(views[1], y, one, now.w[1]))
            told = (int(pseudo[size[0]]), int(pseudo[-1]))
            if ways[0].done and ways[1].done:
                break
        model.w = [way.base for way in ways]
        if round_:
            model.exchanged.append(told)
    way = Descent(model.both)
    for _ in range(STEPS):
        way.tell(_moments(model.odds(x), y, one, way.w))
        if way.done:
            break
    model.both = way.base
    return model


def fit(docs: DataFrame, labels: DataFrame) -> tuple[Model, DataFrame]:
    """The model and the feature table of the documents."""
    table = _features(docs, labels)
    return train(table), table


def quality(docs: DataFrame, labels: DataFrame, accept: float = ACCEPT) -> DataFrame:
    """(doc_id, held_out, content, metadata, quality, accepted) of every row."""
    model, table = fit(docs, labels)

    def run(batches):
        for batch in batches:
            content, metadata, both = model.score(_matrix(batch.column(2), N_CONTENT + N_METADATA)) if batch.num_rows else (np.zeros(0),) * 3
            cols = [batch.column(0), batch.column(1), pa.array(content), pa.array(metadata), pa.array(both), pa.array((both >= accept) | (not model.taught))]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "held_out", "content", "metadata", "quality", "accepted"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return table.select("doc_id", "held_out", "x").mapInArrow(run, f"doc_id {kind}, held_out boolean, content double, metadata double, quality double, accepted boolean")


def accepted(docs: DataFrame, labels: DataFrame, accept: float = ACCEPT) -> DataFrame:
    """The documents that the classifier accepts; all columns stay, rows are judged where they stand."""
    model, _ = fit(docs, labels)
    if not model.taught:
        return docs
    at = [docs.columns.index(c) for c in ("text", "lang", "source", "n_chars")]

    def run(batches):
        with no_cycle_search():
            for piece in slices(batches):
                text, lang, source, size = (piece.column(k).to_pylist() for k in at)
                x = np.array([content_features(t) + metadata_features(a, s, n) for t, a, s, n in zip(text, lang, source, size, strict=True)])
                yield piece.filter(pa.array(model.score(x)[2] >= accept))

    return docs.mapInArrow(run, docs.schema)
