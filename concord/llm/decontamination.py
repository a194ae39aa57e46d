"""Benchmark decontamination by a prefix-filtered set join.

Each benchmark item becomes windows of ``width`` consecutive words (one window if it has fewer). A window is a set of
(word, occurrence) tokens, ordered by rarity: how often the word occurs in all documents, ties by the word. A text holds a window only
if it holds every token of it, so a prefix of ``len - required + 1`` tokens must be hit; for whole windows
that is the rarest word alone. Documents are joined with the windows on these prefix tokens. A match at
document position p of a token at window offset o can only mean an occurrence that starts at p - o: the
positional and length bounds keep those that fit into the document, and the words are compared one by one.

Up to ``BROADCAST_BYTES`` of item text the windows travel to the documents as one index, so that these never shuffle. Larger
benchmarks are joined by Spark: windows stay a table, documents in two passes (word counts, tokens) emit only the words that a filter of
fixed size (``FILTER_BITS``) lets through, each with the words around it, and the join on the prefix token
verifies a window against these. A frequent word's partition can be split, as the window side of a word is small.

Defined results: null texts have no words; items without words have no windows; equal windows of several items count
for each; null item ids are left out of the item list but their words count as hit; ids may repeat.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter, defaultdict
from collections.abc import Callable

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from concord.llm.rows import map_text, no_cycle_search, slices
from concord.runtime import keep

WIDTH = 13
BROADCAST_BYTES = 4 << 20
FILTER_BITS = 27
LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")
WORDS = re.compile(rb"[0-9a-z\x80-\xff]+").findall  # of UTF-8: bytes from 80 on belong to characters beyond ASCII


def words(text: str | None) -> list[bytes]:
    return WORDS((text or "").encode().translate(LOWER))


def word_counts(docs: DataFrame, vocabulary: set[bytes]) -> dict[bytes, int]:
    """Occurrences in all documents of each word of a bounded vocabulary (one row per word and task is shuffled)."""
    held = docs.sparkSession.sparkContext.broadcast(vocabulary)

    def run(batches):
        known, seen = held.value, Counter()
        for piece in slices(batches):
            for text in piece.column(0).to_pylist():
                seen.update(filter(known.__contains__, words(text)))
        yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.binary()), pa.array(list(seen.values()), pa.int64())], names=["word", "n"])

    counted = docs.select(docs["text"].cast("string")).mapInArrow(run, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))
    return {bytes(r["word"]): r["n"] for r in counted.collect()}  # at most one row per benchmark word


def windows(items: list[tuple[str | None, list[bytes]]], width: int) -> dict[tuple[bytes, ...], list[str | None]]:
    """The distinct windows with the ids of their items."""
    out: dict[tuple[bytes, ...], list] = defaultdict(list)
    for item, w in items:
        for at in range(max(1, len(w) - width + 1) if w else 0):
            out[tuple(w[at : at + width])].append(item)
    return out


def index(items: list[tuple[str | None, list[bytes]]], width: int, counts: dict[bytes, int]) -> dict[bytes, list]:
    """Prefix token -> (offset of its word in the window, window, item ids)."""
    out: dict[bytes, list] = defaultdict(list)
    for window, ids in windows(items, width).items():
        at = min(range(len(window)), key=lambda k: (counts.get(window[k], 0), window[k]))
        out[window[at]].append((at, window, tuple(set(ids))))
    return dict(out)


def matcher(prefix: dict[bytes, list]) -> Callable[[list[bytes]], tuple[list[tuple[int, int]], set]]:
    """A function from the words of a document to its hit intervals (merged, ends exclusive) and the items that occur."""
    known = prefix.__contains__

    def match(doc: list[bytes]) -> tuple[list[tuple[int, int]], set]:
        n, spans, items = len(doc), set(), set()
        for p in [k for k, w in enumerate(doc) if known(w)]:
            for offset, window, ids in prefix[doc[p]]:
                start = p - offset
                if start >= 0 and start + len(window) <= n and doc[start] == window[0] and tuple(doc[start : start + len(window)]) == window:
                    spans.add((start, start + len(window)))
                    items.update(ids)
        return merged(spans), items

    return match


def merged(spans) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def _row(n: int, spans, items) -> tuple:
    hit = sum(b - a for a, b in spans)
    ids = sorted(str(i) for i in items if i is not None)
    return n, hit, len(ids), hashlib.sha256(",".join(ids).encode()).hexdigest(), hit > 0 and 20 * hit >= n


HITS = "n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean"


def _small(benchmark: DataFrame) -> bool:
    return (benchmark.agg(F.sum(F.octet_length("text"))).first()[0] or 0) <= BROADCAST_BYTES


def _load(block: DataFrame) -> list[tuple[str | None, list[bytes]]]:
    rows = block.select(F.col("item_id").cast("string").alias("item_id"), F.col("text").cast("string").alias("text"))
    return [(r["item_id"], words(r["text"])) for r in rows.toLocalIterator()]


def _prepared(docs: DataFrame, block: DataFrame, width: int):
    """The prefix index as a broadcast; its size is bounded by the text of a small benchmark."""
    items = _load(block)
    return docs.sparkSession.sparkContext.broadcast(index(items, width, word_counts(docs, {w for _, ws in items for w in ws})))


SPANS = "array<struct<a:long,b:long>>"


def _filter(vocabulary: DataFrame):
    """A broadcast Bloom filter, of fixed size, of a column ``word``: a bit for a word's hash."""
    bit = F.shiftrightunsigned(F.xxhash64(F.col("word").cast("binary")), 64 - FILTER_BITS)
    slots = vocabulary.select(bit.alias("bit")).groupBy(F.shiftright("bit", 3).alias("slot")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("bit").bitwiseAND(F.lit(7)).cast("int"))).alias("bits"))
    table = np.zeros(1 << FILTER_BITS - 3, dtype=np.uint8)
    told = slots.toArrow()  # one row a byte of the filter at most
    table[told.column("slot").to_numpy()] = told.column("bits").to_numpy()
    return vocabulary.sparkSession.sparkContext.broadcast(table.tobytes())


def _holds(table: bytes) -> Callable[[bytes], int]:
    digest, shift = xxhash.xxh64_intdigest, 64 - FILTER_BITS

    def holds(word: bytes) -> int:
        bit = digest(word, 42) >> shift
        return table[bit >> 3] >> (bit & 7) & 1

    return holds


def _item_windows(benchmark: DataFrame, width: int) -> DataFrame:
    """(item, win, len) with win the words of a window, space-joined."""

    def run(batches):
        for piece in slices(batches):
            for item, text in zip(piece.column(0).to_pylist(), piece.column(1).to_pylist(), strict=True):
                w = [x.decode() for x in words(text)]
                n = max(1, len(w) - width + 1) if w else 0
                for at in range(0, n, 4096):
                    wins = [" ".join(w[k : k + width]) for k in range(at, min(n, at + 4096))]
                    yield pa.RecordBatch.from_arrays([pa.array([item] * len(wins), pa.string()), pa.array(wins, pa.string()), pa.array([min(len(w), width)] * len(wins), pa.int32())], names=["item", "win", "len"])

    return benchmark.select(benchmark["item_id"].cast("string"), benchmark["text"].cast("string")).mapInArrow(run, "item string, win string, len int")


def _counted(texts: DataFrame, vocabulary: DataFrame) -> DataFrame:
    """(word, n): occurrences in all documents of every word of a vocabulary."""
    held = _filter(vocabulary)

    def run(batches):
        holds, seen = _holds(held.value), Counter()
        for piece in slices(batches):
            for text in piece.column(0).to_pylist():
                seen.update(w for w in words(text) if holds(w))
            if len(seen) > 1 << 18:
                yield pa.RecordBatch.from_arrays([pa.array([w.decode() for w in seen], pa.string()), pa.array(list(seen.values()), pa.int64())], names=["word", "n"])
                seen.clear()
        yield pa.RecordBatch.from_arrays([pa.array([w.decode() for w in seen], pa.string()), pa.array(list(seen.values()), pa.int64())], names=["word", "n"])

    some = texts.mapInArrow(run, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))
    return vocabulary.join(some, "word", "left").select("word", F.coalesce("n", F.lit(0)).alias("n"))


def _with_hits(docs: DataFrame, benchmark: DataFrame, width: int) -> tuple[DataFrame, str, str]:
    """For large benchmarks: the documents with the spans and the items of their hits, in two columns whose names are given."""
    row, spans, ids = (name + "_" * max(map(len, docs.columns)) for name in ("row", "spans", "ids"))  # longer than any column's name
    numbered = keep(docs.withColumn(row, F.monotonically_increasing_id()))
    texts = numbered.select(numbered[row].alias("row"), numbered["text"].cast("string").alias("text"))
    every = keep(_item_windows(benchmark, width))
    wins = every.select("win", "len").distinct()
    placed = wins.select("win", "len", F.posexplode(F.split("win", " ")).alias("at", "word"))
    counted = _counted(texts.select("text"), placed.select("word").distinct())
    rarest = placed.join(counted, "word").groupBy("win", "len").agg(F.min(F.struct("n", "word", "at")).alias("m"))
    prefix = keep(rarest.select("win", "len", "m.word", "m.at"))
    held = _filter(prefix.select("word").distinct())

    def tokens(batches):
        holds = _holds(held.value)
        for piece in slices(batches):
            for key, text in zip(piece.column(0).to_pylist(), piece.column(1).to_pylist(), strict=True):
                w = [x.decode() for x in words(text)]
                at = [k for k, x in enumerate(w) if holds(x.encode())]
                for k in range(0, len(at), 4096):
                    some = at[k : k + 4096]
                    lead = [min(p, width - 1) for p in some]
                    around = [" ".join(w[p - n : p + width]) for p, n in zip(some, lead, strict=True)]
                    yield pa.RecordBatch.from_arrays(
                        [pa.array([key] * len(some), pa.int64()), pa.array(some, pa.int64()), pa.array([w[p] for p in some], pa.string()), pa.array(lead, pa.int32()), pa.array(around, pa.string())],
                        names=["row", "pos", "word", "lead", "around"],
                    )

    near = texts.mapInArrow(tokens, "row long, pos long, word string, lead int, around string")
    same = F.array_join(F.slice(F.split("around", " "), F.col("lead") - F.col("at") + 1, F.col("len")), " ") == F.col("win")
    met = near.join(prefix, "word").where(F.col("lead") >= F.col("at")).where(same)  # the positional bound, then the words
    met = keep(met.select("row", (F.col("pos") - F.col("at")).alias("a"), "len", "win").distinct())
    where = met.groupBy("row").agg(F.collect_set(F.struct("a", (F.col("a") + F.col("len")).alias("b"))).cast(SPANS).alias(spans))
    items = every.where("item is not null").select("win", "item").distinct()
    whose = met.select("row", "win").distinct().join(items, "win").groupBy("row").agg(F.collect_set("item").alias(ids))
    hits = where.join(whose, "row", "left").withColumnRenamed("row", row)
    return numbered.join(hits, row, "left").select(*docs.columns, spans, ids), spans, ids


def contamination(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH) -> DataFrame:
    """Per document: words, words inside occurrences of benchmark windows, items that occur, verdict (a twentieth of the words or more)."""
    docs = docs.select("doc_id", docs["text"].cast("string").alias("text"))
    if _small(benchmark):
        held = _prepared(docs, benchmark, width)

        def start():
            match = matcher(held.value)

            def one(text: str | None) -> tuple:
                doc = words(text)
                return _row(len(doc), *match(doc))

            return one

        return map_text(docs, start, HITS)

    def unite(batches):
        for piece in slices(batches):
            made = [_row(len(words(t)), merged((s["a"], s["b"]) for s in spans or ()), set(ids or ())) for t, spans, ids in zip(*(c.to_pylist() for c in piece.columns[1:]), strict=True)]
            yield pa.RecordBatch.from_arrays([piece.column(0), *(pa.array(list(c)) for c in zip(*made, strict=True))], names=["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"])

    return _with_hits(docs, benchmark, width)[0].mapInArrow(unite, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, {HITS}")


def clean(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, least_share: int = 20) -> DataFrame:
    """The documents that are not contaminated: less than 1/least_share of their words stand inside benchmark windows. All columns stay."""
    at = docs.columns.index("text")
    held = _prepared(docs, benchmark, width) if _small(benchmark) else None

    def run(batches):
        with no_cycle_search():
            match = matcher(held.value) if held else None
            for piece in slices(batches):
                texts = [words(t) for t in piece.column(at).to_pylist()]
                if match:
                    spans = [match(doc)[0] for doc in texts]
                else:
                    spans = [merged((s["a"], s["b"]) for s in x or ()) for x in piece.column(len(piece.columns) - 2).to_pylist()]
                hits = [sum(b - a for a, b in x) for x in spans]
                kept = pa.array([not (hit and least_share * hit >= len(doc)) for hit, doc in zip(hits, texts, strict=True)], pa.bool_())
                left = piece.filter(kept)
                yield left if match else pa.RecordBatch.from_arrays(left.columns[:-2], names=left.schema.names[:-2])

    return (docs if held else _with_hits(docs, benchmark, width)[0]).mapInArrow(run, docs.schema)


ORACLE = """
WITH d AS (
  SELECT row_number() OVER () AS r, doc_id,
    regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM documents),
b AS (
  SELECT item_id,
    regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM benchmark),
bw AS (
  SELECT DISTINCT item_id, least(len(w), 13) AS k, array_to_string(w[s:s + 12], ' ') AS g
  FROM b, LATERAL (SELECT unnest(range(1, greatest(len(w) - 12, 1) + 1)) AS s) WHERE len(w) > 0),
dw AS (
  SELECT r, s, k, array_to_string(w[s:s + k - 1], ' ') AS g
  FROM d, (SELECT DISTINCT k FROM bw), LATERAL (SELECT unnest(range(1, len(w) - k + 2)) AS s)),
m AS (SELECT r, s, bw.k, item_id FROM dw JOIN bw USING (k, g)),
h AS (SELECT r, count(DISTINCT p) AS n FROM m, LATERAL (SELECT unnest(range(s, s + k)) AS p) GROUP BY r),
i AS (SELECT r, list_sort(list(DISTINCT CAST(item_id AS VARCHAR))) AS ids FROM m GROUP BY r)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n, 0) AS BIGINT) AS n_hit, CAST(coalesce(len(ids), 0) AS BIGINT) AS n_items,
  sha256(coalesce(array_to_string(ids, ','), '')) AS items_sha256, coalesce(n, 0) > 0 AND 20 * coalesce(n, 0) >= len(w) AS contaminated
FROM d LEFT JOIN h USING (r) LEFT JOIN i USING (r)
"""
