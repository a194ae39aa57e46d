"""Document operators on small, awkward tables, against brute force."""

import hashlib
import math
import random
import re
import struct
import zlib
from collections import Counter
from pathlib import Path

import public_tokenizers
import numpy as np
import pytest
import tiktoken
import xxhash
import zstandard
from pyspark.sql import functions as F

from concord.llm import bpe, cotraining, decontamination, gif, license_scan, pii, registry, secret_scan, sharding, simhash, toxicity

SF = "/root/testdata/sf0.01"
VOCABULARY = public_tokenizers.path("byte_bpe_50k.tiktoken")
COLUMNS = "doc_id long, text string, lang string, source string, n_chars long, fp long, row string, label string, shard int, score string, key int"
WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega".split()


def awkward() -> list[tuple]:
    """Nulls in any column, empty, blank and long texts, ties, repeated rows and clashing column names."""
    rnd = random.Random(9)
    texts = [None, "", " \n\t ", "a", "A b", "one two three", "é漢🙂 x\u0085y", "x" * 5000, " ".join(rnd.choice(WORDS) for _ in range(30_000)), "\x00\x7f weird"]
    base = " ".join(rnd.choice(WORDS) for _ in range(400))
    texts += [base, base, base + " end", base.replace(" beta ", " BETA "), base[:1500], base + "\n"]
    rows = [(i, t, "en" if i % 3 else None, f"s{i % 4}" if i % 5 else None, i if i % 2 else None, 1, "r", None, 7, "s", i) for i, t in enumerate(texts)]
    return [*rows, rows[11], rows[11], (None, base, None, None, None, None, None, None, None, None, None), (None, None, *([None] * 9))]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(awkward(), COLUMNS).repartition(3).cache()


def brute_rows(df):
    return [(r["doc_id"], r["text"]) for r in df.select("doc_id", "text").collect()]


def as_counter(rows):
    return Counter(map(repr, rows))


# ---------------------------------------------------------------- media


def test_gif_digest(docs):
    def one(i, t):
        b = (t or "").encode()
        p = b + b"\0" * (-len(b) % 64 or (0 if b else 64))
        return i, len(b), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:])

    got = gif.media_digest(docs).select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32").collect()
    assert as_counter(map(tuple, got)) == as_counter(one(*r) for r in brute_rows(docs))


def test_gif_stored_form_by_hand(docs):
    """The stored bytes from a naive encoder, and the feature from painting pixel by pixel."""

    def lzw(data):
        codes, table, word, width = [(256, 9)], {bytes([i]): i for i in range(256)}, b"", 9
        fresh, size = True, 258  # the reader's dictionary is one entry behind
        for k in range(len(data) + 1):
            longer = word + data[k : k + 1]
            if k < len(data) and longer in table:
                word = longer
                continue
            width = next(w for w in range(9, 13) if size < 1 << w or w == 12)
            codes.append((table[word], width))
            size, fresh = (size if fresh else min(size + 1, 4096)), False
            if k == len(data):
                break
            if len(table) + 2 < 4096:
                table[longer] = len(table) + 2
            else:
                codes.append((256, next(w for w in range(9, 13) if size < 1 << w or w == 12)))
                table, fresh, size = {bytes([i]): i for i in range(256)}, True, 258
            word = data[k : k + 1]
        codes.append((257, next(w for w in range(9, 13) if size < 1 << w or w == 12)))
        value = at = 0
        for code, w in codes:
            value, at = value | code << at, at + w
        return value.to_bytes((at + 7) // 8, "little")

    def one(text):
        body = (text or "").encode()
        p = body + b"\0" * (-len(body) % 64 or (0 if body else 64))
        rows = min(64, len(p) // 64)
        out = b"GIF89a" + struct.pack("<HHBBB", 64, rows, 0xF7, 0, 0) + b"".join(bytes([i & 0xE0, (i << 3) & 0xE0, (i << 6) & 0xC0]) for i in range(256))
        bins, canvas = [0] * 64, [None] * (64 * rows)
        for k in range(0, len(p), 4096):
            part = p[k : k + 4096]
            out += b"\x21\xf9\x04" + struct.pack("<BHB", ((k // 4096) % 3 + 1) * 4 + 1, 10, 0) + b"\0\x2c" + struct.pack("<HHHHB", 0, 0, 64, len(part) // 64, 0) + b"\x08"
            stream = lzw(part)
            out += b"".join(bytes([len(stream[i : i + 255])]) + stream[i : i + 255] for i in range(0, len(stream), 255)) + b"\0"
            before = list(canvas)
            for i, v in enumerate(part):
                canvas[i] = v if v else canvas[i]
            for v in canvas:
                if v is not None:
                    bins[(v >> 6) * 16 + (v >> 3 & 3) * 4 + (v & 3)] += 1
            if (k // 4096) % 3 == 1:
                canvas[: len(part)] = [None] * len(part)
            elif (k // 4096) % 3 == 2:
                canvas = before
        out += b"\x3b"
        return len(out), hashlib.sha256(out).hexdigest(), ",".join(map(str, bins))

    got = gif.media_digest(docs).select("doc_id", "media_bytes", "media_sha256", "feature").collect()
    assert as_counter(map(tuple, got)) == as_counter((i, *one(t)) for i, t in brute_rows(docs))
    assert any(len((t or "").encode()) > 3 * 4096 for _, t in brute_rows(docs))


def test_gif_that_states_too_much(spark):
    head = b"GIF89a" + struct.pack("<HHBBB", 65535, 65535, 0, 0, 0)
    small = b"GIF89a" + struct.pack("<HHBBB", 9, 9, 0, 0, 0)
    frame = b"\x2c" + struct.pack("<HHHHB", 0, 0, 65535, 65535, 0) + b"\x08\x01\x00\x00\x3b"
    assert gif.decode(head + frame).error == "canvas too large" and gif.decode(small + frame).error == "frame larger than its stream"
    rows = gif.frame_table(spark.createDataFrame([(1, head + frame), (2, small + frame)], "id long, gif binary"), "id", "gif").collect()
    assert [(r["id"], r["frame"]) for r in rows] == [(1, None), (2, None)] and all(r["error"] for r in rows)


def test_lzw_round_trip():
    rnd = random.Random(1)
    for n in (1, 2, 255, 256, 4000, 70_000):
        for data in (bytes(n), bytes(rnd.randrange(256) for _ in range(n)), bytes(rnd.choice(b"ab ") for _ in range(n))):
            assert gif.lzw_decode(gif.lzw_pack(gif.lzw_codes(data)), 8, n) == data
            assert b"".join(f.samples for f in gif.decode(gif.encode(data, 64, 16)).frames)[:n] == data


def bits(codes):
    out = "".join(format(c, f"0{w}b")[::-1] for c, w in codes)
    out += "0" * (-len(out) % 8)
    return bytes(int(out[i : i + 8][::-1], 2) for i in range(0, len(out), 8))


def test_lzw_small_codes_and_self_reference():
    # code size 2: clear 4, end 5, first free 6; 6 is used in the step that makes it
    stream = bits([(4, 3), (1, 3), (6, 3), (6, 3), (2, 4), (5, 4)])
    assert gif.lzw_decode(stream, 2, 99) == bytes([1, 1, 1, 1, 1, 2])
    assert gif.lzw_decode(stream[:1], 2, 99) == bytes([1])
    assert gif.lzw_decode(bits([(4, 3), (7, 3)]), 2, 99) == b""


def test_deferred_clear():
    data = bytes(random.Random(2).choice(b"abcdef") for _ in range(60_000))
    table, word, codes = {bytes([i]): i for i in range(256)}, b"", []
    for b in data:  # an encoder that never clears once the dictionary is full
        if word + bytes([b]) in table:
            word += bytes([b])
        else:
            codes.append(table[word])
            if len(table) + 2 < 4096:
                table[word + bytes([b])] = len(table) + 2
            word = bytes([b])
    codes.append(table[word])
    widths = [int(w) for w in gif._widths(len(codes) + 1, 258, 9)]
    stream = bits([(256, 9), *zip([*codes, 257], widths, strict=True)])
    assert gif.lzw_decode(stream, 8, len(data)) == data


def build(frames, width=2, height=2, palette=((255, 0, 0), (0, 255, 0), (0, 0, 255), (9, 9, 9))):
    """A GIF from (left, top, w, h, samples, delay, disposal, transparent, interlaced)."""

    out = b"GIF89a" + struct.pack("<HHBBB", width, height, 0xF1, 0, 0) + bytes(v for c in palette for v in c)
    for left, top, w, h, samples, delay, disposal, transparent, interlaced in frames:
        out += b"\x21\xf9\x04" + struct.pack("<BHB", disposal << 2 | (transparent is not None), delay, transparent or 0) + b"\0"
        body = gif.lzw_pack(gif.lzw_codes(bytes(samples)))
        out += b"\x2c" + struct.pack("<HHHHB", left, top, w, h, 0x40 * interlaced) + b"\x08" + gif._blocks(body)
    return out + b"\x3b"


def test_disposal_transparency_and_times(spark):
    data = build([
        (0, 0, 2, 2, [0, 0, 0, 0], 5, 1, None, False),
        (0, 0, 2, 1, [1, 2], 7, 3, 2, False),  # green over the first pixel, the second is see-through; then restored
        (1, 1, 1, 1, [2], 0, 2, None, False),  # blue in the corner; then cleared
        (0, 0, 1, 1, [3], 0, 0, None, False),
    ])
    shots = [(t, c[..., :3].reshape(-1, 3).tolist(), c[..., 3].reshape(-1).tolist()) for t, c in gif.compose(gif.decode(data))]
    red, green, blue, grey = [255, 0, 0], [0, 255, 0], [0, 0, 255], [9, 9, 9]
    assert [t for t, _, _ in shots] == [0, 5, 12, 12]
    assert [c for _, c, _ in shots] == [[red] * 4, [green, red, red, red], [red, red, red, blue], [grey, red, red, [0, 0, 0]]]
    assert shots[3][2] == [255, 255, 255, 0]
    table = gif.frame_table(spark.createDataFrame([(1, data), (2, None), (3, b"no gif"), (4, data[:60])], "id long, gif binary"), "id", "gif").collect()
    assert [(r["id"], r["frame"], r["start_cs"], r["opaque"]) for r in table if r["id"] == 1] == [(1, 0, 0, 4), (1, 1, 5, 4), (1, 2, 12, 4), (1, 3, 12, 3)]
    assert {r["id"] for r in table} <= {1, 4} and sum(table[0]["histogram"]) == 4


def test_interlace():
    rows = [bytes([k]) for k in range(9)]
    order = [0, 8, 4, 2, 6, 1, 3, 5, 7]
    image = gif.decode(build([(0, 0, 1, 9, b"".join(rows[k] for k in order), 0, 0, None, True)], 1, 9))
    assert image.frames[0].samples == b"".join(rows)


# ---------------------------------------------------------------- near duplicates


def brute_print(text, seed=42):
    t = (text or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
    w = re.findall(r"[^\x20\x09-\x0D]+", t)
    grams = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or ([" ".join(w)] if w else [])
    hs = [xxhash.xxh64_intdigest(g.encode(), seed) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs)) if hs else 0


def brute_components(rows, prints):
    parent = list(range(len(rows)))

    def top(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if (prints[i] ^ prints[j]).bit_count() <= 3:
                parent[top(i)] = top(j)
    least: dict = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            least[top(i)] = min(least.get(top(i), d), d)
    return [least.get(top(i)) for i in range(len(rows))]


def test_simhash_components(docs):
    rows = brute_rows(docs)
    prints = [brute_print(t) for _, t in rows]
    want = [(d, f"{p:016x}", c) for (d, _), p, c in zip(rows, prints, brute_components(rows, prints), strict=True)]
    assert as_counter(map(tuple, simhash.near_duplicates(docs).collect())) == as_counter(want)


def test_simhash_links_all_pairs(spark):
    rnd = random.Random(5)
    prints = set()
    for _ in range(40):
        f = rnd.getrandbits(64)
        for _ in range(12):
            prints.add(f)
            f ^= sum({1 << rnd.randrange(64) for _ in range(rnd.randint(1, 4))})
    signed = lambda f: f - (1 << 64) if f >> 63 else f
    want = {(min(a, b), max(a, b)) for a in map(signed, prints) for b in map(signed, prints) if a != b and ((a ^ b) & (2**64 - 1)).bit_count() <= 3}
    got = [(r["a"], r["b"]) for r in simhash.links(spark.createDataFrame([(signed(f),) for f in prints], "fp long")).collect()]
    assert len(got) == len(set(got)) and set(got) == want and len(want) > 200


def test_first_of_each_keeps_columns_and_one_row(docs):
    kept = simhash.first_of_each(docs)
    assert kept.columns == docs.columns
    ids = [r["doc_id"] for r in kept.select("doc_id").collect()]
    rows = brute_rows(docs)
    comp = brute_components(rows, [brute_print(t) for _, t in rows])
    assert Counter(i for i in ids if i is not None) == Counter({c: 1 for c in comp if c is not None})
    assert ids.count(None) == 2


# ---------------------------------------------------------------- shards


@pytest.mark.parametrize("shards", [1, 3, 40])
def test_sharding_laws(docs, shards):
    rows = sharding.shard(docs, shards).collect()
    n = docs.count()
    assert len(rows) == n and {r["law"] for r in rows} == {"rows"} and {r["grown_shard"] for r in rows} == {None}
    per: dict = {}
    for r in rows:
        per.setdefault(r["shard"], []).append(r["slot"])
    sizes = [len(per.get(k, [])) for k in range(shards)]
    assert max(sizes) - min(sizes) <= 1 and set(per) <= set(range(shards))
    assert all(sorted(s) == list(range(len(s))) for s in per.values())
    want = as_counter((d, len((t or "").encode()) + 16, zlib.crc32((t or "").encode())) for d, t in brute_rows(docs))
    assert as_counter((r["doc_id"], r["size"], r["text_crc32"]) for r in rows) == want


def test_sharding_keeps_groups_and_reads_no_python(spark):
    docs = spark.range(4000).selectExpr("id as doc_id", "case when id % 3 = 0 then 'hot' else concat('t', id div 4) end as text")
    placed = sharding.shard(docs, 10).cache()
    cost = sharding.cut_edges(placed).first()
    assert cost["cut_keys"] <= 10 and cost["linked_keys"] > 500
    assert placed.where("key = md5('hot')").select("shard").distinct().count() <= 5


def test_propagation_moves_rows(spark):
    """Cut pairs by rounds: fewer than without, which is a placement by hash; also where rows have several keys."""
    docs = spark.range(1200).selectExpr("id as doc_id", "concat('t', id % 300) as text")
    by_hash = docs.selectExpr("text as key", "pmod(xxhash64(doc_id), 8) as shard")
    cut = [sharding.cut_edges(sharding.shard(docs, 8, rounds)).first()["cut_pairs"] for rounds in (0, 3)]
    assert cut[1] < cut[0] / 10 and cut[1] < sharding.cut_edges(by_hash).first()["cut_pairs"] / 10
    chain = spark.range(2000).selectExpr("id as row", "explode(array(cast(id div 5 as string), cast((id + 3) div 5 as string))) as key").distinct()
    cost = []
    for rounds in (0, 1, 4):
        placed = sharding.level(sharding.propagate(chain, 8, rounds, overlapping=True), 8, 2000, True).cache()
        sizes = [r["count"] for r in placed.groupBy("shard").count().collect()]
        assert sum(sizes) == 2000 and max(sizes) - min(sizes) <= 1
        cost.append(sharding.cut_edges(chain.join(placed, "row")).first()["cut_pairs"])
    assert cost[2] < cost[1] < cost[0]


# ---------------------------------------------------------------- secrets, licences


def brute_secrets(t):
    word = "".join
    either = lambda w: word(f"[{c}{c.upper()}]" if c.isalpha() else c for c in w)
    names = "|".join([either(w) for w in ("password", "passwd", "secret", "token")] + [either("api") + "_?" + either("key")])
    out = [(m.start(), 0, "assign", m.end()) for m in re.finditer(rf"({names})[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", t) if len(m[2]) >= 6]
    out += [(m.start(), 1, "access", m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", t) if len(m[0]) >= 20]
    out += [(m.start(), 2, "hex", m.end()) for m in re.finditer(r"[0-9a-f]+", t) if len(m[0]) >= 24]
    added = []
    for m in re.finditer(secret_scan.CANDIDATE, t):
        c = m[0]
        if not (re.search("[0-9]", c) and re.search("[A-Za-z]", c)) or re.search(secret_scan.ALLOW, c):
            continue
        least = next(b for p, b in secret_scan.LEAST_BITS if re.search(p, c))
        hot = [k for k in range(len(c) - 19) if -sum(n / 20 * math.log2(n / 20) for n in Counter(c[k : k + 20]).values()) >= least - 1e-9]
        if hot:
            added.append((m.start() + hot[0], 3, "entropy", m.start() + hot[-1] + 20))
    out.sort()
    text = lambda v: ",".join(f"{k}:{a}:{b}" for a, _, k, b in v)
    return [sum(x[1] == k for x in out) for k in range(3)] + [hashlib.sha256(text(out).encode()).hexdigest(), text(sorted(out + added))]


def test_secrets_against_brute_force(spark):
    rnd = random.Random(3)
    bits_ = ['token = "', "PassWord:", "api_key=", "AKIA", "secret", "0123456789abcdef", "ABCDEF0123456789", "xyz+/=_-", "é🙂 ", " ", "\n", '"', "example", "=:"]
    texts = [None, "", "token=token:abcdef", "token=abcdefg 🙂" * 300]
    for _ in range(600):
        texts.append("".join(rnd.choice(bits_) if rnd.random() < 0.5 else "".join(rnd.choice("abcdef0123456789ABCDEFGHXYZxyz+/_") for _ in range(rnd.randint(1, 45))) for _ in range(rnd.randint(0, 8))))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: list(r)[1:] for r in secret_scan.secrets(df).collect()}
    assert all(got[i] == brute_secrets(t or "") for i, t in enumerate(texts))
    assert sum("entropy" in v[4] for v in got.values()) > 100


def test_secrets_by_window(spark):
    rnd = random.Random(8)
    make = lambda n, letters: "".join(rnd.choice(letters) for _ in range(n))
    mixed = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    key = "9F86D081884C7D659A2FEAA0C55AD015A3BF4F1B2B0B822CD15D6C15B0F00A08"
    texts = [f"/srv/examples/{make(40, mixed)}", f"Key={key}", f"b3BlbnNzaC1rZXktdjEAAAAABG5vbmUAAAAEbm9uZQAAAAAAAAABAAAA{make(80, mixed)}", "examplexample1234", "550e8400-e29b-41d4-a716-446655440000", "id550e8400-e29b-41d4-a716-446655440000"]
    bits_ = ["example", "Sample", "dummy", "your_", "xample", "aaaaaaaa", "=", "/", "01234567", "8"]
    for _ in range(250):
        texts.append("".join(rnd.choice(bits_) if rnd.random() < 0.4 else make(rnd.randint(1, 45), rnd.choice((mixed, "0123456789abcdef", "ABCDEF0123456789"))) for _ in range(rnd.randint(1, 6))))

    def spans(t):  # every window for itself; a span ends where a match of the allow-list lies between windows
        out = []
        for m in re.finditer(secret_scan.CANDIDATE, t):
            c = m[0]
            if not (re.search("[0-9]", c) and re.search("[A-Za-z]", c)) or re.search(f"(?i){secret_scan.ALLOWED_WHOLE}", c):
                continue
            bad = {j for p in secret_scan.ALLOWED for k in range(len(c)) if (x := re.compile(f"(?i){p}").match(c, k)) for j in range(k, x.end())}
            last = None
            for k in range(len(c) - 19):
                w = c[k : k + 20]
                least = next(b for p, b in secret_scan.LEAST_BITS if re.search(p, w))
                if bad & set(range(k, k + 20)) or -sum(n / 20 * math.log2(n / 20) for n in Counter(w).values()) < least - 1e-9:
                    continue
                if last is not None and not bad & set(range(last, k)):
                    out[-1][1] = m.start() + k + 20
                else:
                    out.append([m.start() + k, m.start() + k + 20])
                last = k
        return out

    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: [[x["start"], x["end"]] for x in r["added"]] for r in secret_scan.find_secrets(df, by_window=True).collect()}
    assert [got[i] for i in range(len(texts))] == [spans(t) for t in texts]
    assert got[0] and got[1] and got[2][-1][1] > 100 and not got[3] and not got[4]
    assert not any(r["added"] for r in secret_scan.find_secrets(df).where("doc_id < 3").collect())


def test_native_scans_survive_awkward_rows(docs):
    n = docs.count()
    assert secret_scan.secrets(docs).count() == n == license_scan.license_report(docs).count()


def test_licence_rules(spark):
    k = next(i for i, r in enumerate(license_scan.RULES) if r.licence == "Apache-2.0")
    a, b = license_scan.RULES[k].sentences
    texts = {
        1: f"Intro here.\n{a}\n{b} More text.", 2: f"{b} {a}", 3: "released UNDER the mit license!  Licensed under CC BY-NC 4.0.", 4: None, 5: "", 6: "Released under the MIT License.\n" * 3,
    }
    got = {r["doc_id"]: r for r in license_scan.licences(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect()}
    assert {k: r["licenses"] for k, r in got.items()} == {1: "Apache-2.0", 2: "", 3: "CC-BY-NC-4.0,MIT", 4: "", 5: "", 6: "MIT"}
    assert [tuple(h) for h in got[1]["hits"]] == [(k, 1, 2)] and len(got[6]["hits"]) == 3
    early = license_scan.Rule("LONG", ("x y.", "z."))
    rules = (early, license_scan.Rule("SHORT", ("z.",)))
    one = license_scan.licences(spark.createDataFrame([(1, "X y. Z."), (2, "Z.")], "doc_id long, text string"), rules)
    assert {r["doc_id"]: r["licenses"] for r in one.collect()} == {1: "LONG", 2: "SHORT"}


def test_wrapped_licences(spark):
    import textwrap

    texts, want = [], []
    for k, rule in enumerate(license_scan.RULES):
        if "v." in rule.sentences[0]:  # holds the mark of a sentence's end: never wrapped whole
            continue
        for width, mark, end in ((75, "", "\n"), (70, " * ", "\r\n"), (60, "# ", "\n"), (40, "// ", "\n"), (12, "", "\n")):
            body = (mark.rstrip() + end).join(end.join(mark + x for x in textwrap.wrap(("1. " if k == 1 else "") + s, width, break_long_words=False, break_on_hyphens=False)) + end for s in rule.sentences)
            texts.append(f"{mark}Copyright 2020{end}{body}{mark.rstrip()}{end}{mark}more words{end}")
            want.append(rule.licence)
    texts += ["Licensed under the\n\nMIT License.", "Licensed under the.\nMIT License.", "Licensed under the\n *\nMIT License.", "Licensed under\nthe MIT\nLicense. Licensed under the MIT\nLicense.\n"]
    want += ["", "", "", "MIT"]
    got = {r["doc_id"]: r for r in license_scan.licences(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert [got[i]["licenses"] for i in range(len(texts))] == want
    plain = license_scan.RULES.index(license_scan.Rule("MIT", ("Licensed under the MIT License.",)))
    assert [tuple(h) for h in got[len(texts) - 1]["hits"]] == [(plain, 0, 2), (plain, 3, 4)]
    rules = (license_scan.Rule("LONG", ("p q.",)), license_scan.Rule("SHORT", ("q.",)), license_scan.Rule("HEAD", ("p.",)))
    one = license_scan.licences(spark.createDataFrame([(1, "p\nq\nq"), (2, "p\nr\nq")], "doc_id long, text string"), rules)
    assert {r["doc_id"]: [tuple(h) for h in r["hits"]] for r in one.collect()} == {1: [(0, 0, 1), (1, 2, 2)], 2: [(2, 0, 0), (1, 2, 2)]}


def test_long_candidates_and_anchors_take_linear_time(spark):
    import base64
    import random
    import time

    rnd = random.Random(5)
    noise = lambda n: base64.b64encode(rnd.randbytes(n)).decode().replace("=", "A")
    long = noise(300_000) + "example" * 3000 + noise(150_000)
    docs = spark.createDataFrame([(1, long), (2, long[:2000]), (3, "mailto:a" * 100_000), (4, "x" * 300 + noise(40))], "doc_id long, text string")
    began = time.perf_counter()
    got = {r["doc_id"]: r["added"] for r in secret_scan.find_secrets(docs, by_window=True).where("doc_id < 3 or doc_id = 4").collect()}
    assert len(got[1]) == 2 and got[1][0]["start"] < 5 and abs(got[1][0]["end"] - 400_000) < 25 and abs(got[1][1]["start"] - 421_000) < 25
    assert len(got[2]) == 1 and len(got[4]) == 1 and got[4][0]["start"] >= 295
    pii.personal_data(docs).collect()
    assert time.perf_counter() - began < 120


# ---------------------------------------------------------------- tokens


def library():
    ranks = bpe.read_ranks(Path(VOCABULARY).read_bytes())
    return ranks, tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_tokens_against_the_library(docs):
    _, enc = library()

    def one(i, t):
        ids = enc.encode_ordinary(t or "")
        return i, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()

    assert as_counter(map(tuple, bpe.token_digest(docs, VOCABULARY, public_tokenizers.PATTERN).collect())) == as_counter(one(*r) for r in brute_rows(docs))
    coded = bpe.encode_table(docs, VOCABULARY, public_tokenizers.PATTERN)
    assert as_counter((r["doc_id"], r["text"]) for r in bpe.decode_table(coded, VOCABULARY).collect()) == as_counter((i, t or "") for i, t in brute_rows(docs))


def test_tokens_of_random_text(monkeypatch):
    ranks, enc = library()
    rnd = random.Random(6)
    monkeypatch.setattr(bpe, "SETTLE", 7)
    coder = bpe.Encoder(ranks, public_tokenizers.PATTERN)
    for _ in range(3000):
        t = "".join(rnd.choice("abcdeinorst ABT 's  \n\t.,!é漢🙂019") for _ in range(rnd.randint(0, 60)))
        assert coder.encode(t) == enc.encode_ordinary(t)
    for t in ("a" * 5000, "ab" * 999, "é" * 700, "-" * 333, " " * 77):
        assert coder.encode(t) == enc.encode_ordinary(t)


def test_streaming_utf8():
    rnd = random.Random(7)
    for _ in range(3000):
        data = bytes(rnd.choice([65, 0xC3, 0xA9, 0xE2, 0x82, 0xAC, 0xF0, 0x9F, 0x98, 0x80, 0xED, 0xA0, 0xFF, 0xF4, 0x90]) for _ in range(rnd.randint(0, 9)))
        out, rest = "", b""
        for k in range(len(data)):
            more, rest = bpe.utf8_step(rest, data[k : k + 1])
            out += more
        assert out + ("�" if rest else "") == data.decode("utf8", "replace")


# ---------------------------------------------------------------- personal data

PATTERNS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def brute_pii(t):
    def fine(k, s):
        d = re.sub("[^0-9]", "", s)
        return {"email": True, "ip": k != "ip" or all(int(p) < 256 for p in s.split(".")), "card": 13 <= len(d) <= 19 and pii.luhn(d), "phone": 9 <= len(d) <= 15}[k]

    return [(k, m.start(), m.end()) for k, p in PATTERNS.items() for m in re.finditer(p, t) if fine(k, m[0])]


def test_personal_data_against_patterns(docs):
    find, rnd = pii.finder(), random.Random(2)
    for _ in range(20_000):
        t = "".join(rnd.choice(rnd.choice(["0123456789", "@.+- ()", "ab@.1", "4111 1111-1.2.@"])) for _ in range(rnd.randint(0, 60)))
        assert [s for s in find(t) if s[0] in pii.BASE] == brute_pii(t), t
    assert pii.personal_data(docs).count() == docs.count()


def test_personal_data_kinds_and_redaction(spark):
    text = "iban: GB82 WEST 1234 5698 7654 32, account 12345678 https://bob:pw@host.org/x me@x.org or +1 (017) 555-7713 or 4111111111111111 or 10.0.0.1"
    assert [s[0] for s in pii.finder()(text)] == ["email", "email", "ip", "card", "phone", "address", "account", "account"]
    df = spark.createDataFrame([(1, text, len(text)), (2, None, None), (3, "clean text", 99)], "doc_id long, text string, n_chars long")
    got = {r["doc_id"]: r for r in pii.redact(df, "n_chars").collect()}
    assert got[1]["text"] == "iban: [ACCOUNT], account [ACCOUNT] [ADDRESS] [EMAIL] or [PHONE] or [CARD] or [IP]" and got[1]["n_chars"] == len(got[1]["text"])
    assert got[2]["text"] is None and (got[3]["text"], got[3]["n_chars"]) == ("clean text", 99)


# ---------------------------------------------------------------- benchmark windows


def benchmark(spark):
    base = awkward()[10][1]
    items = [("i1", base[:400]), ("i2", "One, two three!"), ("i3", None), ("i4", ""), ("i5", base[:400]), (None, "zeta " * 5), ("i6", "é漢🙂 x")]
    return spark.createDataFrame(items, "item_id string, text string")


def brute_hits(docs, items):
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")))
    wins = [(i, tuple(w[s : s + 13])) for i, t in items for w in [words(t)] if w for s in range(max(1, len(w) - 12))]
    for d, t in docs:
        w, hit, ids = words(t), set(), set()
        places: dict = {}
        for k, x in enumerate(w):
            places.setdefault(x, []).append(k)
        for i, win in wins:
            for s in places.get(win[0], ()):
                if tuple(w[s : s + len(win)]) == win:
                    hit.update(range(s, s + len(win)))
                    if i is not None:
                        ids.add(i)
        yield d, len(w), len(hit), len(ids), hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)


def test_contamination(spark, docs, monkeypatch):
    items = benchmark(spark)
    want = as_counter(brute_hits(brute_rows(docs), [tuple(r) for r in items.collect()]))
    assert as_counter(map(tuple, decontamination.contamination(docs, items).collect())) == want
    whole = decontamination.clean(docs, items)
    monkeypatch.setattr(decontamination, "BROADCAST_BYTES", 60)
    assert as_counter(map(tuple, decontamination.contamination(docs, items).collect())) == want
    assert as_counter(map(tuple, decontamination.clean(docs, items).collect())) == as_counter(map(tuple, whole.collect()))
    assert whole.columns == docs.columns and whole.count() == sum(n for r, n in want.items() if not r.endswith("True)"))
    none = items.where("false")
    assert decontamination.clean(docs, none).count() == docs.count()


# ---------------------------------------------------------------- classifiers


def test_quality_on_held_out_labels(spark):
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    told = cotraining.quality(docs, labels).join(labels.withColumnRenamed("quality", "label"), "doc_id").where("held_out").collect()
    assert len(told) > 50 and sum(r["accepted"] == bool(r["label"]) for r in told) / len(told) > 0.97
    assert cotraining.accepted(docs, labels).columns == docs.columns


def test_unlabelled_documents_all_exchange(spark):
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    few = labels.where("doc_id % 3 = 0")
    free = cotraining._sum(cotraining._features(docs, few), lambda x, y, kept: np.array([(np.isnan(y) & ~kept).sum()], float), 1)
    assert free[0] == docs.join(few.where("quality in (0, 1)"), "doc_id", "left_anti").count() > 0


def test_quality_without_teachers(spark, docs):
    labels = spark.createDataFrame([(1, 1, 0), (1, 0, 0), (None, 1, 0), (2, None, None)], "doc_id long, quality int, toxic int")
    rows = cotraining.quality(docs, labels).collect()
    assert len(rows) == docs.count() and all(r["accepted"] and r["quality"] == 0.5 for r in rows)
    assert cotraining.accepted(docs, labels).count() == docs.count()
    mixed = spark.createDataFrame([(10, 1, 0), (7, 0, 0)], "doc_id long, quality int, toxic int")
    assert cotraining.quality(docs, mixed).count() == docs.count()


def test_toxicity_on_held_out_labels(spark):
    """Words that only toxic texts use, among syllables."""
    import random

    rnd = random.Random(3)
    word = lambda: "".join(rnd.choice(("ba", "ne", "ti", "lo", "sur", "ka", "men", "dro")) for _ in range(rnd.randint(1, 4)))
    line = lambda bad: " ".join(rnd.choice(("grobiank", "twerfling", "schmuxel")) if bad and rnd.random() < 0.06 else word() for _ in range(150))
    rows = [(k, line(k % 4 == 0), 1, int(k % 4 == 0)) for k in range(1200)]
    table = spark.createDataFrame(rows, "doc_id long, text string, quality int, toxic int")
    told = toxicity.toxicity(table.select("doc_id", "text"), table.drop("text")).join(table.select("doc_id", "toxic"), "doc_id").where("held_out").collect()
    found, right = [r for r in told if r["predicted"]], [r for r in told if r["toxic"]]
    assert sum(r["toxic"] for r in found) / len(found) > 0.9 and sum(r["predicted"] for r in right) / len(right) > 0.9
    assert all(0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.7) for r in told)


def test_toxicity_of_many_texts_at_once(monkeypatch):
    """Gains as by compressing window by window; windows that texts share reach each dictionary once, in one call."""
    rnd, asked = random.Random(4), []
    content = [" ".join(rnd.choice(WORDS) for _ in range(400)).encode() for _ in range(2)]
    texts = [r[1] for r in awkward()]
    monkeypatch.setattr(toxicity, "TOGETHER", 97)

    def alone(t):
        lengths = []
        for c in content:
            packer = zstandard.ZstdCompressor(level=15, dict_data=zstandard.ZstdCompressionDict(c), write_content_size=False, write_checksum=False, write_dict_id=False)
            lengths.append([len(packer.compress(w)) for w in toxicity.windows(t)])
        return [a - b for a, b in zip(*lengths, strict=True)]

    assert toxicity.scorer(*content)(texts) == [toxicity.summary(alone(t)) for t in texts]
    assert toxicity.scorer(*content)([None, ""]) == [toxicity.summary(alone(None))] * 2 and toxicity.scorer(*content)([]) == []

    def counting(content, real=toxicity.compressed):
        lengths = real(content)
        return lambda found: (asked.append(list(found)), lengths(found))[1]

    monkeypatch.setattr(toxicity, "compressed", counting)
    features = toxicity.scorer(*content)
    every = sorted({w for t in texts for w in toxicity.windows(t)})
    first = features(texts)
    assert len(asked) == 2 and asked[0] == asked[1] and sorted(asked[0]) == every
    assert features(texts[::-1]) == first[::-1] and asked[2:] == [[], []]  # remembered
    monkeypatch.setattr(toxicity, "REMEMBERED", len(every) - 1)
    assert features(texts) == first and sorted(asked[4]) == sorted(asked[5]) == every  # begun anew


def test_toxicity_by_hand(spark, docs):
    """Dictionaries, calibration and scores again, in plain Python over lists."""
    table = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    marks: dict = {}
    for r in labels.collect():
        marks.setdefault(r["doc_id"], set()).add(r["toxic"])
    texts = {r["doc_id"]: r["text"] or "" for r in table.collect()}
    seeded = lambda i: xxhash.xxh64_intdigest(struct.pack("<q", i), xxhash.xxh64_intdigest(b"part", 42))
    signed = lambda v: v - (1 << 64) if v >> 63 else v
    may = {i: next(iter(m)) for i, m in marks.items() if len(m) == 1 and m <= {0, 1} and zlib.crc32(str(i).encode()) % 3 != 1 and i in texts}
    part = {(k, j): [texts[i] for i in may if may[i] == k and (signed(seeded(i)) % 10 < 3) == j] for k in (0, 1) for j in (False, True)}
    assert all(part.values())

    def learn(some):
        mixed = sorted({w for t in some for w in toxicity.spaced(toxicity.windows(t))}, key=lambda w: (xxhash.xxh64_intdigest(w), w))
        try:
            return zstandard.train_dictionary(1 << 17, mixed, k=12, d=6, steps=1).as_bytes()
        except zstandard.ZstdError:
            return b"".join(mixed)[-(1 << 17) :]

    def length(content):
        d = zstandard.ZstdCompressionDict(content)
        c = zstandard.ZstdCompressor(level=15, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False)
        return lambda w: len(c.compress(w))

    plain, marked = length(learn(part[0, False])), length(learn(part[1, False]))

    def features(t):
        g = sorted((plain(w) - marked(w) for w in toxicity.windows(t)), reverse=True)
        return [g[0], sum(g[:3]) / len(g[:3]), sum(g) / len(g), math.log(len(g)), g[len(g) // 10], sum(x >= 4 for x in g) / len(g), *[math.log1p(sum(x >= k for x in g)) for k in (2, 3, 4, 5, 6, 8, 10)]]

    x = np.array(sorted(map(features, part[1, True])) + sorted(map(features, part[0, True])))
    w, mean, scale = toxicity.logistic(x, np.array([1.0] * len(part[1, True]) + [0.0] * len(part[0, True])))
    some = [i for i in texts if i % 5 == 0]
    got = {r["doc_id"]: r["score"] for r in toxicity.toxicity(table, labels).collect()}
    for i in some:
        v = w[0] + sum(a * (f - m) / s for a, f, m, s in zip(w[1:], features(texts[i]), mean, scale, strict=True))
        assert abs(got[i] - 1 / (1 + math.exp(-max(-30.0, min(30.0, v))))) < 1e-6


def test_quality_by_hand(spark):
    """Co-training again over whole matrices in memory: the same scores, and the exchange changes them."""
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet").where("doc_id % 4 = 0")
    marks: dict = {}
    for r in labels.collect():
        marks.setdefault(r["doc_id"], set()).add(r["quality"])
    rows = docs.collect()
    x = np.array([cotraining.content_features(r["text"]) + cotraining.metadata_features(r["lang"], r["source"], r["n_chars"]) for r in rows])
    held = np.array([zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0 for r in rows])
    mark = np.array([next(iter(marks[r["doc_id"]])) if len(marks.get(r["doc_id"], ())) == 1 else np.nan for r in rows], float)
    y, free = np.where(held, np.nan, mark), np.isnan(mark)
    mean = x.mean(axis=0)
    z = np.clip((x - mean) / (np.sqrt(np.maximum((x * x).mean(axis=0) - mean * mean, 1e-12)) + 1e-6), -10, 10)
    one = np.ones((len(x), 1))
    n = cotraining.N_CONTENT
    view = [np.hstack([one, z[:, :n]]), np.hstack([one, z[:, n:]])]
    taught = ~np.isnan(y)
    sigmoid = lambda v: 1 / (1 + np.exp(-np.clip(v, -30, 30)))

    def newton(a, target, weight, w, steps, prior):
        ridge = np.r_[1e-6, np.ones(len(w) - 1)]
        base, best, step = w, np.inf, None
        for _ in range(steps):
            v, off = a @ w, w - prior
            loss = weight @ (np.logaddexp(0, v) - target * v) + 0.5 * (ridge * off) @ off
            if loss <= best + 1e-9:
                p = sigmoid(v)
                base, best, step = w, loss, -np.linalg.solve((a * (weight * p * (1 - p))[:, None]).T @ a + np.diag(ridge), a.T @ (weight * (p - target)) + ridge * off)
            else:
                step = step / 2
            w = base + step
            yield base, loss <= best and np.abs(step).max() < 0.01

    def both(data, starts, steps):
        runs = [newton(*d, s, steps, np.zeros_like(s)) for d, s in zip(data, starts, strict=True)]
        for state in zip(*runs, strict=True):
            if all(done for _, done in state):
                break
        return [w for w, _ in state]

    def train(rounds):
        ws = both([(v[taught], y[taught], np.ones(taught.sum())) for v in view], [np.zeros(v.shape[1]) for v in view], 25)
        for _ in range(rounds):
            said = [sigmoid(np.clip(v @ w, -15, 15)) for v, w in zip(view, ws, strict=True)]
            data = []
            for k in (0, 1):
                p = said[1 - k]
                sure = free & ((p >= 0.95) | (p <= 0.05))
                use = taught | sure
                data.append((view[k][use], np.where(taught, y, (p > 0.5).astype(float))[use], np.where(taught, 1.0, min(1.0, taught.sum() / free.sum()))[use]))
            ws = both(data, ws, 3)
        odds = np.column_stack([np.ones(len(x))] + [np.clip(v @ w, -15, 15) for v, w in zip(view, ws, strict=True)])
        start = np.array([0.0, 0.5, 0.5])
        for w, done in newton(odds[taught], y[taught], np.ones(taught.sum()), start, 25, start):
            if done:
                break
        return sigmoid(odds @ w)

    want = train(2)
    got = {}
    for r in cotraining.quality(docs, labels).collect():
        got.setdefault(r["doc_id"], []).append(r["quality"])
    assert max(min(abs(g - v) for g in got[r["doc_id"]]) for r, v in zip(rows, want, strict=True)) < 1e-6
    assert np.abs(want - train(0)).max() > 1e-3
    model, _ = cotraining.fit(docs, labels)
    assert len(model.exchanged) == 2 and all(min(pair) > 0 for pair in model.exchanged)


def test_toxicity_without_teachers(spark, docs):
    labels = spark.createDataFrame([(1, 1, 1)], "doc_id long, quality int, toxic int")
    assert {r["score"] for r in toxicity.toxicity(docs, labels.where("false")).collect()} == {0.0}
    rows = toxicity.toxicity(docs, labels).collect()
    assert len(rows) == docs.count()
    held = {r["doc_id"]: r["held_out"] for r in rows}
    assert all(h == (d is not None and zlib.crc32(str(d).encode()) % 3 == 1) for d, h in held.items())


# ---------------------------------------------------------------- empty tables, pipeline


def test_empty_tables(spark, docs):
    none = docs.where("false")
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    for made in (
        gif.media_digest(none), simhash.near_duplicates(none), simhash.first_of_each(none), sharding.shard(none), secret_scan.secrets(none), license_scan.license_report(none),
        bpe.token_digest(none, VOCABULARY, public_tokenizers.PATTERN), pii.personal_data(none), cotraining.quality(none, labels), decontamination.contamination(none, benchmark(spark)),
        toxicity.toxicity(none, labels), decontamination.clean(none, benchmark(spark)), cotraining.accepted(none, labels), pii.redact(none, "n_chars"),
    ):
        assert made.count() == 0


def test_pipeline_on_awkward_rows(spark, docs):
    """Each stage on what the one before kept, and the whole against its parts done by brute force."""
    import corpus_pipeline

    kept = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        kept = stage(spark, kept, SF)
        assert kept.columns == docs.columns, name
    assert corpus_pipeline.STAGES[-1][1](spark, kept, SF).count() == kept.count()


def test_pipeline_stages_in_the_tables(spark):
    import corpus_pipeline

    d = "/root/testdata/sf0.001"
    got = {r["doc_id"]: list(r["ids"]) for r in corpus_pipeline.run(spark, d).collect()}
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    good = {r["doc_id"] for r in cotraining.quality(docs, labels).where("accepted").collect()}
    rows = [(r["doc_id"], r["text"]) for r in docs.collect() if r["doc_id"] in good]
    comp = brute_components(rows, [brute_print(t) for _, t in rows])
    rows = [r for r, c in zip(rows, comp, strict=True) if r[0] == c]
    items = [tuple(r) for r in spark.read.parquet(f"{d}/benchmark.parquet").select(F.col("item_id").cast("string"), "text").collect()]
    clean = {h[0] for h in brute_hits(rows, items) if not h[5]}
    _, enc = library()

    def redacted(t):
        spans, out, at = sorted(pii.finder()(t), key=lambda s: (s[1], -s[2])), "", 0
        for k, a, b in spans:
            if a >= at:
                out += t[at:a] + f"[{k.upper()}]"
            at = max(at, b)
        return out + t[at:]

    assert got == {i: enc.encode_ordinary(redacted(t)) for i, t in rows if i in clean}


def test_registry_names():
    names = set(registry.queries())
    assert {f"op{n}_" for n in range(1, 11)} == {n[: n.index("_") + 1] for n in names if n.startswith("op")} and "pipeline" in names
    assert set(registry.oracle_sql()) <= names
