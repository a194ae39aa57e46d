"""Byte-level BPE encoding and decoding.

Encoding. ``Transducer`` compiles the merges into a finite-state transducer. Its states are the beginnings of vocabulary tokens:
after some bytes of a pretoken, the longest suffix that may still become a token. The trie's own transitions are compiled, all
others are determinised when a text first asks for them, and kept. In each state few tokens can end; the one
that ends the canonical encoding of what has been read is the one that may follow the token before it. Two tokens
may follow one another if rank-ordered merging of their joined bytes gives back those two; that local condition
makes a token sequence the one that merging gives. A token that may still start must start within the state's suffix,
so lookahead is bounded by the longest token: tokens before the point where the chains of all open starts
meet are emitted (in long pretokens on the way, otherwise at their end).

Decoding. ``StreamDecoder`` runs a UTF-8 state machine over the bytes of each id; the effect of an id in a state is kept, so
decoding is one lookup per id, and text comes out as soon as characters are complete. Ill-formed bytes
come out as U+FFFD, one for each maximal ill-formed part.

Defined results: a null text is encoded like an empty one (no ids); ids may repeat or be null; a null id list decodes to an empty text.
The vocabulary file is a parameter; its bytes go to the executors in one broadcast, whose size is checked.
"""

from __future__ import annotations

import base64
import hashlib
import re
import sys
from itertools import chain
from pathlib import Path

import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from concord.llm.rows import map_text, replace_text, slices

MAX_VOCABULARY_BYTES = 64 << 20
SETTLE = 1 << 12
MAX_CHUNKS = 5 << 17


def read_ranks(data: bytes) -> dict[bytes, int]:
    return {base64.b64decode(a): int(b) for a, b in map(bytes.split, data.splitlines()) if a}


def merge(piece: bytes, ranks: dict[bytes, int], until: int = 1) -> list[int]:
    """Plain rank-ordered merging of one pretoken (down to ``until`` parts): the definition that the transducer must equal."""
    parts = [piece[i : i + 1] for i in range(len(piece))]
    while len(parts) > until:
        best = min(range(len(parts) - 1), key=lambda i: ranks.get(parts[i] + parts[i + 1], 1 << 60))
        joined = parts[best] + parts[best + 1]
        if joined not in ranks:
            break
        parts[best : best + 2] = [joined]
    return [ranks[p] for p in parts]


class Transducer:
    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        self.bytes_of = {i: b for b, i in ranks.items()}
        self.size_of = {i: len(b) for b, i in ranks.items()}
        # vocabulary prefixes are states, the empty one is 1; moves are keyed by state << 8 | byte
        number = {b"": 1}
        self.word = [b"", b""]
        self.moves: dict[int, tuple[int, tuple]] = {}  # to the next state and the (token, size) that can end there, longest first
        for word in sorted(ranks, key=len):
            for k in range(1, len(word) + 1):
                if (start := word[:k]) not in number:
                    number[start] = len(self.word)
                    self.word.append(start)
        self.number = number
        self.follows: dict[int, bool] = {}  # last << 20 | token
        self.made_of: dict[int, tuple[int, int] | None] = {}

    def _halves(self, token: int) -> tuple[int, int] | None:
        """The two tokens whose merge made this one; None for a byte; (-1, -1) if merging never makes it."""
        known = self.made_of.get(token, 0)
        if known == 0:
            word = self.bytes_of[token]
            known = None
            if len(word) > 1:
                parts = merge(word, self.ranks, 2)
                known = tuple(parts) if len(parts) == 2 and self.ranks.get(word) == token else (-1, -1)
            self.made_of[token] = known
        return known

    def _may_follow(self, last: int, token: int) -> bool:
        """Whether rank-ordered merging of the joined bytes leaves just these two tokens.

        Goes back in time over the merges along the seam. At each moment the two parts that touch
        the seam must not merge with each other before the next of them merges on its own side; of
        equal ranks the merge further left comes first.
        """
        seam = last << 20 | token
        ranks, word = self.ranks, self.bytes_of
        fine = self._halves(token) != (-1, -1)
        if last >= 0 and fine:
            a, b, before = last, token, 1 << 60
            while True:
                joined = ranks.get(word[a] + word[b])
                if joined is not None and joined < before:
                    fine = False
                    break
                left, right = self._halves(a), self._halves(b)
                if left is None and right is None:
                    break
                if right is None or (left is not None and a > b):
                    a, before = left[1], a
                else:
                    b, before = right[0], b + 1
        if len(self.follows) > 1 << 20:
            self.follows.clear()
        self.follows[seam] = fine
        return fine

    def _move(self, state: int, byte: int) -> tuple[int, tuple]:
        """Determinise one transition: to the longest suffix that begins a token."""
        read, number, ranks = self.word[state] + bytes([byte]), self.number, self.ranks
        to = next((number[read[k:]] for k in range(len(read)) if read[k:] in number), 1)
        word = self.word[to]
        ends = [(ranks[word[k:]], len(word) - k) for k in range(len(word)) if word[k:] in ranks]
        made = self.moves[state << 8 | byte] = (to, tuple([(t, size) for t, size in ends if self._halves(t) != (-1, -1)]))
        return made

    def _settled(self, last: list[int], at: int, depth: int) -> int:
        """The furthest boundary that every continuation passes: where the chains of all open starts have met."""
        open_ = set(range(at - depth, at + 1))
        while len(open_) > 1:
            far = max(open_)
            open_.discard(far)
            open_.add(far - self.size_of[last[far]])
        return open_.pop()

    def encode(self, piece: bytes) -> list[int]:
        """Ids of one pretoken."""
        whole = self.ranks.get(piece)
        if whole is not None:
            return [whole]
        out: list[int] = []
        state, last, at = 1, [-1], 0  # last: the token that ends at each place since the last settled boundary
        whole = True  # nothing is settled yet: a token that is all of what was read needs no look at its seam
        moves, follows, put = self.moves.get, self.follows.get, last.append
        for byte in piece:
            state, ends = moves(state << 8 | byte) or self._move(state, byte)
            at += 1
            for token, size in ends:
                if size >= at:
                    if size == at and whole:
                        put(token)
                        break
                    if size > at:  # it would start before the last settled boundary
                        continue
                fits = follows(last[at - size] << 20 | token)
                if fits or (fits is None and self._may_follow(last[at - size], token)):
                    put(token)
                    break
            else:
                raise ValueError("the vocabulary does not give every byte string a canonical encoding")
            if at >= SETTLE:
                done = self._settled(last, at, len(self.word[state]))
                if done:
                    out += self._back(last, done)
                    last, at = last[done:], at - done
                    put, whole = last.append, False
        return out + self._back(last, at)

    def _back(self, last: list[int], at: int) -> list[int]:
        out, size_of = [], self.size_of
        while at > 0:
            token = last[at]
            out.append(token)
            at -= size_of[token]
        out.reverse()
        return out


#: A pretoken pattern under which texts may be cut before a space that is followed by a non-space: no piece spans such a place
#: and none looks past it. (Fixed value, the published byte-level pattern.)
CUTTABLE = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
NO_CUT = (None, None)
RUN = re.compile(r" (?:\s|$)").search
MARKS = frozenset(".,;:!?")


class Encoder:
    """Whole texts to ids: split by the pretoken pattern, each piece through the transducer.

    With a cuttable pattern, space-delimited chunks are remembered, in bounded number.
    """

    def __init__(self, ranks: dict[bytes, int], pattern: str, most: int | None = None):
        self.most = most or MAX_CHUNKS
        self.split = regex.compile(pattern).findall
        self.cuttable = pattern == CUTTABLE
        self.machine = Transducer(ranks)
        self.name = {i: str(i) for i in ranks.values()}
        self.chunks: dict[str, tuple] = {}
        self.old: dict[str, tuple] = {}
        self.lines: dict[str, tuple] = {}

    def _whole(self, text: str) -> tuple[list[int], str]:
        ids: list[int] = []
        encode = self.machine.encode
        for piece in self.split(text):
            ids += encode(piece.encode())
        return ids, " ".join([self.name[i] for i in ids])

    def _keep(self, chunk: str, made: tuple) -> tuple:
        """Remember in the young generation; when that is full, it takes the place of the old one."""
        if len(self.chunks) >= self.most:
            self.old, self.chunks = self.chunks, {}
        self.chunks[chunk] = made
        return made

    def _plain(self, letters: str) -> tuple[list[int], str]:
        """A space and letters: one piece."""
        known = self.chunks.get(letters)
        if known is None:
            known = self.old.get(letters)
            if known is None:
                ids = self.machine.encode((" " + letters).encode())
                known = ids, " ".join([self.name[i] for i in ids])
            self._keep(letters, known)
        return known

    def _chunk(self, after_space: str) -> tuple:
        """What no generation's first look has found. Letters are remembered alone, marks and lone line ends are joined to them."""
        if after_space.isalpha():
            return self._plain(after_space)
        if not after_space or after_space[0].isspace():
            return NO_CUT
        if after_space[-1] in MARKS and after_space[:-1].isalpha():  # letters and one mark: two pieces
            ids, names = self._plain(after_space[:-1])
            mark = self.machine.ranks[after_space[-1].encode()]
            return [*ids, mark], f"{names} {self.name[mark]}"
        left, line, right = after_space.partition("\n")
        if line and left and right and not (left[-1].isspace() or right[0].isspace()):  # a lone line end is a piece
            ids, names = self.chunks.get(left) or self._chunk(left)
            more, more_names = self._line(right)
            return ids + more, f"{names} {more_names}"
        known = self.old.get(after_space)
        return self._keep(after_space, known if known is not None else self._whole(" " + after_space))

    def _line(self, text: str) -> tuple[list[int], str]:
        """A line end and what follows it up to the next space."""
        known = self.lines.get(text)
        if known is None:
            if len(self.lines) >= self.most // 4:
                self.lines.clear()
            known = self.lines[text] = self._whole("\n" + text)
        return known

    def chunked(self, text: str) -> list[tuple[list[int], str]]:
        """(ids, ids as text) of consecutive parts of the text."""
        if not self.cuttable or " " not in text:
            return [self._whole(text)] if text else []
        first, *rest = text.split(" ")
        make = self._chunk
        get = self.chunks.get  # of a generation that may become the old one on the way
        made = [get(p) or make(p) for p in rest]
        if not RUN(text):
            return [self._whole(first), *made] if first else made
        joined: list[list] = [[first, None]]
        for part, known in zip(rest, made, strict=True):
            if known is NO_CUT:  # white space in a row: no cut here
                joined[-1] = [f"{joined[-1][0]} {part}", None]
            else:
                joined.append([" " + part, known])
        return [known or self._whole(part) for part, known in joined if part]

    def encode(self, text: str | None) -> list[int]:
        return list(chain.from_iterable([ids for ids, _ in self.chunked(text or "")]))


#: Fixed values of UTF-8: for a lead byte, how many bytes follow and the range of the first of them.
LEADS = {
    **{b: (1, 0x80, 0xBF) for b in range(0xC2, 0xE0)},
    **{b: (2, 0x80, 0xBF) for b in range(0xE1, 0xF0)},
    **{b: (3, 0x80, 0xBF) for b in range(0xF1, 0xF4)},
    0xE0: (2, 0xA0, 0xBF),
    0xED: (2, 0x80, 0x9F),
    0xF0: (3, 0x90, 0xBF),
    0xF4: (3, 0x80, 0x8F),
}


def utf8_step(pending: bytes, more: bytes) -> tuple[str, bytes]:
    """Characters completed by ``more`` after the incomplete character ``pending``, and what is incomplete then."""
    out: list[str] = []
    need, low, high = 0, 0x80, 0xBF
    if pending:
        need, low, high = LEADS[pending[0]]
        if len(pending) > 1:
            need, low, high = need - len(pending) + 1, 0x80, 0xBF
    have = bytearray(pending)
    for b in more:
        if need:
            if low <= b <= high:
                have.append(b)
                need, low, high = need - 1, 0x80, 0xBF
                if not need:
                    out.append(have.decode())
                    have.clear()
                continue
            out.append("�")
            have.clear()
            need = 0
        if b < 0x80:
            out.append(chr(b))
        elif b in LEADS:
            need, low, high = LEADS[b]
            have.append(b)
        else:
            out.append("�")
    return "".join(out), bytes(have)


class StreamDecoder:
    """Incremental ids-to-text; a state is the incomplete character so far."""

    def __init__(self, bytes_of: dict[int, bytes]):
        self.bytes_of = bytes_of
        self.states: dict[bytes, dict[int, tuple]] = {b"": {}}
        self.pending_of = {id(self.states[b""]): b""}
        made = {i: utf8_step(b"", b) for i, b in bytes_of.items()}
        self.whole = {i: text for i, (text, rest) in made.items() if not rest and "\ufffd" not in text}

    def _learn(self, state: dict, token: int) -> tuple:
        text, rest = utf8_step(self.pending_of[id(state)], self.bytes_of[token])
        if rest not in self.states:
            self.states[rest] = {}
            self.pending_of[id(self.states[rest])] = rest
        made = state[token] = (text, self.states[rest])
        return made

    def decode(self, ids) -> str:
        return self.decode_runs([ids])

    def decode_runs(self, runs: list) -> str:
        """Text of consecutive id lists. Tokens that begin and end in the accepting state need no stepping."""
        try:
            return "".join(map(self.whole.__getitem__, chain.from_iterable(runs)))
        except KeyError:  # some token holds a part of a character
            pass
        state, out = self.states[b""], []
        put, learn = out.append, self._learn
        for i in chain.from_iterable(runs):
            text, state = state.get(i) or learn(state, i)
            put(text)
        if state is not self.states[b""]:
            put("\ufffd")
        return "".join(out)


def coders(data: bytes, pattern: str, most: int | None = None) -> tuple[Encoder, StreamDecoder]:
    """Encoder and decoder for a vocabulary file. A worker process keeps them from task to task: what they learn is bounded and only saves time."""
    kept = sys.__dict__.setdefault("_byte_bpe_coders", {})
    key = (hashlib.sha256(data).hexdigest(), pattern, most)
    if key not in kept:
        kept.clear()
        ranks = read_ranks(data)
        kept[key] = Encoder(ranks, pattern, most), StreamDecoder({i: b for b, i in ranks.items()})
    return kept[key]


def vocabulary(spark: SparkSession, path: str):
    """The vocabulary file as a broadcast of its bytes."""
    data = Path(path).read_bytes()
    if len(data) > MAX_VOCABULARY_BYTES:
        raise ValueError(f"{path}: {len(data)} bytes exceed the {MAX_VOCABULARY_BYTES} that are broadcast")
    return spark.sparkContext.broadcast(data)


def encode_table(docs: DataFrame, path: str, pattern: str, most: int = 1 << 17) -> DataFrame:
    """(doc_id, ids array<int>). ``most`` bounds the chunks that a worker remembers, twice over; fewer than alone, as jobs before it have filled memory."""
    held = vocabulary(docs.sparkSession, path)

    def start():
        encoder, _ = coders(held.value, pattern, most)
        return lambda text: (encoder.encode(text),)

    return map_text(docs, start, "ids array<int>")


def decode_table(coded: DataFrame, path: str) -> DataFrame:
    """(doc_id, text) of a table (doc_id, ids)."""
    held = vocabulary(coded.sparkSession, path)
    out = T.StructType([T.StructField("doc_id", coded.schema["doc_id"].dataType), T.StructField("text", T.StringType())])
    arrow = to_arrow_schema(out)

    def run(batches):
        decoder = StreamDecoder({i: b for b, i in read_ranks(held.value).items()})
        for piece in slices(batches):
            texts = [decoder.decode(ids or ()) for ids in piece.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([piece.column(0).cast(arrow.field(0).type), pa.array(texts, type=arrow.field(1).type)], schema=arrow)

    return coded.select("doc_id", "ids").mapInArrow(run, out)


def token_digest(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """Encode every whole text, decode the ids again, and give counts and digests of both."""
    held = vocabulary(docs.sparkSession, path)

    def start():
        encoder, decoder = coders(held.value, pattern)

        def one(text: str | None) -> tuple:
            parts = encoder.chunked(text or "")
            runs = [ids for ids, _ in parts]
            listed = " ".join([names for _, names in parts])
            return sum(map(len, runs)), hashlib.sha256(listed.encode()).hexdigest(), hashlib.sha256(decoder.decode_runs(runs).encode()).hexdigest()

        return one

    return map_text(docs, start, "n_tokens long, ids_sha256 string, decoded_sha256 string")


def round_trip_text(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """The documents with each text encoded and decoded again (what a reader of the ids would see); a null text stays null."""
    held = vocabulary(docs.sparkSession, path)

    def start():
        encoder, decoder = coders(held.value, pattern)
        return lambda text: None if text is None else decoder.decode(encoder.encode(text))

    return replace_text(docs, start)
