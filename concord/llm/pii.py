"""Personal data by anchor expansion.

One Aho-Corasick pass finds anchors: at-signs, plus signs, adjoining digits, dotted digits, address schemes and
identifier cues. At each anchor a deterministic local parser expands to the left and right and validates what it
finds. Work is linear in the text: an anchor inside a parsed span of its kind is skipped, and the left expansion
of one anchor never passes the previous anchor of its kind, and user data that has led to no host is not read again.

Kinds: email, ip, card, phone as the leftmost non-overlapping matches of their patterns that validate;
``address`` (a scheme followed by user data and a host), and ``account`` (an IBAN that passes its checksum, or 6 to 20
digits directly behind an account cue). Kinds may overlap each other. Offsets count code points, ends
are exclusive. A null text is an empty one and gives no span; in redaction it stays null.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable
from itertools import product

import ahocorasick
from pyspark.sql import DataFrame

from concord.llm.rows import map_text, replace_text

BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "address", "account")
DIGITS = "0123456789"
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
DOTTED = re.compile(r"[0-9]+(?:\.[0-9]+){3}")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
USER = re.compile(r"[A-Za-z0-9._~%!$&'()*+,;=:-]+")
HOST = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*(?::[0-9]{1,5})?(?:/[^\s\"'<>]*)?")
IBAN = re.compile(r"[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]){11,30}")
NUMBER = re.compile(r"[ :#=.]{0,3}([0-9](?:[ -]?[0-9]){5,19})(?![0-9])")
SCHEMES = ("http://", "https://", "ftp://", "ssh://", "sip:", "mailto:")
CUES = ("account", "Account", "ACCOUNT", "acct", "Acct", "IBAN", "Iban", "iban", "Konto", "konto", "cuenta", "Cuenta", "compte", "Compte")


def luhn(digits: str) -> bool:
    total = 0
    for k, d in enumerate(reversed(digits)):
        v = int(d) * (1 + k % 2)
        total += v - 9 if v > 9 else v
    return total % 10 == 0


def _only_digits(s: str) -> str:
    return "".join([c for c in s if c in DIGITS])


def _iban(text: str, at: int) -> int | None:
    """End of the longest IBAN at a position whose checksum holds."""
    m = IBAN.match(text, at)
    if not m:
        return None
    end = m.end()
    while end - at >= 15:
        plain = text[at:end].replace(" ", "")
        if 15 <= len(plain) <= 34 and text[end - 1] != " " and int("".join(str(int(c, 36)) for c in plain[4:] + plain[:4])) % 97 == 1:
            return end
        end -= 1
    return None


def automaton() -> ahocorasick.Automaton:
    a = ahocorasick.Automaton()
    for x, y in product(DIGITS, DIGITS):
        a.add_word(f"{x}.{y}", ("ip", 2))
        a.add_word(f"{x}{y}", ("card", 1))
        a.add_word(f"{x} {y}", ("card", 2))
        a.add_word(f"{x}-{y}", ("card", 2))
    a.add_word("@", ("email", 0))
    a.add_word("+", ("phone", 0))
    for s in SCHEMES:
        a.add_word(s, ("address", len(s) - 1))
    for s in CUES:
        a.add_word(s, ("account", len(s) - 1))
    a.make_automaton()
    return a


def finder() -> Callable[[str | None], list[tuple[str, int, int]]]:
    """A function from a text to its spans (kind, start, end), in the order of kinds, then of starts."""
    anchors = automaton().iter

    def find(text: str | None) -> list[tuple[str, int, int]]:
        found: dict[str, list[tuple[str, int, int]]] = {k: [] for k in KINDS}
        past = dict.fromkeys(KINDS, 0)
        barren = 0  # user data up to here leads to no host, wherever it begins
        for end, (kind, back) in anchors(text or ""):
            at = end - back
            free = past[kind]
            if at < free:
                continue
            if kind == "email":
                start = at
                while start > free and text[start - 1] in LOCAL:
                    start -= 1
                m = DOMAIN.match(text, at + 1) if start < at else None
                past[kind] = m.end() if m else at + 1  # what stands before a failed at-sign cannot reach over it
                if m:
                    found[kind].append((kind, start, m.end()))
            elif kind == "ip":
                start = at
                while start > free and text[start - 1] in DIGITS:
                    start -= 1
                m = DOTTED.match(text, start)
                if m:
                    past[kind] = m.end()
                    if all(len(p.lstrip("0")) < 4 and int(p.lstrip("0") or 0) < 256 for p in m[0].split(".")):
                        found[kind].append((kind, start, m.end()))
                else:
                    past[kind] = at + 1
            elif kind == "card":
                m = CARD.match(text, at)
                past[kind] = m.end()
                if m.end() - at < 40:
                    digits = _only_digits(m[0])
                    if 13 <= len(digits) <= 19 and luhn(digits):
                        found[kind].append((kind, at, m.end()))
            elif kind == "phone":
                m = PHONE.match(text, at)
                if m:
                    past[kind] = m.end()
                    if 9 <= len(_only_digits(m[0])) <= 15:
                        found[kind].append((kind, at, m.end()))
            elif kind == "address":
                user = USER.match(text, end + 1) if end + 1 >= barren else None
                if user:
                    m = HOST.match(text, user.end())
                    if m:
                        past[kind] = m.end()
                        found[kind].append((kind, at, m.end()))
                    else:
                        barren = user.end()
            else:
                here = end + 1
                while here < len(text) and here < end + 4 and text[here] in " :#=":
                    here += 1
                stop = _iban(text, here)
                m = None if stop else NUMBER.match(text, end + 1)
                start, stop = (here, stop) if stop else m.span(1) if m else (0, 0)
                if stop:
                    past[kind] = stop
                    found[kind].append((kind, start, stop))
        return [s for k in KINDS for s in found[k]]

    return find


SPANS = "n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string"


def personal_data(docs: DataFrame) -> DataFrame:
    """Counts and spans of every whole text."""

    def start():
        find = finder()

        def one(text: str | None) -> tuple:
            spans = find(text)
            listed = [f"{k}:{a}:{b}" for k, a, b in spans]
            base = [s for s, (k, _, _) in zip(listed, spans, strict=True) if k in BASE]
            kinds = [k for k, _, _ in spans]
            return (*(kinds.count(k) for k in BASE), hashlib.sha256(",".join(base).encode()).hexdigest(), ",".join(listed))

        return one

    return map_text(docs, start, SPANS)


def redact(docs: DataFrame, length_col: str | None = None) -> DataFrame:
    """The documents with every span replaced by its kind in brackets; of overlapping spans the union goes, under the first kind.

    Where a text changes, ``length_col`` gets its new length in code points.
    """

    def start():
        find = finder()

        def one(text: str | None) -> str | None:
            spans = sorted(find(text), key=lambda s: (s[1], -s[2]))
            if not spans:
                return text
            out, at = [], 0
            for kind, a, b in spans:
                if a >= at:
                    out += [text[at:a], f"[{kind.upper()}]"]
                at = max(at, b)
            return "".join([*out, text[at:]])

        return one

    return replace_text(docs, start, length_col=length_col)
