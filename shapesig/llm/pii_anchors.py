"""Personal data by anchor expansion.

One Aho-Corasick pass over a text finds at-signs, plus signs, digits, URL schemes
and identifier cues; a local parser expands each anchor to its item's boundaries
and validates it, without scanning the rest of the text. The base kinds (email,
ip, card, phone) give what a leftmost, non-overlapping search by their patterns
gives; a match that fails its check is dropped and the search goes on at its end.
The method's own kinds, url and account, are added and never change a base span.

Spans are (kind, start, end) in code points, end exclusive. Defined cases: null
text counts as empty and gives no spans; rows that repeat a doc_id are scanned
each; a null doc_id is returned; extra columns are ignored; an empty table gives
no rows; a text is scanned whole, of any length.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame

from shapesig.llm.common import rows_of

BASE, ADDED = ("email", "ip", "card", "phone"), ("url", "account")

# The patterns of the base kinds, anchored at their first or inner character.
_BEFORE_AT = re.compile(r"[A-Za-z0-9._%+-]+\Z")
_AFTER_AT = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_NOT_DIGIT = re.compile(r"[^0-9]")
_URL = re.compile(r"[A-Za-z0-9.-]+(?::[0-9]+)?(?:[/?#][^\s<>\"']*)?")
_ACCOUNT = re.compile(r"(?:\s*(?:number|no\.?|nr\.?|id|#))?\s*[:=#]?\s*([A-Za-z]{0,4}[0-9][A-Za-z0-9-]{4,33})(?![A-Za-z0-9])", re.IGNORECASE)
CUES = ("account", "acct", "iban", "ssn", "passport", "customer", "konto", "cuenta", "compte")
SCHEMES = ("http://", "https://", "ftp://")


def _automaton() -> ahocorasick.Automaton:
    a = ahocorasick.Automaton()
    a.add_word("@", ("@", 1))
    a.add_word("+", ("+", 1))
    for d in "0123456789":
        a.add_word(d, ("0", 1))
    for s in SCHEMES:
        a.add_word(s, ("url", len(s)))
    for c in CUES:
        for form in (c, c.upper(), c.capitalize()):
            a.add_word(form, ("cue", len(c)))
    a.make_automaton()
    return a


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        n = ord(c) - 48
        if i % 2:
            n = n * 2 - 9 if n > 4 else n * 2
        total += n
    return total % 10 == 0


def iban_like(code: str) -> bool:
    """The ISO 7064 check of codes that begin with two letters and two digits."""
    whole = code[4:] + code[:4]
    return int("".join(str(int(c, 36)) for c in whole.upper())) % 97 == 1


def spans(text: str, machine: ahocorasick.Automaton) -> list[tuple[str, int, int]]:
    """All spans of a text by kind, then start."""
    found: dict[str, list[tuple[int, int]]] = {k: [] for k in BASE + ADDED}
    free = dict.fromkeys(BASE + ADDED, 0)  # where each kind's search stands
    for last, (kind, size) in machine.iter(text):
        at = last - size + 1
        if kind == "0":
            if at >= free["ip"]:
                if m := _IP.match(text, at):
                    free["ip"] = m.end()
                    if all(len(p.lstrip("0")) <= 3 and int(p) <= 255 for p in m[0].split(".")):
                        found["ip"].append(m.span())
                else:  # no other start in this run of digits can match
                    end = at + 1
                    while end < len(text) and "0" <= text[end] <= "9":
                        end += 1
                    free["ip"] = end
            if at >= free["card"]:
                if m := _CARD.match(text, at):
                    free["card"] = m.end()
                    digits = _NOT_DIGIT.sub("", m[0])
                    if 13 <= len(digits) <= 19 and luhn(digits):
                        found["card"].append(m.span())
                else:
                    free["card"] = at + 1
        elif kind == "@":
            if m := _AFTER_AT.match(text, at + 1):
                start = at
                while start > free["email"] and text[start - 1] in _LOCAL:
                    start -= 1
                if start < at:
                    found["email"].append((start, m.end()))
                    free["email"] = m.end()
        elif kind == "+":
            if at >= free["phone"] and (m := _PHONE.match(text, at)):
                free["phone"] = m.end()
                if 9 <= len(_NOT_DIGIT.sub("", m[0])) <= 15:
                    found["phone"].append(m.span())
        elif kind == "url":
            if at >= free["url"] and (m := _URL.match(text, last + 1)) and "." in m[0]:
                end = m.end()
                while text[end - 1] in ".,;:!?)":
                    end -= 1
                found["url"].append((at, end))
                free["url"] = end
        elif at >= free["account"] and (m := _ACCOUNT.match(text, last + 1)) and sum(c.isdigit() for c in m[1]) >= 5:
            code = m[1].replace("-", "")
            if not (code[:2].isalpha() and code[2:4].isdigit() and len(code) >= 15) or iban_like(code):
                found["account"].append(m.span(1))
                free["account"] = m.end(1)
    return [(k, a, b) for k in BASE + ADDED for a, b in found[k]]


def _joined(items: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in items)


def find(docs: DataFrame) -> DataFrame:
    """Per document: counts of the base kinds, the digest of base spans, and all spans."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = _automaton()
        for batch in batches:
            for part in rows_of(batch, "text"):
                counts: list[list[int]] = [[], [], [], []]
                shas, every = [], []
                for text in part.column(1).to_pylist():
                    items = spans(text, machine) if text else []
                    base = [x for x in items if x[0] in BASE]
                    for c, k in zip(counts, BASE, strict=True):
                        c.append(sum(x[0] == k for x in base))
                    shas.append(hashlib.sha256(_joined(base).encode()).hexdigest())
                    every.append(_joined(items))
                yield pa.RecordBatch.from_arrays([part.column(0), *map(pa.array, (*counts, shas, every))], ["doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string")
