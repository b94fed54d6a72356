"""Personal data by anchor expansion.

One Aho-Corasick pass over each whole text finds anchors: at-signs, plus-signs
before a digit, digits, URL schemes and cues such as "password" or "iban".  A
small deterministic parser then expands each anchor to the borders of its
entity and validates it.  Parsers never look twice at what they consumed, so
the work is linear in the text.

Base kinds (email, ip, card, phone) are exactly the leftmost non-overlapping
matches of their patterns; a match that fails validation is dropped and not
tried again.  Extra kinds only add spans: url (with user information), secret,
key, iban, ssn.  Offsets are code points, ends exclusive.

Defined cases: a null or empty text has no entities; repeated rows get equal
results; an empty table gives an empty result; other columns are ignored by
`find_pii` and kept by `redact_pii`.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._spark import bounded_batches
from ._text import trim_memory

BASE_KINDS = ("email", "ip", "card", "phone")
EXTRA_KINDS = ("url", "secret", "key", "iban", "ssn")
KINDS = BASE_KINDS + EXTRA_KINDS

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+").match
_IP = re.compile(r"[0-9]+(?:\.[0-9]+){3}").match
_RUN = re.compile(r"[0-9]+").match
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+").match
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]").match
_DIGITS = re.compile(r"[^0-9]").sub
_URL = re.compile(r"://[^\s/?#@\"'<>]+@[^\s\"'<>]+").match
_SCHEME = re.compile(r"[A-Za-z][A-Za-z0-9+.-]{0,15}$")
_SECRET = re.compile(r"\s{0,2}[=:]\s{0,2}\"?([A-Za-z0-9_+/=-]{8,})").match
_KEY = re.compile(r"AKIA[0-9A-Z]{16}(?![0-9A-Z])").match
_IBAN = re.compile(r"[\s:]{0,3}([A-Z]{2}[0-9]{2}(?: ?[0-9A-Z]{4}){2,7}(?: ?[0-9A-Z]{1,3})?)(?![0-9A-Za-z])").match
_SSN = re.compile(r"[\s:#]{0,3}([0-9]{3}-[0-9]{2}-[0-9]{4})(?![0-9-])").match

_AUTOMATON = None


def _anchors():
    global _AUTOMATON
    if _AUTOMATON is None:
        import ahocorasick

        made = ahocorasick.Automaton()
        made.add_word("@", "@")
        made.add_word("://", ":")
        for d in "0123456789":
            made.add_word(d, "0")
            made.add_word("+" + d, "+")
        for cue in ("password", "Password", "PASSWORD", "passwd", "token", "Token", "TOKEN", "secret", "api_key", "apikey", "API_KEY"):
            made.add_word(cue, "s")
        made.add_word("AKIA", "k")
        for cue in ("IBAN", "Iban", "iban"):
            made.add_word(cue, "b")
        for cue in ("SSN", "ssn"):
            made.add_word(cue, "n")
        made.make_automaton()
        _AUTOMATON = made
    return _AUTOMATON


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        x = ord(d) - 48
        total += x if i % 2 == 0 else (2 * x if x < 5 else 2 * x - 9)
    return total % 10 == 0


def _mod97(iban: str) -> bool:
    moved = iban[4:] + iban[:4]
    return int("".join(str(int(c, 36)) for c in moved)) % 97 == 1


def entities(text: str) -> list[tuple[int, int, int]]:
    """(kind index, start, end) of one text, sorted by kind, then start."""
    found: list[tuple[int, int, int]] = []
    email_end = ip_end = card_end = phone_end = extra_end = 0
    # A digit after "+d" is reported too; hits come in order of their ends.
    for last, what in _anchors().iter(text):
        if what == "0":
            if last >= card_end and (m := _CARD(text, last)):
                card_end = m.end()
                if card_end - last >= 16 and 16 <= len(digits := _DIGITS("", m.group())) <= 19 and luhn(digits):
                    found.append((2, last, card_end))
            if last >= ip_end:
                if m := _IP(text, last):
                    ip_end = m.end()
                    if all(len(p.lstrip("0")) <= 3 and int(p[-4:]) <= 255 for p in m.group().split(".")):
                        found.append((1, last, ip_end))
                else:  # any later start in this run of digits fails the same way
                    ip_end = _RUN(text, last).end()
        elif what == "@":
            if last >= email_end and (m := _DOMAIN(text, last + 1)):
                at = last
                while at > email_end and text[at - 1] in _LOCAL:
                    at -= 1
                if at < last:
                    email_end = m.end()
                    found.append((0, at, email_end))
        elif what == "+":
            if last - 1 >= phone_end and (m := _PHONE(text, last - 1)):
                phone_end = m.end()
                if 8 <= len(_DIGITS("", m.group())) <= 15:
                    found.append((3, last - 1, phone_end))
        elif last >= extra_end:
            kind = span = None
            if what == ":" and (m := _URL(text, last - 2)) and (s := _SCHEME.search(text, max(0, last - 18), last - 2)):
                kind, span = 4, (s.start(), m.end())
            elif what == "s" and (m := _SECRET(text, last + 1)):
                kind, span = 5, m.span(1)
            elif what == "k" and (m := _KEY(text, last - 3)):
                kind, span = 6, m.span()
            elif what == "b" and (m := _IBAN(text, last + 1)) and _mod97(m[1].replace(" ", "")):
                kind, span = 7, m.span(1)
            elif what == "n" and (m := _SSN(text, last + 1)):
                kind, span = 8, m.span(1)
            if span:
                extra_end = span[1]
                found.append((kind, *span))
    found.sort()
    return found


def _find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    kinds = pa.array(KINDS)
    for batch in batches:
        flat, ends = [], [0]
        for text in batch.column("text").to_pylist():
            flat += entities(text)
            ends.append(len(flat))
        kind, start, end = zip(*flat) if flat else ((), (), ())
        spans = pa.StructArray.from_arrays(
            [kinds.take(pa.array(kind, pa.int32())), pa.array(start, pa.int64()), pa.array(end, pa.int64())], names=["kind", "start", "end"]
        )
        yield pa.RecordBatch.from_arrays([batch.column("id"), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), spans)], names=["id", "entities"])
    trim_memory()


def find_pii(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id and entities, an array of (kind, start, end)."""
    bounded_batches(docs.sparkSession)
    base = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    schema = f"id {dict(base.dtypes)['id']}, entities array<struct<kind:string,start:long,end:long>>"
    return base.mapInArrow(_find, schema).withColumnRenamed("id", id_col)


def spans_text(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def redacted(text: str | None) -> str | None:
    """The text with every entity replaced by its kind in brackets; overlaps become one."""
    if not text:
        return text
    out, at = [], 0
    for kind, start, end in sorted(entities(text), key=lambda e: (e[1], -e[2])):
        if start >= at:
            out += [text[at:start], f"[{KINDS[kind].upper()}]"]
        at = max(at, end)
    out.append(text[at:])
    return "".join(out)


def redact_pii(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The same rows and columns with entities replaced; null texts stay null."""
    bounded_batches(docs.sparkSession)

    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            clean = pa.array([redacted(t) for t in batch.column(at).to_pylist()], batch.schema.field(at).type)
            yield pa.RecordBatch.from_arrays([clean if i == at else c for i, c in enumerate(batch.columns)], schema=batch.schema)
        trim_memory()

    return docs.mapInArrow(run, docs.schema)
