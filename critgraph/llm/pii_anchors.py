"""PII: anchor expansion.

An Aho-Corasick automaton finds anchors (at-signs, plus-signs, digits, schemes, cues of
accounts and street names) in one pass over the text; a deterministic local parser expands
each anchor to its boundaries and validates it. Base kinds: email, ip, card, phone. The
method adds url (scheme or www anchor), account (cue, separator, code with digits; a
valid IBAN, with a cue or by its country code) and address (house number beside a street word).

Defined results: null texts are empty and have no spans; offsets are code points of the
whole text, end exclusive; repeated rows are judged alike; other columns are not read.
"""

from __future__ import annotations

import hashlib
import re

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from critgraph.runtime import ship

BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "url", "account", "address")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DIGITS = frozenset("0123456789")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_URL = re.compile(r"[^\s<>\"'(){}\[\]]+")
_CODE = re.compile(r"[\s]{0,3}(?:(?:no|nr|number|id)\b\.?)?[\s]{0,3}[:=#]?[\s]{0,3}[\"']?([A-Za-z0-9][A-Za-z0-9_-]{5,63})", re.I)
_IBAN = re.compile(r"[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]){11,30}")
NEAR, IBAN_MOST = 50, 64  # characters from a cue to a code's start; of a code with all its blanks
_AFTER = re.compile(r"[.,]?\s{1,2}([0-9]{1,5}[a-z]?)\b")
_BEFORE = re.compile(r"([0-9]{1,5}),?\s{1,2}(?:\w{1,30}\s){0,3}$")
#: Cues of accounts and of street names.
ACCOUNT_CUES = ("account", "acct", "iban", "ssn", "passport", "token", "password", "secret", "api_key", "apikey", "konto", "cuenta", "compte", "routing", "swift", "vat", "nif", "dni", "license")
STREET_CUES = ("street", "avenue", "boulevard", "road", "lane", "rue", "chemin", "calle", "avenida", "plaza")
STREET_ENDS = ("straße", "strasse", "platz", "gasse", "allee")
SCHEMES = ("http://", "https://", "ftp://", "www.")


def automaton() -> ahocorasick.Automaton:
    a = ahocorasick.Automaton()
    for d in _DIGITS:
        a.add_word(d, ("d", 1))
    a.add_word("@", ("@", 1))
    a.add_word("+", ("+", 1))
    for kind, cues in (("u", SCHEMES), ("a", ACCOUNT_CUES), ("s", STREET_CUES), ("t", STREET_ENDS)):
        for c in cues:
            for form in {c, c.capitalize(), c.upper()}:
                a.add_word(form, (kind, len(form)))
    a.make_automaton()
    return a


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if i % 2 == 0 else (2 * d - 9 if d > 4 else 2 * d)
    return total % 10 == 0


def iban(code: str) -> bool:
    s = code.replace(" ", "")
    return 15 <= len(s) <= 34 and int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


def iban_end(text: str, start: int, stop: int) -> int | None:
    """Where a valid code that begins at ``start`` ends: at ``stop`` or before a blank within, the farthest that has its checksum."""
    while stop - start >= 15:
        if iban(text[start:stop]):
            return stop
        stop = text.rfind(" ", start, stop)
    return None


def spans(text: str, anchors: ahocorasick.Automaton) -> list[tuple[int, int, int]]:
    """(start, kind's number, end), sorted."""
    out = []
    end = [0] * len(KINDS)
    for last, (kind, size) in anchors.iter(text):
        at = last - size + 1
        if kind == "d":
            if at and text[at - 1] in _DIGITS:
                continue
            if at - 2 >= end[5] and text[at - 2 : at].isupper() and not (at > 2 and text[at - 3].isalnum()) and (m := _IBAN.match(text, at - 2)) and (stop := iban_end(text, at - 2, m.end())):
                out.append((at - 2, 5, stop))
                end[5] = stop
            if at >= end[1] and (m := _IP.match(text, at)):
                end[1] = m.end()
                if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m[0].split(".")):
                    out.append((at, 1, m.end()))
            if at >= end[2] and (m := _CARD.match(text, at)):
                end[2] = m.end()
                digits = m[0].replace(" ", "").replace("-", "")
                if 12 <= len(digits) <= 19 and luhn(digits):
                    out.append((at, 2, m.end()))
        elif kind == "@":
            s = at
            while s > end[0] and text[s - 1] in _LOCAL:
                s -= 1
            if s < at and (m := _DOMAIN.match(text, at + 1)):
                end[0] = m.end()
                out.append((s, 0, m.end()))
        elif kind == "+":
            if at >= end[3] and (m := _PHONE.match(text, at)):
                end[3] = m.end()
                if 9 <= sum(c in _DIGITS for c in m[0]) <= 15:
                    out.append((at, 3, m.end()))
        elif kind == "u":
            if at >= end[4] and (m := _URL.match(text, last + 1)):
                stop = last + 1 + len(m[0].rstrip(".,;:!?"))
                if "." in text[at:stop].partition("://")[2] or text[at : at + 4].lower() == "www.":
                    end[4] = stop
                    out.append((at, 4, stop))
        elif kind == "a":
            if (at and text[at - 1].isalnum()) or at < end[5]:
                continue
            m = _CODE.match(text, last + 1)
            near = _IBAN.search(text, last + 1, last + NEAR + IBAN_MOST)  # the cue bounds where a code starts, not where it ends
            if near and near.start() < last + NEAR and (stop := iban_end(text, near.start(), near.end())):
                out.append((near.start(), 5, stop))
                end[5] = stop
            elif m and sum(c in _DIGITS for c in m[1]) >= 3 and not (m.start(1) == last + 1):
                out.append((m.start(1), 5, m.end(1)))
                end[5] = m.end(1)
        elif at >= end[6] and not (kind == "s" and at and text[at - 1].isalpha()) and (last + 1 == len(text) or not text[last + 1].isalpha()):
            if m := _BEFORE.search(text, max(0, at - 110), at):
                start, stop = m.start(), last + 1
            elif m := _AFTER.match(text, last + 1):
                start, stop = at, m.end(1)
                while start and text[start - 1].isalpha():
                    start -= 1
            else:
                continue
            if start >= end[6]:
                out.append((start, 6, stop))
                end[6] = stop
    out.sort()
    return out


def joined(found: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in found)


def personal_data(docs: DataFrame) -> DataFrame:
    """Per document: doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans."""
    ship(docs.sparkSession)
    schema = "doc_id bigint, n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, base_sha256 string, spans string"

    def run(batches):
        anchors = automaton()
        for b in batches:
            rows = []
            for text in b.column(1).to_pylist():
                found = spans(text, anchors) if text else []
                base = [x for x in found if x[1] < len(BASE)]
                rows.append((*(sum(x[1] == k for x in base) for k in range(len(BASE))), hashlib.sha256(joined(base).encode()).hexdigest(), joined(found)))
            cols = list(zip(*rows)) or [[]] * 6
            yield pa.record_batch([b.column(0), *(pa.array(c, pa.int64()) for c in cols[:4]), *(pa.array(c, pa.string()) for c in cols[4:])], names=[x.split()[0] for x in schema.split(", ")])

    return docs.select(F.col("doc_id").cast("bigint"), F.col("text").cast("string")).mapInArrow(run, schema)


def masked(docs: DataFrame) -> DataFrame:
    """``docs`` with each span of personal data replaced by its kind in angle brackets, all columns kept."""
    ship(docs.sparkSession)
    at = docs.columns.index("text")

    def run(batches):
        anchors = automaton()
        for b in batches:
            out = []
            for text in b.column(at).to_pylist():
                done, parts = 0, []
                for a, k, e in spans(text, anchors) if text else []:
                    if a >= done:
                        parts += [text[done:a], f"<{KINDS[k]}>"]
                        done = e
                out.append(text if text is None else "".join(parts) + text[done:])
            yield b.set_column(at, b.schema.field(at).name, pa.array(out, b.schema.field(at).type))

    return docs.mapInArrow(run, docs.schema)
