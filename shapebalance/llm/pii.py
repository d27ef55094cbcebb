"""Personal data: regular expressions propose spans, checksums confirm them, context words adjust their scores.

Four base kinds (email, ip, card, phone) are kept wherever their rule holds; a score tells how sure they are. Account
numbers with a mod-97 check and local phone numbers are added where their score reaches `least`.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import ship, text_slices
from .spans import SPANS, Span, digests, in_order, scan

BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "iban", "local_phone")
LEAST = 0.6
#: Characters before a span that are searched for context words, and after it.
BEFORE, AFTER = 48, 16
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?= ?[A-Z0-9])")
_IBAN_RUN = {n: re.compile(rf"[A-Z]{{2}}[0-9]{{2}}(?: ?[A-Z0-9]){{{n - 4}}}(?![A-Za-z0-9])") for n in range(15, 35)}
# Characters of an international account number by country.
_IBAN_LENGTH = {
    "AD": 24, "AE": 23, "AL": 28, "AT": 20, "AZ": 28, "BA": 20, "BE": 16, "BG": 22, "BH": 22, "BR": 29, "BY": 28, "CH": 21, "CR": 22, "CY": 28, "CZ": 24, "DE": 22, "DK": 18, "DO": 28, "EE": 20, "EG": 29,
    "ES": 24, "FI": 18, "FO": 18, "FR": 27, "GB": 22, "GE": 22, "GI": 23, "GL": 18, "GR": 27, "GT": 28, "HR": 21, "HU": 28, "IE": 22, "IL": 23, "IQ": 23, "IS": 26, "IT": 27, "JO": 30, "KW": 30, "KZ": 20,
    "LB": 28, "LC": 32, "LI": 21, "LT": 20, "LU": 20, "LV": 21, "LY": 25, "MC": 27, "MD": 24, "ME": 22, "MK": 19, "MR": 27, "MT": 31, "MU": 30, "NL": 18, "NO": 15, "PK": 24, "PL": 28, "PS": 29, "PT": 25,
    "QA": 29, "RO": 24, "RS": 22, "SA": 24, "SC": 31, "SE": 24, "SI": 19, "SK": 24, "SM": 27, "ST": 25, "SV": 28, "TL": 23, "TN": 24, "TR": 26, "UA": 29, "VA": 22, "VG": 24, "XK": 20,
}
_OWN = re.compile(r"(?<![0-9+(])\(?0[0-9][0-9 ()/-]{6,14}[0-9](?![0-9])")
_WORDS = {
    "email": re.compile("e-?mail|contact|write to|kontakt|correo|courriel", re.I),
    "ip": re.compile(r"\bip\b|address|host|server|login", re.I),
    "card": re.compile("card|credit|visa|payment|karte|carte|tarjeta", re.I),
    "phone": re.compile("phone|tel|call|mobile|fax|anruf|llam", re.I),
    "iban": re.compile("iban|account|bank|konto|compte|cuenta", re.I),
    "local_phone": re.compile(r"phone|\btel\b|\btel[.:]|call|mobile|\bfax\b|telefon|téléphone|teléfono", re.I),
}
#: Score of the pattern alone, what a passed checksum adds, what a context word adds.
_SCORES = {"email": (0.8, 0.0, 0.2), "ip": (0.6, 0.1, 0.3), "card": (0.3, 0.4, 0.3), "phone": (0.6, 0.1, 0.3), "iban": (0.2, 0.6, 0.2), "local_phone": (0.35, 0.0, 0.3)}


def luhn(digits: str) -> bool:
    doubled = (0, 2, 4, 6, 8, 1, 3, 5, 7, 9)
    return sum(doubled[int(d)] if i % 2 else int(d) for i, d in enumerate(reversed(digits))) % 10 == 0


def mod97(code: str) -> bool:
    """The check of international account numbers: moved by four places and read in base 36, the rest by 97 is 1."""
    code = code.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in code[4:] + code[:4])) % 97 == 1


def _digits(text: str) -> str:
    return "".join(c for c in text if "0" <= c <= "9")


def _emails(text: str) -> list[tuple[int, int]]:
    """From each @: the run of local characters before it, back to the match before, and the domain after it."""
    out, done, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at) if start < at else None
        if m:
            done = m.end()
            out.append((start, done))
        at = text.find("@", m.end() if m else at + 1)
    return out


def _account_numbers(text: str) -> list[tuple[int, int]]:
    """Account numbers that pass mod-97: of the country's length, or for other countries the longest such run of whole words."""
    out, done = [], 0
    for m in _IBAN.finditer(text):
        start = m.start()
        if start < done:
            continue
        known = _IBAN_LENGTH.get(text[start : start + 2])
        # for other countries, any end that cuts no word, the last one first
        for n in (known,) if known else range(34, 14, -1):
            run = _IBAN_RUN[n].match(text, start)
            if run and mod97(run[0]):
                out.append(run.span())
                done = run.end()
                break
    return out


def find_personal(text: str, least: float = LEAST) -> list[Span]:
    """All spans of a text by start, then kind. An added span that overlaps a base one is left out, but for account numbers."""
    found = [(s, e, "email", False) for s, e in _emails(text)]
    for m in _CARD.finditer(text):  # any two digits in a row or apart by one mark, so ip and account numbers too
        d = _digits(m[0])
        if 14 <= len(d) <= 19 and luhn(d):
            found.append((*m.span(), "card", True))
    if "." in text:
        found += [(*m.span(), "ip", True) for m in _IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0")[:4] or 0) <= 255 for p in m[0].split("."))]
    if "+" in text:
        found += [(*m.span(), "phone", True) for m in _PHONE.finditer(text) if 10 <= len(_digits(m[0])) <= 15]
    base = list(found)
    found += [(*span, "iban", True) for span in _account_numbers(text)]
    for m in _OWN.finditer(text) if "0" in text else ():
        if 9 <= len(_digits(m[0])) <= 12 and not any(s < m.end() and m.start() < e for s, e, *_ in base):
            found.append((*m.span(), "local_phone", False))
    out = []
    for s, e, kind, checked in found:
        alone, check, near = _SCORES[kind]
        score = alone + check * checked + near * bool(_WORDS[kind].search(text[max(0, s - BEFORE) : s] + " " + text[e : e + AFTER]))
        if kind in BASE or score >= least:
            out.append((s, e, kind, round(score, 4)))
    return in_order(out, KINDS)


def personal_spans(docs: DataFrame, least: float = LEAST) -> DataFrame:
    """doc_id, spans (kind, start, end, score) of every row of docs (doc_id, text; other columns are ignored).

    Null or empty text has no spans; repeated rows and null doc_ids pass through; an empty table gives an empty one.
    Narrow: no shuffle, memory for one Arrow batch.
    """
    return scan(docs, lambda text: find_personal(text, least))


def personal_digests(docs: DataFrame) -> DataFrame:
    """doc_id, counts of the base kinds, base_sha256, spans of every row, as personal_spans() finds them; null and empty texts count 0."""
    return digests(personal_spans(docs), BASE)


def redact(text: str, least: float = LEAST) -> str:
    """The text with each span replaced by its kind in brackets; overlapping spans become one, named by the first."""
    out, at = [], 0
    merged: list[list] = []
    for s, e, kind, _ in find_personal(text, least):
        if merged and s < merged[-1][1]:
            merged[-1][1] = max(merged[-1][1], e)
        else:
            merged.append([s, e, kind])
    for s, e, kind in merged:
        out += [text[at:s], f"[{kind.upper()}]"]
        at = e
    return "".join([*out, text[at:]]) if merged else text


def redact_documents(docs: DataFrame, least: float = LEAST) -> DataFrame:
    """docs with all columns kept, personal data replaced in text, and n_chars (if there) counted anew. Null text stays null."""
    ship(docs.sparkSession)
    counts = "n_chars" in docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in text_slices(batches):
            texts = [redact(t.as_py(), least) if t.is_valid else None for t in b.column("text")]
            b = b.set_column(b.schema.get_field_index("text"), "text", pa.array(texts, b.column("text").type))
            if counts:
                kind = b.column("n_chars").type
                b = b.set_column(b.schema.get_field_index("n_chars"), "n_chars", pa.array([None if t is None else len(t) for t in texts], pa.int64()).cast(kind))
            yield b

    return docs.mapInArrow(run, docs.schema)


__all__ = ["BASE", "SPANS", "find_personal", "luhn", "mod97", "personal_digests", "personal_spans", "redact", "redact_documents"]
