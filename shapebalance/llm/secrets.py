"""Secrets: an Aho-Corasick automaton finds keywords, anchored regular expressions run only at its hits, and checksums
embedded in tokens are verified. Long hexadecimal runs have no keyword: one character in 32 is probed, which no such
run escapes, and runs are measured at the hits only.
"""

from __future__ import annotations

import base64
import json
import re
import string
import zlib
from functools import cache

from pyspark.sql import DataFrame

from .spans import Span, digests, in_order, scan

BASE = ("assign", "access", "hex")
KINDS = (*BASE, "checked", "jwt", "pem")
_KEYS = ("password", "passwd", "secret", "token", "api_key", "apikey")
_CHECKED = ("ghp_", "gho_", "ghu_", "ghs_", "ghr_", "npm_")
_RULES = {
    "assign": re.compile(r"""(?ai:password|passwd|secret|token|api_?key)["']? *[:=] *["']?([A-Za-z0-9+/_.=-]+)"""),
    "access": re.compile("AKIA[A-Z0-9]+"),
    "checked": re.compile("(?:gh[pousr]|npm)_([A-Za-z0-9]{30})([A-Za-z0-9]{6})(?![A-Za-z0-9])"),
    "jwt": re.compile(r"(eyJ[A-Za-z0-9_-]+)\.eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]{8,}"),
    "pem": re.compile("-----BEGIN [A-Z ]{0,32}PRIVATE KEY-----"),
}
_JWT_RUN = re.compile("[A-Za-z0-9_-]*")
_HEX = frozenset("0123456789abcdef")
_HEX_RUN = re.compile("[0-9a-f]*")
_HEX_HIT = re.compile("[0-9a-f]")
_DIGITS62 = string.digits + string.ascii_uppercase + string.ascii_lowercase
_ASCII_LOWER = {i: i + 32 for i in range(65, 91)}


@cache
def _automaton():
    import ahocorasick

    a = ahocorasick.Automaton()
    for kind, words in (("assign", _KEYS), ("access", ("akia",)), ("checked", _CHECKED), ("jwt", ("eyj",)), ("pem", ("-----begin ",))):
        for w in words:
            a.add_word(w, (len(w), kind))
    a.make_automaton()
    return a


def crc62(body: str) -> str:
    """The six base-62 digits of a body's CRC-32, as tokens with an embedded checksum carry them."""
    n, out = zlib.crc32(body.encode()), ""
    for _ in range(6):
        n, d = divmod(n, 62)
        out = _DIGITS62[d] + out
    return out


def _is_header(part: str) -> bool:
    try:
        return "alg" in json.loads(base64.urlsafe_b64decode(part + "=" * (-len(part) % 4)))
    except (ValueError, TypeError):
        return False


#: Whether a match counts. The first three define the base kinds, the others verify what is added.
_KEEP = {
    "assign": lambda m: len(m[1]) >= 8,
    "access": lambda m: len(m[0]) >= 16,
    "checked": lambda m: crc62(m[1]) == m[2],
    "jwt": lambda m: _is_header(m[1]),
    "pem": lambda m: True,
}
_SCORE = {"assign": 0.6, "access": 0.9, "hex": 0.5, "checked": 1.0, "jwt": 0.9, "pem": 1.0}


def _hex_runs(text: str) -> list[tuple[int, int]]:
    out, done = [], 0
    for hit in _HEX_HIT.finditer(text[31::32]):
        at = hit.start() * 32 + 31
        if at < done:
            continue
        start, done = at, _HEX_RUN.match(text, at).end()
        while start and text[start - 1] in _HEX:
            start -= 1
        if done - start >= 32:
            out.append((start, done))
    return out


def find_secrets(text: str) -> list[Span]:
    """All spans of a text by start, then kind. A match that fails its rule is dropped, and what it covers is not tried again."""
    low = text.lower()
    if len(low) != len(text):
        low = text.translate(_ASCII_LOWER)
    out = [(s, e, "hex", _SCORE["hex"]) for s, e in _hex_runs(text)]
    hits = [(end + 1 - size, kind) for end, (size, kind) in _automaton().iter(low)]
    if hits:
        hits.sort()
        done = dict.fromkeys(KINDS, 0)
        for start, kind in hits:
            if start < done[kind]:
                continue
            if m := _RULES[kind].match(text, start):
                done[kind] = m.end()
                if _KEEP[kind](m):
                    out.append((*m.span(), kind, _SCORE[kind]))
            elif kind == "jwt":  # what follows the run fails for every start in it
                done[kind] = _JWT_RUN.match(text, start).end()
    return in_order(out, KINDS) if len(out) > 1 else out


def secret_spans(docs: DataFrame) -> DataFrame:
    """doc_id, spans (kind, start, end, score) of every row of docs (doc_id, text; other columns are ignored).

    Null or empty text has no spans; repeated rows and null doc_ids pass through; an empty table gives an empty one.
    Narrow: no shuffle, memory for one Arrow batch.
    """
    return scan(docs, find_secrets)


def secret_digests(docs: DataFrame) -> DataFrame:
    """doc_id, counts of the base kinds, base_sha256, spans of every row, as secret_spans() finds them; null and empty texts count 0."""
    return digests(secret_spans(docs), BASE)
