"""Byte-level BPE by prefix dynamic programming.

For every prefix of a piece, exactly one vocabulary entry can be the last token of that prefix's encoding: the one
that, after the last token of the prefix before it, is left alone by the merges. Storing that entry for each prefix
gives the encoding by walking back, lets bytes be appended without touching what is stored, and confines an edit to
the prefixes behind it, up to where the stored entries agree again.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from functools import cache

import ahocorasick
import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from .common import as_strings, ship, text_slices
from .ragged import GATHER_BYTES, Memo, gather, woven


class ByteVocabulary:
    """Ranks of byte strings, and which two tokens may stand side by side."""

    #: Remembered answers about two neighbours.
    PAIRS = 300_000

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        self.tokens = [b""] * (max(ranks.values(), default=-1) + 1)
        for b, i in ranks.items():
            self.tokens[i] = b
        self.endings = ahocorasick.Automaton()  # all tokens that end at a byte, the longest first
        for b, i in ranks.items():
            self.endings.add_word(b.decode("latin-1"), (len(b), i))
        self.endings.make_automaton()
        self.longest = max(map(len, ranks), default=1)
        self._pairs: dict[int, bool] = {}
        self._whole: dict[int, bool] = {}
        self._halves: dict[int, tuple[int, int]] = {}

    @classmethod
    def read(cls, path: str) -> ByteVocabulary:
        with open(path, "rb") as f:
            return cls({base64.b64decode(a): int(b) for a, b in map(bytes.split, f)})

    def merged(self, text: bytes, least: int = 1) -> list[int]:
        """The encoding by its definition: merge the neighbours of lowest rank, the leftmost first, while there are any and over `least` parts."""
        parts = [text[i : i + 1] for i in range(len(text))]
        while len(parts) > least:
            best = min(((r, i) for i in range(len(parts) - 1) if (r := self.ranks.get(parts[i] + parts[i + 1])) is not None), default=None)
            if best is None:
                break
            parts[best[1] : best[1] + 2] = [parts[best[1]] + parts[best[1] + 1]]
        return [self.ranks[p] for p in parts]

    def whole(self, token: int) -> bool:
        """Whether the merges of the token's bytes make the token."""
        if (known := self._whole.get(token)) is None:
            left, right = self.halves(token)
            known = self._whole[token] = right < 0 or self.ranks.get(self.tokens[left] + self.tokens[right]) == token
        return known

    def halves(self, token: int) -> tuple[int, int]:
        """The two tokens whose merge made this one; a single byte is its own first half."""
        known = self._halves.get(token)
        if known is None:
            text = self.tokens[token]
            parts = self.merged(text, 2) if len(text) > 1 else [token, -1]
            known = self._halves[token] = (parts[0], parts[-1])
        return known

    def neighbours(self, left: int, right: int) -> bool:
        """Whether the merges leave these two tokens as they are: none across their border came before those that made them.

        Looks at the border as it was ever earlier, taking back the later merge of the two sides each time. `before` is
        the first rank at which a merge across the border comes too late.
        """
        key = left << 20 | right
        if (known := self._pairs.get(key)) is not None:
            return known
        ranks, tokens, halves, before, free = self.ranks, self.tokens, self.halves, 1 << 60, True
        while True:
            if ranks.get(tokens[left] + tokens[right], before) < before:
                free = False
                break
            if left > right:
                before, (inner, at) = left, halves(left)
                if at < 0:
                    break
                left = at
            else:
                before, (inner, at) = right + 1, halves(right)
                if at < 0:
                    break
                right = inner
        if len(self._pairs) >= self.PAIRS:
            self._pairs.clear()
        self._pairs[key] = free
        return free


class PrefixEncoding:
    """A piece of bytes with the last token of each of its prefixes; lengths in bytes."""

    def __init__(self, vocabulary: ByteVocabulary, text: bytes = b""):
        self.vocabulary, self.text, self.last = vocabulary, bytearray(), [-1]
        if text:
            self.append(text)

    def append(self, more: bytes) -> None:
        """Extends the piece; what is stored stays as it is."""
        self.text += more
        for _ in self._entries(len(self.text) - len(more)):
            pass

    @staticmethod
    def encode(vocabulary: ByteVocabulary, text: bytes) -> list[int]:
        """ids() of a piece that is not kept, in one lean loop."""
        pairs, last, done = vocabulary._pairs, [-1], 0
        for end, (size, token) in vocabulary.endings.iter(text.decode("latin-1")):
            if end == done:
                before = last[end + 1 - size]
                free = vocabulary.whole(token) if before < 0 else pairs.get(before << 20 | token)
                if free is None:
                    free = vocabulary.neighbours(before, token)
                if free:
                    last.append(token)
                    done += 1
        if done < len(text):
            raise ValueError(f"no token ends at byte {done + 1}: the vocabulary lacks a byte")
        out, tokens = [], vocabulary.tokens
        while done:
            out.append(token := last[done])
            done -= len(tokens[token])
        return out[::-1]

    def _entries(self, start: int) -> Iterator[int]:
        """Makes the entries of the prefixes longer than `start`, one by one; yields each prefix's length."""
        v, last = self.vocabulary, self.last
        pairs, neighbours = v._pairs, v.neighbours
        shift = max(0, start - v.longest)
        del last[start + 1 :]
        done = start
        for end, (size, token) in v.endings.iter(self.text[shift:].decode("latin-1")):
            end += shift + 1
            if end == done + 1:
                before = last[end - size]
                if before < 0:
                    if not v.whole(token):
                        continue
                elif (free := pairs.get(before << 20 | token)) is None:
                    if not neighbours(before, token):
                        continue
                elif not free:
                    continue
                last.append(token)
                done = end
                yield end
        if done < len(self.text):
            raise ValueError(f"no token ends at byte {done + 1}: the vocabulary lacks a byte")

    def replace(self, start: int, end: int, new: bytes) -> int:
        """Puts new bytes at [start, end). Entries before stay, entries behind are made again until as many as the
        longest token has bytes agree with the old ones in a row; the rest is kept. Returns the number made again."""
        old, shift, behind = list(self.last), len(new) - (end - start), start + len(new)
        self.text[start:end] = new
        same, made, longest, tokens = 0, 0, self.vocabulary.longest, self.vocabulary.tokens
        for at in self._entries(start):
            made += 1
            # an entry is reusable only where its whole token lies behind the edit
            agrees = at > behind and old[at - shift] == self.last[at] and at - behind >= len(tokens[self.last[at]])
            same = same + 1 if agrees else 0
            if same >= longest:
                self.last += old[at - shift + 1 :]
                break
        return made

    def ids(self) -> list[int]:
        out, end = [], len(self.text)
        while end:
            out.append(self.last[end])
            end -= len(self.vocabulary.tokens[out[-1]])
        return out[::-1]


class ByteEncoder:
    """Ids of whole texts: each match of the splitting pattern by its own prefix table."""

    #: What may follow a space so that the space belongs to what stands before it.
    HARD = "[ ][\\s\\x{85}\\x{a0}\\x{1680}\\x{2000}-\\x{200a}\\x{2028}\\x{2029}\\x{202f}\\x{205f}\\x{3000}\\x{b}\\x{1c}-\\x{1f}]|[ ]$"

    def __init__(self, path: str, pattern: str):
        import regex

        self.vocabulary = ByteVocabulary.read(path)
        self.find = regex.compile(pattern).findall
        self.memo, self.pieces = Memo(150_000), Memo(400_000)
        self.dtype = np.uint16 if len(self.vocabulary.tokens) <= 1 << 16 else np.uint32

    def piece(self, text: str) -> list[int]:
        raw = text.encode()
        known = self.vocabulary.ranks.get(raw)
        return [known] if known is not None else PrefixEncoding.encode(self.vocabulary, raw)

    def _pieces(self, names: list[str]) -> list[bytes]:
        return [np.array(self.piece(n), self.dtype).tobytes() for n in names]

    def _chunks(self, names: list[str]) -> list[bytes]:
        split = [self.find(n) for n in names]
        flat = self.pieces.many([p for ps in split for p in ps], self._pieces)
        out, at = [], 0
        for ps in split:
            out.append(flat[at] if len(ps) == 1 else b"".join(flat[at : at + len(ps)]))
            at += len(ps)
        return out

    def __call__(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row, and n + 1 offsets of the texts in them. Null texts count as empty.

        A single space before anything but white space opens a new match of the pattern, so texts are cut there.
        Texts where a space ends the text or stands before white space are split by the pattern as a whole.
        """
        s = as_strings(texts)
        hard = pc.match_substring_regex(s, self.HARD)
        rows = np.flatnonzero(hard.to_numpy(zero_copy_only=False))
        own = [np.frombuffer(self._chunks([s[i].as_py()])[0], self.dtype) for i in rows.tolist()]
        if len(rows):
            s = s.filter(pc.invert(hard))
        parts = gather(pc.split_pattern(s, " "), self.memo, self._chunks, lead=" ", dtype=self.dtype)
        return woven(parts, rows, own) if len(rows) else parts

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.vocabulary.tokens.__getitem__, ids))


@cache
def byte_encoder(path: str, pattern: str) -> ByteEncoder:
    return ByteEncoder(path, pattern)


def _encode(path: str, pattern: str, digests: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = byte_encoder(path, pattern)
        names = list(map(str, range(len(encoder.vocabulary.tokens))))
        for b in text_slices(batches, limit=GATHER_BYTES):
            ids, at = encoder(b.column("text"))
            counts = pa.array(np.diff(at), pa.int64())
            if not digests:
                lists = pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(ids, pa.int32()))
                yield pa.record_batch([b.column("doc_id"), counts, lists], ["doc_id", "n_tokens", "ids"])
                continue
            shown, decoded = [], []
            for start, end in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
                own = ids[start:end].tolist()
                shown.append(hashlib.sha256(" ".join(map(names.__getitem__, own)).encode()).hexdigest())
                decoded.append(hashlib.sha256(encoder.decode(own)).hexdigest())
            yield pa.record_batch([b.column("doc_id"), counts, pa.array(shown), pa.array(decoded)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return run


def encode_documents(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, n_tokens, ids array<int> of every row of docs (doc_id, text; other columns are ignored).

    Null text counts as empty; empty text has no ids; repeated rows and null doc_ids pass through; an empty table gives
    an empty one. No shuffle; memory is bounded by GATHER_BYTES of text or one document.
    """
    ship(docs.sparkSession)
    return docs.select("doc_id", "text").mapInArrow(_encode(path, pattern, False), "doc_id long, n_tokens long, ids array<int>")


def encoding_digests(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, n_tokens, sha256 of the decimal ids joined by spaces, sha256 of the bytes decoded from the ids. Rows as in encode_documents."""
    ship(docs.sparkSession)
    return docs.select("doc_id", "text").mapInArrow(_encode(path, pattern, True), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def decode_documents(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, data binary: the bytes of each row's ids (null ids: null)."""
    ship(encoded.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = byte_encoder(path, pattern)
        for b in batches:
            yield pa.record_batch([b.column("doc_id"), pa.array([None if x is None else encoder.decode(x) for x in b.column("ids").to_pylist()], pa.binary())], ["doc_id", "data"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, data binary")
