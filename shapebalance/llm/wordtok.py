"""Token ids of the lower-casing word tokenizer for whole batches, as the tokenizers library gives them.

The tokenizer drops white space and never merges across it, nor across a letter and the ASCII mark after it;
it lower-cases text. So texts are lower-cased and cut there, and the library encodes each distinct chunk.
"""

from __future__ import annotations

import os
import re
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .common import as_strings
from .ragged import Memo, gather, woven

#: Letters whose lower-casing and composition leave them as they are; each is one or two bytes.
PLAIN = re.compile("[a-zß-öø-ÿ]+")
#: Such a letter and an ASCII mark after it.
MARKS = r"([a-zß-öø-ÿ])([!-/:-@\[-`{-~])"


def _byte_letters() -> dict[int, str]:
    """The public byte-level alphabet: printable bytes stand for themselves, the others for characters from 256 on."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(own)]
    return {b: chr(b) for b in own} | {b: chr(256 + i) for i, b in enumerate(rest)}


class WordTokenizer:
    def __init__(self, path: str, memo: int = 200_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = False
        self.memo = Memo(memo)
        letters = _byte_letters()
        self.spelled = {ord(c): "".join(letters[b] for b in c.encode()) for c in map(chr, [*range(97, 123), *range(0xDF, 0xF7), *range(0xF8, 0x100)])}
        if self.tokenizer.get_vocab_size() > 1 << 16:
            raise ValueError("the vocabulary has over 65536 ids")

    def chunks(self, names: list[str]) -> list[bytes]:
        model, spelled, out, hard = self.tokenizer.model, self.spelled, [b""] * len(names), []
        for i, name in enumerate(names):
            if PLAIN.fullmatch(name):
                word = name if name.isascii() else name.translate(spelled)
                out[i] = np.array([t.id for t in model.tokenize(word)], np.uint16).tobytes()
            elif name:
                hard.append(i)
        for i, e in zip(hard, self.tokenizer.encode_batch_fast([names[i] for i in hard], add_special_tokens=False), strict=True):
            out[i] = np.array(e.ids, np.uint16).tobytes()
        return out

    def __call__(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids (uint16) of all texts in a row, and n + 1 offsets of the texts in them. Null texts count as empty."""
        s = as_strings(texts)
        # texts with the special tokens' marks go to the library whole, as those match before anything else
        marked = pc.match_substring(s, "<|")
        rows = np.flatnonzero(marked.to_numpy(zero_copy_only=False))
        own = [np.array(self.tokenizer.encode(s[i].as_py(), add_special_tokens=False).ids, np.uint16) for i in rows.tolist()]
        if len(rows):
            s = s.filter(pc.invert(marked))
        s = pc.replace_substring(pc.replace_substring_regex(pc.ascii_lower(s), MARKS, r"\1 \2"), "\n", " ")
        parts = gather(pc.split_pattern(s, " "), self.memo, self.chunks)
        return woven(parts, rows, own) if len(rows) else parts


@cache
def word_tokenizer(path: str, memo: int = 200_000) -> WordTokenizer:
    return WordTokenizer(path, memo)
