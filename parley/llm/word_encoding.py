"""Token ids of whole texts by a public word-level BPE, with one encoding for each distinct word.

The tokenizer drops white space and never merges over it, and no token of it holds a letter beside a mark; so a text's
ids are those of its blank-separated chunks, and a chunk's are those of its letters and its closing marks. Each worker
keeps what it has encoded. Chunks that hold combining marks or anything else unusual go to the tokenizer as they are.
"""

from __future__ import annotations

import os
import re
from functools import lru_cache

import numpy as np

#: Chunks that one worker remembers before it starts anew.
MEMORY = 600_000

_MARKS = re.compile("[̀-ͯ]")
#: Of lines: letters (a to z, and the small accented ones of Latin-1), then marks other than the apostrophe: one word of the tokenizer each; or all else.
_SPLIT = re.compile(rb"^((?:[a-z]|\xc3[\xa0-\xb6\xb8-\xbf])*)([!-&(-/:-@\[-`{-~]*)$|^(.+)$", re.M)


@lru_cache(maxsize=4)
def encoder(path: str) -> WordEncoder:
    return WordEncoder(path)


class WordEncoder:
    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import WhitespaceSplit

        self.tokenizer = Tokenizer.from_file(path)
        # what _SPLIT takes apart is lower-case and composed: normalising and finding words in it again would change nothing
        self.apart = Tokenizer.from_file(path)
        self.apart.normalizer, self.apart.pre_tokenizer = None, WhitespaceSplit()
        self.dtype = np.dtype("<u2" if self.tokenizer.get_vocab_size() <= 1 << 16 else "<u4")
        ends = np.zeros(self.tokenizer.get_vocab_size(), bool)
        ends[[i for token, i in self.tokenizer.get_vocab().items() if token.endswith("</w>")]] = True
        self.last = ends
        self.known: dict[bytes, bytes] = {b"": b""}

    def _direct(self, chunks: list[bytes]) -> dict[bytes, bytes]:
        found = self.tokenizer.encode_batch_fast([c.decode() for c in chunks], add_special_tokens=False)
        return {c: np.array(e.ids, self.dtype).tobytes() for c, e in zip(chunks, found, strict=True)}

    def _joined(self, words: list[bytes]) -> dict[bytes, bytes]:
        """Words that are one word of the tokenizer each, encoded as one text: an id that ends a word ends its ids."""
        text = b" ".join(words).decode("latin-1").replace("\xa0", "\u0142").replace("\xad", "\u0143")  # a character a byte, as the vocabulary spells them
        ids = np.array(self.apart.encode_batch_fast([text], add_special_tokens=False)[0].ids, self.dtype)
        ends = (np.nonzero(self.last[ids])[0] + 1).tolist()
        if len(ends) != len(words):
            return self._direct(words)
        raw, width = ids.tobytes(), self.dtype.itemsize
        return {w: raw[a * width : b * width] for w, a, b in zip(words, [0, *ends], ends, strict=False)}

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """Little-endian ids of each text, of this vocabulary's width."""
        split = []
        for t in texts:
            raw = (t or "").encode().replace(b"\n", b" ")
            split.append((raw if _MARKS.search(t or "") else raw.lower()).split(b" "))
        if len(self.known) > MEMORY:  # common chunks soon come back
            self.known = {b"": b""}
        known = self.known
        new = list(set().union(*split).difference(known)) if split else []
        if new:
            parts = _SPLIT.findall(b"\n".join(new))
            words = {a for a, _, _ in parts}.union(b for _, b, _ in parts).difference(known)
            fresh = (self._joined(list(words)) if words else {}) | self._direct([c for _, _, c in parts if c])
            known.update(fresh)
            for c, (a, b, other) in zip(new, parts, strict=True):
                if b and not other:
                    known[c] = known[a] + known[b]
        return [b"".join(map(known.__getitem__, words)) for words in split]
