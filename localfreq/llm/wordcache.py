"""Token ids of whole texts as the tokenizers library gives them, with exact reuse of words.

The public vocabularies split a text before merging, and no merge crosses a split. A text may therefore be cut at
places that are always splits, each piece encoded once, and the ids of the pieces joined. ``WordIds`` keeps a
bounded number of words per worker. Texts outside the range for which the cut is proven go to the library whole.

New words are merged by the byte-pair core of the tiktoken library, which takes a vocabulary's tokens by rank. That
agrees with merging by listed pairs: where a token's bytes stand between two token borders, no earlier merge
has crossed those borders, so its inside has come about as in the vocabulary's training and only the listed pair is left.
The end-of-word mark becomes the byte FF, which no UTF-8 text holds.
"""

from __future__ import annotations

import json
import os
import re
from array import array
from collections.abc import Iterable

__all__ = ["WordIds", "byte_alphabet", "load_tokenizer"]

_END = "</w>"

#: What the cut at white space is proven for: printable text below U+0250 (stable under NFC, lower case by
#: character), blanks that all parties call white space, no mark that could begin a special token.
_UNPROVEN = re.compile(r"[\x00-\x08\x0b\x0c\x0e-\x1f\x7f-\xa0İɐ-\U0010ffff]|<\|")


def load_tokenizer(path: str):
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(path)
    tok.no_truncation()
    tok.no_padding()
    return tok


def byte_alphabet() -> dict[int, str]:
    """The public byte-level alphabet: printable bytes stand for themselves, the rest follow from U+0100 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}


class WordIds:
    """Ids of lower-casing, white-space-dropping vocabularies, as little-endian unsigned 32-bit bytes."""

    def __init__(self, path: str, most: int = 250_000):
        import regex
        import tiktoken

        self.tok, self.most, self.known = load_tokenizer(path), most, {}
        back = {c: b for b, c in byte_alphabet().items()}
        ranks = {}
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        if model["end_of_word_suffix"] != _END:
            raise ValueError("a vocabulary with ends of words is needed")
        for token, i in model["vocab"].items():
            end = token.endswith(_END) and len(token) > len(_END)
            ranks[bytes(back[c] for c in (token[:-len(_END)] if end else token)) + b"\xff" * end] = i
        self.merge = tiktoken.Encoding("words", pat_str=r"\S+", mergeable_ranks=ranks, special_tokens={})._core_bpe.encode_single_piece
        #: Fixed value: how the vocabulary splits a lower-case text.
        self.split = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+").findall

    def _word(self, word: str) -> bytes:
        ids: list[int] = []
        for piece in self.split(word):
            ids += self.merge(piece.encode() + b"\xff")
        return array("I", ids).tobytes()

    def _encode(self, texts: list[str]) -> list[bytes]:
        import numpy as np

        return [np.array(e.ids, "<u4").tobytes() for e in self.tok.encode_batch_fast(texts, add_special_tokens=False)]

    def ids(self, text: str) -> bytes:
        if _UNPROVEN.search(text):
            return self._encode([text])[0]
        words, known = text.lower().split(), self.known
        try:
            return b"".join(map(known.__getitem__, words))
        except KeyError:
            pass
        missing = list({w for w in words if w not in known})
        if len(known) + len(missing) > self.most:
            known.clear()
            missing = list(set(words))
        for w in missing:
            known[w] = self._word(w)
        return b"".join(map(known.__getitem__, words))

    def many(self, texts: Iterable[str]) -> list[bytes]:
        return [self.ids(t) for t in texts]
