"""BPE encoding and decoding with content-defined chunk reuse.

A rolling hash over a window of bytes picks cut points by content, so a passage shared by documents falls into
the same chunks wherever it stands. A chunk is encoded and decoded once per worker and taken from a bounded cache
afterwards. Cut points move forward to the next place where a word ends and one blank begins another: there the
vocabulary's own pre-tokenizer always splits. Every join is then checked by encoding a window around it; where the
window's ids differ from the chunks' ids, the window grows until both agree, and at last the two chunks are encoded as one.
New chunks of plain text are merged by the tiktoken library over the same vocabulary taken by rank (see ``wordcache``),
all others by the tokenizers library itself.

Results are those of the tokenizers library for any text: the caches and cuts only save work. A null text counts as
empty: no ids, an empty decoded text. Rows are independent, so repeated rows get equal results and there is no shuffle.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from localfreq.llm.common import batches, read_table, texts_of
from localfreq.llm.wordcache import byte_alphabet, load_tokenizer

__all__ = ["ByteBpe", "chunk_ends", "encode_decode", "op5_bpe_round_trip"]

_WINDOW, _MULTIPLIER = 32, 0x9E3779B97F4A7C15
#: Text for which the two libraries' character classes are known to agree, without marks of special tokens.
_UNPROVEN = re.compile(r"[\x00-\x08\x0b\x0c\x0e-\x1f\x7f-\xa0ɐ-\U0010ffff]|<\|")
#: Fixed value: how the byte-level vocabulary splits a text.
_SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def chunk_ends(raw: np.ndarray, mean: int = 1024) -> np.ndarray:
    """Byte places after which a content-defined chunk may end: the hash of the last 32 bytes has its top bits zero."""
    if len(raw) < 2 * _WINDOW:
        return np.zeros(0, np.int64)
    powers = np.cumprod(np.full(_WINDOW, _MULTIPLIER, np.uint64))
    x = (raw.astype(np.uint64) + np.uint64(1)) * np.uint64(0xD6E8FEB86659FD93)
    h, span = x.copy(), 1
    while span < _WINDOW:  # doubling: the hash of 2n bytes from two hashes of n bytes
        h[span:] += h[:-span] * powers[span - 1]
        span *= 2
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    return np.flatnonzero(h[_WINDOW - 1:] >> np.uint64(64 - int(mean).bit_length() + 1) == 0) + _WINDOW


class ByteBpe:
    """The given byte-level vocabulary: for a text, (number of ids, decimal ids each with a comma, decoded bytes).

    With ``packed`` the ids are little-endian numbers of so many bytes instead.
    """

    def __init__(self, path: str, mean: int = 1024, most_chunks: int = 16_000, most_words: int = 50_000, special_as_text: bool = False, packed: int | None = None):
        import tiktoken

        self.tok, self.mean, self.most_chunks, self.most_words = load_tokenizer(path), mean, most_chunks, most_words
        self.tok.encode_special_tokens = special_as_text
        back = {c: b for b, c in byte_alphabet().items()}
        special = {i for i, t in self.tok.get_added_tokens_decoder().items()}
        self.piece: dict[int, bytes] = {}
        for token, i in self.tok.get_vocab(with_added_tokens=True).items():
            whole = i in special or any(c not in back for c in token)
            self.piece[i] = token.encode() if whole else bytes(back[c] for c in token)
        if any(len(self.piece.get(i, b"")) != 1 for i in range(256)):
            raise ValueError("a byte-level vocabulary is needed")
        self.decimal = {i: i.to_bytes(packed, "little") if packed else f"{i},".encode() for i in self.piece}
        ranks = {p: i for i, p in self.piece.items() if i not in special}
        self.fast = tiktoken.Encoding("bytes", pat_str=_SPLIT, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
        self.chunks: dict[bytes, tuple[int, bytes, bytes]] = {}
        self.words: dict[str, tuple[int, bytes, bytes]] = {}
        self.joins = self.repairs = 0

    def ids(self, text: str) -> list[int]:
        return self.tok.encode(text, add_special_tokens=False).ids

    def _ids(self, text: str) -> list[int]:
        """The library's ids; within the proven range by its faster twin."""
        return self.ids(text) if _UNPROVEN.search(text) else self.fast(text)

    def _triple(self, ids: list[int]) -> tuple[int, bytes, bytes]:
        return len(ids), b"".join(map(self.decimal.__getitem__, ids)), b"".join(map(self.piece.__getitem__, ids))

    def _lookup(self, words: list[str]) -> list[tuple[int, bytes, bytes]]:
        known = self.words
        for w in words:
            if w not in known:
                if len(known) >= self.most_words:
                    known.clear()
                known[w] = self._triple(self._ids(w))
        return [known.get(w) or self._triple(self._ids(w)) for w in words]

    def _chunk(self, raw: bytes) -> tuple[int, bytes, bytes]:
        got = self.chunks.get(raw)
        if got is None:
            got = self._triple(self._ids(raw.decode()))
            if len(raw) <= 16 * self.mean:
                if len(self.chunks) >= self.most_chunks:
                    self.chunks.clear()
                self.chunks[raw] = got
        return got

    def cut(self, raw: bytes) -> list[bytes]:
        """The chunks of a text's bytes; joined they are the text."""
        out, at = [], 0
        for end in chunk_ends(np.frombuffer(raw, np.uint8), self.mean).tolist():
            if end - at < self.mean // 4:
                continue
            while (end := raw.find(b" ", end)) != -1 and not (raw[end - 1] < 128 and raw[end - 1:end].isalnum() and raw[end + 1:end + 2].isalnum()):
                end += 1
            if end == -1:
                break
            if end > at:
                out.append(raw[at:end])
                at = end
        return [*out, raw[at:]] if at < len(raw) else out

    def _joined(self, left: bytes, right: bytes) -> bytes | None:
        """None if the ids of two chunks stand as they are; else the chunks' union, to be encoded anew."""
        self.joins += 1
        a, b = left.rfind(b" "), right.find(b" ", 1)
        tail, head = left[max(a, 0):], right[:b] if b > 0 else right
        while True:
            parts = self._lookup([tail.decode(), head.decode()]) if len(tail) + len(head) <= 512 else [self._triple(self.ids(x.decode())) for x in (tail, head)]
            whole = self._lookup([(tail + head).decode()])[0] if len(tail) + len(head) <= 512 else self._triple(self.ids((tail + head).decode()))
            if whole[1] == parts[0][1] + parts[1][1]:
                return None
            self.repairs += 1
            if len(tail) == len(left) and len(head) == len(right):
                return left + right
            a, b = left.rfind(b" ", 0, max(0, len(left) - 2 * len(tail))), right.find(b" ", 2 * len(head))
            tail, head = left[max(a, 0):], right[:b] if b > 0 else right

    def encode(self, text: str) -> tuple[int, bytes, bytes]:
        raw = text.encode("utf-8", "surrogatepass")
        pieces = self.cut(raw)
        if len(pieces) <= 1:
            return self._chunk(raw) if raw else (0, b"", b"")
        done = [pieces[0]]
        for p in pieces[1:]:
            both = self._joined(done[-1], p)
            if both is None:
                done.append(p)
            else:
                done[-1] = both
        parts = [self._chunk(p) for p in done]
        return sum(p[0] for p in parts), b"".join(p[1] for p in parts), b"".join(p[2] for p in parts)


def encode_decode(df: DataFrame, path: str, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per row of ``df``: (doc_id, n_tokens, ids_sha256, decoded_sha256). Narrow: no shuffle."""

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = ByteBpe(path)
        for b in batches(rows):
            n, ids, dec = [], [], []
            for t in texts_of(b.column(1)):
                k, decimal, raw = bpe.encode(t)
                n.append(k)
                ids.append(hashlib.sha256(decimal[:-1]).hexdigest())
                dec.append(hashlib.sha256(raw.decode("utf-8", "replace").encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(dec, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return df.select(df[doc_id].cast("long").alias("doc_id"), df[text].cast("string").alias("text")).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op5_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return encode_decode(read_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
