"""Byte-level BPE as a monoid: encode halves, join neighbours, concatenate to decode.

A text is cut in halves down to leaves. A leaf is encoded directly. Joining
two encoded neighbours re-encodes a window around the seam that grows until
the tokens outside it provably can't change:

* between pieces, a window may end at a *firm* position: a non-space character
  before a blank, or two ASCII characters of different classes where no piece
  of the pattern can span both. The pattern has no lookbehind, and what stands
  before a firm position ends there whatever follows, so both sides encode
  independently of each other;
* inside one long piece (no firm position near), a token row is a valid BPE
  encoding exactly if every two neighbouring tokens re-encode to themselves,
  so the window grows until both of its seams pass that test.

If neither stops the growth, the window becomes the whole text; the result is
always that of encoding the whole text at once. Decoding concatenates the
tokens' bytes up the same tree.
"""

from __future__ import annotations

import base64
import hashlib
from functools import lru_cache

from pyspark.sql import DataFrame

from linkblock.llm.common import narrow, per_document

LEAF_CHARS = 2048
FIRST_WINDOW = 32
#: Without a firm position in so many characters next to a seam, the seam counts as inside one piece.
FIRM_WITHIN = 4096


def _kind(c: str) -> str:
    if c.isspace():
        return "s"
    if c.isascii():
        return "l" if c.isalpha() else "n" if c.isdigit() else "q" if c == "'" else "p"
    return "?"


def firm(before: str, after: str) -> bool:
    """Whether text may be cut between these two characters without changing any token."""
    x, y = _kind(before), _kind(after)
    if x == "s":
        return False
    if after == " ":
        return True
    if "?" in (x, y) or y == "s" or x == "q":
        return False
    return x != y and {x, y} != {"p", "q"}


class Bpe:
    """Encoder and decoder for one rank file and one splitting pattern."""

    def __init__(self, rank_path: str, pattern: str):
        import tiktoken

        with open(rank_path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        size = max(ranks.values()) + 1
        self.token = [b""] * size
        for piece, rank in ranks.items():
            self.token[rank] = piece
        self.digits = [str(i) for i in range(size)]
        self._own = tiktoken.Encoding("given-ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self.pair_stable = lru_cache(1 << 16)(self._pair_stable)

    def _one_piece(self, data: bytes) -> list[int]:
        return self._own._encode_single_piece(data)

    def _pair_stable(self, left: int, right: int) -> bool:
        return self._one_piece(self.token[left] + self.token[right]) == [left, right]

    def encode(self, text: str, leaf: int = LEAF_CHARS) -> list[int]:
        """The tokens of text; leaves hold at most `leaf` characters."""
        return self._tree(text, 0, len(text), leaf)

    def _tree(self, text: str, start: int, end: int, leaf: int) -> list[int]:
        if end - start <= leaf:
            return self._own.encode_ordinary(text[start:end])
        mid = (start + end) // 2
        return self.join(text, start, mid, end, self._tree(text, start, mid, leaf), self._tree(text, mid, end, leaf))

    def join(self, text: str, start: int, mid: int, end: int, left: list[int], right: list[int]) -> list[int]:
        """Tokens of text[start:end] from those of text[start:mid] and text[mid:end]."""
        if not left or not right:
            return left + right
        lo = self._firm_before(text, start, mid)
        hi = self._firm_after(text, mid, end)
        if lo is None or hi is None:
            inside = self._inside_piece(text, start, mid, end, left, right)
            if inside is not None:
                return inside
        lo, hi = start if lo is None else lo, end if hi is None else hi
        keep_left = self._drop_last(left, len(text[lo:mid].encode()))
        keep_right = self._drop_first(right, len(text[mid:hi].encode()))
        return left[:keep_left] + self._own.encode_ordinary(text[lo:hi]) + right[keep_right:]

    @staticmethod
    def _firm_before(text: str, start: int, mid: int) -> int | None:
        for at in range(mid, max(start, mid - FIRM_WITHIN), -1):
            if at < len(text) and firm(text[at - 1], text[at]):
                return at
        return start if mid - start <= FIRM_WITHIN else None

    @staticmethod
    def _firm_after(text: str, mid: int, end: int) -> int | None:
        for at in range(mid, min(end, mid + FIRM_WITHIN)):
            if at and firm(text[at - 1], text[at]):
                return at
        return end if end - mid <= FIRM_WITHIN else None

    def _drop_last(self, tokens: list[int], size: int) -> int:
        n = len(tokens)
        while size > 0:
            n -= 1
            size -= len(self.token[tokens[n]])
        if size:
            raise AssertionError("a firm position inside a token")
        return n

    def _drop_first(self, tokens: list[int], size: int) -> int:
        n = 0
        while size > 0:
            size -= len(self.token[tokens[n]])
            n += 1
        if size:
            raise AssertionError("a firm position inside a token")
        return n

    def _inside_piece(self, text: str, start: int, mid: int, end: int, left: list[int], right: list[int]) -> list[int] | None:
        """Grow a token window over a seam inside a run of plain letters or digits; None if the seam isn't in one."""
        around = text[max(start, mid - FIRM_WITHIN) : min(end, mid + FIRM_WITHIN)]
        if not (around.isascii() and (around.isalpha() or around.isdigit())):
            return None
        width = FIRST_WINDOW
        while True:
            back, ahead = min(width, len(left)), min(width, len(right))
            taken = b"".join(self.token[t] for t in left[len(left) - back :] + right[:ahead])
            if len(taken) >= len(around):
                return None
            made = self._one_piece(taken)
            if (back == len(left) or self.pair_stable(left[-back - 1], made[0])) and (ahead == len(right) or self.pair_stable(made[-1], right[ahead])):
                return left[: len(left) - back] + made + right[ahead:]
            width *= 2

    def decode(self, tokens: list[int]) -> bytes:
        """The bytes of the tokens, concatenated up a tree."""
        if len(tokens) <= LEAF_CHARS:
            return b"".join([self.token[t] for t in tokens])
        mid = len(tokens) // 2
        return self.decode(tokens[:mid]) + self.decode(tokens[mid:])


@lru_cache(4)
def bpe_for(rank_path: str, pattern: str) -> Bpe:
    return Bpe(rank_path, pattern)


def public_vocabulary() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def encode_documents(docs: DataFrame, rank_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids array<int>) for every row; null text counts as empty and gives no ids, repeated rows give repeated rows."""
    return per_document(
        narrow(docs, id_col, text_col),
        lambda raw: (bpe_for(rank_path, pattern).encode(raw.decode()),),
        "doc_id bigint, ids array<int>",
    )


def decode_documents(encoded: DataFrame, rank_path: str, pattern: str) -> DataFrame:
    """(doc_id, text) back from (doc_id, ids)."""
    import pyarrow as pa

    def run(batches):
        own = bpe_for(rank_path, pattern)
        for b in batches:
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), pa.array([own.decode(x or []).decode() for x in b.column("ids").to_pylist()], pa.string())],
                names=["doc_id", "text"],
            )

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id bigint, text string")


def round_trip(docs: DataFrame, rank_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: doc_id, n_tokens, digests of the decimal ids and of the decoded bytes, n_bytes."""

    def work(raw: bytes):
        own = bpe_for(rank_path, pattern)
        ids = own.encode(raw.decode())
        digits = own.digits
        back = own.decode(ids)
        return (
            len(ids), hashlib.sha256(" ".join([digits[i] for i in ids]).encode()).hexdigest(),
            hashlib.sha256(back).hexdigest(), len(back),
        )

    return per_document(
        narrow(docs, id_col, text_col), work,
        "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string, n_bytes bigint",
    )
