"""Byte-level BPE by a monoid tree reduction.

An encoding of a byte string is an element of a monoid: the product of two encodings is the encoding
of the joined bytes. A string is encoded by halves, down to single bytes; two neighbours are joined by
looking only at the boundary. A token sequence is the encoding of its bytes exactly if every adjacent pair of tokens is
the encoding of that pair's bytes, so a join is final as soon as the pairs at both rims of the
re-encoded boundary window are stable; until then the window grows. Decoding is the plain product of
token bytes up the same tree.

Pre-tokens (matches of the pattern) are encoded separately, each once per batch of distinct pre-tokens.
Nulls count as empty texts; empty texts give no ids. Repeated rows, ties and extra columns change
nothing; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import numpy as np
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtwin.llm.common import map_slices

#: Distinct pre-tokens held at once by a task; the table is emptied beyond it.
HELD = 400_000
#: Bytes of the parts that are remembered.
PART = 6


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in f if line.strip())}


class MonoidBpe:
    """Encoder and decoder over one rank table."""

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        self.bytes_of = {r: t for t, r in ranks.items()}
        self._pairs: dict[tuple[int, int], list[int]] = {}
        self._parts: dict[bytes, list[int]] = {}

    def merged(self, b: bytes) -> list[int]:
        """Encoding of a boundary window: merges the lowest-ranked neighbours until none is left."""
        if (whole := self.ranks.get(b)) is not None:
            return [whole]
        get, none = self.ranks.get, 1 << 60
        parts = [b[i : i + 1] for i in range(len(b))]
        found = [get(b[i : i + 2], none) for i in range(len(b) - 1)]
        while found and (best := min(found)) != none:
            i = found.index(best)
            parts[i] += parts.pop(i + 1)
            del found[i]
            if i < len(found):
                found[i] = get(parts[i] + parts[i + 1], none)
            if i:
                found[i - 1] = get(parts[i - 1] + parts[i], none)
        return [self.ranks[p] for p in parts]

    def pair(self, x: int, y: int) -> list[int]:
        """Encoding of the bytes of two tokens; the pair is stable if it is the two tokens again."""
        if (known := self._pairs.get((x, y))) is None:
            if len(self._pairs) > HELD:
                self._pairs.clear()
            known = self._pairs[x, y] = self.merged(self.bytes_of[x] + self.bytes_of[y])
        return known

    def stable(self, x: int, y: int) -> bool:
        return self.pair(x, y) == [x, y]

    def join(self, a: list[int], b: list[int]) -> list[int]:
        """Product of two encodings. The window doubles until its rims are stable, or it is everything."""
        if not a or not b:
            return a + b
        window, width = self.pair(a[-1], b[0]), 1
        if window == [a[-1], b[0]]:
            return a + b
        while True:
            i, j = max(0, len(a) - width), min(len(b), width)
            if (i == 0 or self.stable(a[i - 1], window[0])) and (j == len(b) or self.stable(window[-1], b[j])):
                return a[:i] + window + b[j:]
            width *= 2
            window = self.merged(b"".join(self.bytes_of[t] for t in a[-width:] + b[:width]))

    def encode(self, b: bytes) -> list[int]:
        """A string that is a token is that token; all others are products of their halves."""
        if (whole := self.ranks.get(b)) is not None:
            return [whole]
        return self._product(b) if b else []

    def _product(self, b: bytes) -> list[int]:
        """Short parts recur in many strings and are worked out once."""
        if (known := self._parts.get(b)) is not None:
            return known
        if len(b) == 1:
            out = [self.ranks[b]]
        else:
            mid = len(b) // 2
            out = self.join(self._product(b[:mid]), self._product(b[mid:]))
        if len(b) <= PART:
            if len(self._parts) > HELD:
                self._parts.clear()
            self._parts[b] = out
        return out

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


class TextCodec:
    """Whole texts: pattern matches, each through the monoid; distinct matches are worked out once."""

    def __init__(self, ranks_path: str, pattern: str):
        self.bpe = MonoidBpe(read_ranks(ranks_path))
        self.split = regex.compile(pattern).findall
        self.known: dict[str, str] = {}
        self.back: dict[str, bytes] = {}

    def pieces(self, text: str) -> list[str]:
        """Decimal ids of each match."""
        found, known = self.split(text), self.known
        out = list(map(known.get, found))
        if None in out:
            if len(known) > HELD:
                known.clear()
                self.back.clear()
            for i, x in enumerate(out):
                if x is None:
                    if (said := known.get(found[i])) is None:
                        said = known[found[i]] = " ".join(map(str, self.bpe.encode(found[i].encode())))
                    out[i] = said
        return out

    def decoded(self, pieces: list[str]) -> bytes:
        back = self.back
        out = list(map(back.get, pieces))
        if None in out:
            for i, x in enumerate(out):
                if x is None:
                    if (raw := back.get(pieces[i])) is None:
                        raw = back[pieces[i]] = self.bpe.decode([int(t) for t in pieces[i].split()])
                    out[i] = raw
        return b"".join(out)

    def encode(self, text: str | None) -> list[int]:
        return [int(t) for piece in self.pieces(text or "") for t in piece.split()]


_CODECS: dict[tuple[str, str], TextCodec] = {}


def codec_of(ranks_path: str, pattern: str) -> TextCodec:
    """One codec a Python worker, kept from task to task."""
    if (ranks_path, pattern) not in _CODECS:
        _CODECS[ranks_path, pattern] = TextCodec(ranks_path, pattern)
    return _CODECS[ranks_path, pattern]


def encode_documents(docs: DataFrame, ranks_path: str, pattern: str, ids: bool = True) -> DataFrame:
    """Rows ``doc_id, ids, n_tokens, ids_sha256, decoded_sha256``; without ``ids`` that column is left out.

    One pass without a shuffle: Arrow batches in, digests out. Memory is one batch of texts and the
    table of distinct pre-tokens, which is bounded.
    """
    columns = "doc_id long, " + "ids array<int>, " * ids + "n_tokens long, ids_sha256 string, decoded_sha256 string"

    def run(parts: Iterator[dict]) -> Iterator[dict]:
        from pathtwin.llm.byte_bpe import codec_of

        codec = codec_of(ranks_path, pattern)
        for p in parts:
            out: dict[str, list] = {"doc_id": p["doc_id"], "ids": [], "n_tokens": [], "ids_sha256": [], "decoded_sha256": []}
            for text in p["text"]:
                pieces = codec.pieces(text or "")
                joined = " ".join(pieces)
                out["n_tokens"].append(joined.count(" ") + 1 if joined else 0)
                out["ids_sha256"].append(hashlib.sha256(joined.encode()).hexdigest())
                out["decoded_sha256"].append(hashlib.sha256(codec.decoded(pieces)).hexdigest())
                if ids:
                    out["ids"].append(np.array(joined.split(), np.int32))
            if not ids:
                del out["ids"]
            yield out

    named = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return map_slices(named, run, columns)
