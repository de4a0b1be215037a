"""Sequence packing with bounded space.

Every task keeps a fixed number of open windows. A piece goes into the window that it fits best; when
it fits none, the fullest window is topped up with the head of the piece and sent out full, and the
rest of the piece is placed again. What is left open in the tasks is merged in rounds of a fixed
fan-in until one task has the last windows, whose fill is cut into powers of two, so nothing is padded.

Nulls and empty texts are documents of the end id alone. Repeated rows are packed as often as they
occur. Ties go to the window opened first. An empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtwin.llm.common import map_slices
from pathtwin.plans.lineage import cut

WINDOW = 4096
#: Open windows of a task.
OPEN = 16
#: Tasks whose left-over windows one task of the next round merges.
FAN_IN = 32
#: Distinct blank-free strings a worker remembers.
HELD = 400_000
END_ID = 2

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, ids binary"


class WordIds:
    """Ids of texts by a tokenizer that drops blanks: every blank-free string is looked up once.

    New strings are encoded together, parted by a mark that the tokenizer keeps as a token of its own.
    The table has two generations; a full one becomes the old one, so frequent strings stay.
    """

    MARK = "\x01"

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.known: dict[str, bytes] = {"": b""}
        self.old: dict[str, bytes] = {}
        (self.mark_id,) = self._ids(self.MARK)

    def _ids(self, text: str) -> list[int]:
        return self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids

    def _learn(self, words: list[str]) -> None:
        alone = [w for w in words if self.MARK in w or len(w) > 200]
        for w in alone:
            self.known[w] = array("I", self._ids(w)).tobytes()
        for i in range(0, len(words), 2000):
            group = [w for w in words[i : i + 2000] if not (self.MARK in w or len(w) > 200)]
            ids = np.array(self._ids(f" {self.MARK} ".join([*group, ""])), "<u4")
            at = 0
            for w, end in zip(group, np.flatnonzero(ids == self.mark_id).tolist(), strict=True):
                self.known[w] = ids[at:end].tobytes()
                at = end + 1

    def batch(self, texts: list[str]) -> Iterator[np.ndarray]:
        """Ids of each text, as unsigned 32-bit arrays: the distinct strings are looked up, their ids gathered for all occurrences at once."""
        if not texts:
            return
        split = pc.split_pattern(pa.array([(t.lower() if t.isascii() else t).replace("\n", " ") for t in texts], pa.large_string()), " ")
        coded = split.values.dictionary_encode()
        words, which, ends = coded.dictionary.to_pylist(), coded.indices.to_numpy(), split.offsets.to_numpy()
        if len(self.known) > HELD:
            self.known, self.old = {"": b""}, self.known
        new, known = [], self.known
        for w in words:
            if w in known:
                continue
            if (ids := self.old.get(w)) is None:
                new.append(w)
            else:
                known[w] = ids
        self._learn(new)
        found = [known[w] for w in words]
        sizes = np.fromiter(map(len, found), np.int64, len(found)) // 4
        starts = np.cumsum(sizes) - sizes
        taken = sizes[which]
        before = np.cumsum(taken) - taken
        n = int(taken.sum())
        narrow = np.int32 if n + int(sizes.sum()) < 1 << 31 else np.int64
        at = np.repeat((starts[which] - before).astype(narrow), taken)
        at += np.arange(n, dtype=narrow)
        ids = np.frombuffer(b"".join(found), "<u4")[at]
        edges = np.append(before, len(ids))[ends]
        for i, j in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
            yield ids[i:j]

    def __call__(self, text: str) -> np.ndarray:
        return next(self.batch([text]))


_TOKENIZERS: dict[str, WordIds] = {}


def word_ids(path: str) -> WordIds:
    """One a Python worker, kept from task to task."""
    if path not in _TOKENIZERS:
        _TOKENIZERS[path] = WordIds(path)
    return _TOKENIZERS[path]


class Packer:
    """Bounded-space best fit. ``sent`` holds rows of finished windows."""

    def __init__(self, first_id: int, window: int = WINDOW, open_windows: int = OPEN):
        self.window, self.limit, self.next_id = window, open_windows, first_id
        self.open: list[tuple[int, list]] = []  # fill, pieces
        self.sent: list[tuple] = []

    def _send(self, pieces: list) -> None:
        at = 0
        for doc, start, ids, total in pieces:
            self.sent.append((doc, start, len(ids), zlib.crc32(ids.tobytes()), total, self.next_id, at, None))
            at += len(ids)
        self.next_id += 1

    def add(self, doc: int, start: int, ids: np.ndarray, total: int) -> None:
        while len(ids) >= self.window:
            self._send([(doc, start, ids[: self.window], total)])
            start, ids = start + self.window, ids[self.window :]
        while len(ids):
            fits = [(fill, -i) for i, (fill, _) in enumerate(self.open) if fill + len(ids) <= self.window]
            if fits:
                i = -max(fits)[1]
                fill, pieces = self.open[i]
                pieces.append((doc, start, ids, total))
                self.open[i] = (fill + len(ids), pieces)
                if self.open[i][0] == self.window:
                    self._send(self.open.pop(i)[1])
                return
            if len(self.open) < self.limit:
                self.open.append((len(ids), [(doc, start, ids, total)]))
                return
            i = max(range(len(self.open)), key=lambda k: (self.open[k][0], -k))
            fill, pieces = self.open.pop(i)
            room = self.window - fill
            self._send([*pieces, (doc, start, ids[:room], total)])
            start, ids = start + room, ids[room:]

    def left(self) -> list[tuple]:
        """Rows of the pieces in open windows, with their ids."""
        return [(doc, start, len(ids), None, total, None, None, ids.tobytes()) for _, pieces in self.open for doc, start, ids, total in pieces]

    def close(self) -> None:
        """Cuts what is open into full windows and powers of two."""
        flat = [p for _, pieces in self.open for p in pieces]
        self.open = []
        todo = sum(len(p[2]) for p in flat)
        while todo:
            size = min(self.window, 1 << (todo.bit_length() - 1))
            todo -= size
            row = []
            while size:
                doc, start, ids, total = flat.pop(0)
                row.append((doc, start, ids[:size], total))
                if len(ids) > size:
                    flat.insert(0, (doc, start + size, ids[size:], total))
                size -= min(size, len(ids))
            self._send(row)


def _columns(rows: list[tuple]) -> dict[str, list]:
    names = [c.split()[0] for c in PIECES.split(", ")]
    return {n: [r[k] for r in rows] for k, n in enumerate(names)}


def pack_documents(docs: DataFrame, tokenizer_path: str, window: int = WINDOW, open_windows: int = OPEN, fan_in: int = FAN_IN) -> DataFrame:
    """Rows ``doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset``, one a piece.

    The first round tokenises and packs each scan partition where it lies, without a shuffle, and is
    written once, so a window is never packed twice in different ways. Only left-over pieces, at most
    ``open_windows`` windows a task, move in the later rounds.
    """
    from pyspark import TaskContext

    def first(parts: Iterator[dict]) -> Iterator[dict]:
        ids_of, part = word_ids(tokenizer_path), TaskContext.get().partitionId()
        packer, end = Packer(part << 32, window, open_windows), np.array([END_ID], "<u4")
        for p in parts:
            for doc, ids in zip(p["doc_id"], ids_of.batch([t or "" for t in p["text"]]), strict=True):
                packer.add(doc, 0, np.append(ids, end), len(ids) + 1)
            yield _columns(packer.sent)
            packer.sent = []
        ids_of.old = {}
        yield _columns(packer.left())

    def later(base: int, last: bool):
        def run(parts: Iterator[dict]) -> Iterator[dict]:
            packer = Packer(base + (TaskContext.get().partitionId() << 32), window, open_windows)
            for p in parts:
                for doc, start, ids, total in zip(p["doc_id"], p["start"], p["ids"], p["doc_tokens"], strict=True):
                    packer.add(doc, start, np.frombuffer(ids, "<u4"), total)
                yield _columns(packer.sent)
                packer.sent = []
            if last:
                packer.close()
                yield _columns(packer.sent)
            else:
                yield _columns(packer.left())

        return run

    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    tasks = source.rdd.getNumPartitions()
    round_, parts = 0, []
    done = cut(map_slices(source, first, PIECES))
    while True:
        parts.append(done.filter("sequence_id is not null").drop("ids"))
        if round_ and tasks == 1:
            break
        tasks = max(1, -(-tasks // fan_in))
        round_ += 1
        left = done.filter("sequence_id is null")
        key = F.pmod(F.xxhash64("doc_id", "start"), F.lit(tasks))
        left = (left.coalesce(1) if tasks == 1 else left.repartition(tasks, key)).sortWithinPartitions("doc_id", "start", "length")
        done = cut(map_slices(left, later(round_ << 56, tasks == 1), PIECES))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out
