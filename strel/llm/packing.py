"""Bounded-space online packing of documents into windows of a fixed number of tokens.

A task reads its documents once, in order, and keeps at most ``open_windows`` windows. A document
longer than a window fills whole windows; what is left of it goes to the open window that it fits
most tightly. If none takes it, the fullest window is emitted: its gap is first filled with the
head of the document when the gap is at least ``min_cut`` tokens long. What is still open when the
input ends is merged over tasks, piece by piece, by best fit in falling size. Nothing is shuffled
but those leftovers, whose number is tasks x open windows.

Null and empty texts are one end-of-text id. Repeated doc_ids are packed once for each row. An
empty table gives no piece. Columns other than the two named are not read.
"""

from __future__ import annotations

import bisect
import zlib
from collections.abc import Iterator

import numpy as np
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from strel.llm.encode import blocks, each, encoder, small_batches, tidy, tokenizer_path
from strel.runtime import materialize, ship

WINDOW = 4096
OPEN_WINDOWS = 64
MIN_CUT = 16
END_ID = 2
#: Tasks whose leftovers meet in one merge task.
MERGE_TASKS = 16

_PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
_COLS = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]


class _Packer:
    """Best fit over a bounded number of open windows; pieces come out in closed windows."""

    def __init__(self, base: int, window: int, open_windows: int, min_cut: int):
        self.base, self.window, self.limit, self.min_cut = base, window, open_windows, min_cut
        self.free: list[tuple[int, int]] = []  # (room, window), sorted
        self.held: dict[int, list[tuple]] = {}
        self.next = base
        self.out: list[tuple] = []

    def _new(self) -> int:
        self.next += 1
        self.held[self.next - 1] = []
        return self.next - 1

    def _put(self, seq: int, room: int, piece: tuple) -> None:
        self.held[seq].append((*piece, seq, self.window - room))
        if room == piece[2]:
            self.out += self.held.pop(seq)
        else:
            bisect.insort(self.free, (room - piece[2], seq))

    def _emit_fullest(self) -> None:
        _, seq = self.free.pop(0)
        self.out += self.held.pop(seq)

    def add(self, doc_id: int, ids: np.ndarray) -> None:
        n, at = len(ids), 0
        piece = lambda a, b: (doc_id, a, b - a, zlib.crc32(ids[a:b]), n)
        while n - at >= self.window:
            self._put(self._new(), self.window, piece(at, at + self.window))
            at += self.window
        while at < n:
            k = bisect.bisect_left(self.free, (n - at, -1))
            if k < len(self.free):
                room, seq = self.free.pop(k)
                self._put(seq, room, piece(at, n))
                return
            if len(self.free) < self.limit:
                self._put(self._new(), self.window, piece(at, n))
                return
            room, seq = self.free[0]
            if room >= self.min_cut:
                self.free.pop(0)
                self._put(seq, room, piece(at, at + room))
                at += room
            else:
                self._emit_fullest()

    def left(self) -> list[tuple]:
        return [p for _, seq in self.free for p in self.held[seq]]


def _pack_task(path: str, window: int, open_windows: int, min_cut: int, end_id: int):
    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        task = TaskContext.get().partitionId() if TaskContext.get() else 0
        packer, enc = _Packer(task << 33, window, open_windows, min_cut), encoder(path)

        def table(rows: list[tuple], open_: bool) -> pa.RecordBatch:
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 7
            arrays = [pa.array(c, pa.int64()) for c in cols]
            arrays += [pa.array([open_] * len(rows), pa.bool_()), pa.array([task] * len(rows), pa.int64())]
            return pa.RecordBatch.from_arrays(arrays, [*_COLS, "is_open", "task"])

        for b in batches:
            for keys, texts in blocks(each(b.column("doc_id")), each(b.column("text"))):
                flat, counts = enc.ids(texts)
                at = 0
                for k, c in zip(keys, counts.tolist(), strict=True):
                    packer.add(k, np.append(flat[at : at + c], np.uint32(end_id)).astype("<u4", copy=False))
                    at += c
                if len(packer.out) > 20_000:
                    yield table(packer.out, False)
                    packer.out = []
        yield table(packer.out, False)
        yield table(packer.left(), True)
        tidy()

    return run


def _merge_group(window: int):
    def run(pdf):
        """Best fit in falling size: each piece keeps its ids and gets a window of the group."""
        pdf = pdf.sort_values(["length", "doc_id", "start"], ascending=[False, True, True], kind="stable").reset_index(drop=True)
        base = (1 << 62) | (int(pdf["grp"].iloc[0]) << 33)
        free: list[tuple[int, int]] = []
        seqs, offs, used = [], [], 0
        for n in pdf["length"].tolist():
            k = bisect.bisect_left(free, (n, -1))
            if k < len(free):
                room, seq = free.pop(k)
            else:
                room, seq, used = window, used, used + 1
            seqs.append(base + seq)
            offs.append(window - room)
            if room > n:
                bisect.insort(free, (room - n, seq))
        pdf["sequence_id"], pdf["offset"] = seqs, offs
        return pdf[_COLS]

    return run


def pack(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    window: int = WINDOW,
    open_windows: int = OPEN_WINDOWS,
    min_cut: int = MIN_CUT,
    end_id: int = END_ID,
    tokenizer: str | None = None,
) -> DataFrame:
    """One row for each piece of a document in a sequence.

    Columns: doc_id, start (ids of the document before the piece), length, ids_crc32, doc_tokens,
    sequence_id, offset (of the piece in its sequence). Every id lies in exactly one piece; a
    sequence is gapless from 0 and holds at most ``window`` ids.
    """
    ship(docs.sparkSession)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    with small_batches(docs.sparkSession):
        packed = materialize(
            rows.mapInArrow(_pack_task(tokenizer or tokenizer_path(), window, open_windows, min_cut, end_id), f"{_PIECE}, is_open boolean, task long"),
            "packing",
        )
    merged = (
        packed.where("is_open")
        .withColumn("grp", F.expr(f"task div {MERGE_TASKS}"))
        .groupBy("grp")
        .applyInPandas(_merge_group(window), _PIECE)
    )
    return packed.where("NOT is_open").select(*_COLS).unionByName(merged)
