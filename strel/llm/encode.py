"""Token ids of whole texts, by a public tokenizer file, at memory bandwidth rather than at BPE speed.

No pre-token of the word-level tokenizer spans white space, so the ids of a text are the ids of its
white-space separated chunks, one after the other. Chunks repeat: each worker keeps the ids of the
chunks that it has met (up to a bound, after which it starts afresh) and asks the tokenizer only
about new ones, many at a time. Everything else is NumPy gathers over a batch of texts.
"""

from __future__ import annotations

import contextlib
import ctypes
import gc
from collections.abc import Iterable, Iterator
from itertools import repeat

import numpy as np
from pyspark.sql import SparkSession

#: Distinct chunks a worker remembers at most, in two generations: when the young one is full it
#: becomes the old one, and chunks that recur come back from there.
CACHE_CHUNKS = 300_000
#: Distinct parts of chunks that it remembers before it starts afresh.
CACHE_PARTS = 300_000
#: Bytes of text handled at once.
BLOCK_BYTES = 1 << 20
#: Rows of an Arrow batch of whole texts, where an operator runs its own job.
BATCH_ROWS = 1_000
#: Rows of an Arrow batch that are Python objects at once.
SLICE_ROWS = 128


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class _Runs:
    """Runs of ids by key, in growing arrays."""

    def __init__(self):
        self.index: dict = {}
        self.ids = np.empty(1 << 16, np.uint32)
        self.used = 0
        self.start = np.zeros(1 << 14, np.int64)
        self.count = np.zeros(1 << 14, np.int64)

    def add(self, keys: list, ids: np.ndarray, count: np.ndarray) -> None:
        have, n = len(self.index), len(ids)
        while self.used + n > len(self.ids):
            self.ids = np.concatenate([self.ids, np.empty_like(self.ids)])
        while have + len(keys) > len(self.start):
            self.start = np.concatenate([self.start, np.zeros_like(self.start)])
            self.count = np.concatenate([self.count, np.zeros_like(self.count)])
        self.ids[self.used : self.used + n] = ids
        self.start[have : have + len(keys)] = self.used + np.cumsum(count) - count
        self.count[have : have + len(keys)] = count
        self.used += n
        self.index.update(zip(keys, range(have, have + len(keys)), strict=True))

    def take(self, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The runs at these places one after the other, and their lengths."""
        count, start = self.count[place], self.start[place]
        ends = np.cumsum(count)
        flat = np.arange(ends[-1] if len(ends) else 0)
        flat += np.repeat(start - (ends - count), count)
        return self.ids[flat], count


#: Punctuation that may end a chunk: as a run, it is a pre-token of its own.
_TAIL = "".join(c for c in map(chr, range(33, 127)) if not c.isalnum() and c not in "'<>|")
_TAIL_BYTES = _TAIL.encode()


class ChunkEncoder:
    """Ids by chunk, for a ``tokenizers`` file whose pre-tokens never hold white space.

    A chunk of letters and a tail of punctuation is two pre-tokens, and letters are lower-cased
    first: such chunks are put together from the ids of their two parts, which recur more often.
    """

    def __init__(self, path: str, cache_chunks: int = CACHE_CHUNKS):
        from tokenizers import Tokenizer

        self._tok = Tokenizer.from_file(path)
        self._limit = cache_chunks // 2
        vocab = self._tok.get_vocab(with_added_tokens=True)
        self._last = np.zeros(max(vocab.values()) + 1, bool)
        self._last[[i for t, i in vocab.items() if t.endswith("</w>")]] = True
        self._chunks, self._older, self._parts = _Runs(), _Runs(), _Runs()

    def _learn_parts(self, parts: list[str]) -> None:
        for at in range(0, len(parts), 8192):
            some = parts[at : at + 8192]
            ids = np.asarray(self._tok.encode(" ".join(some), add_special_tokens=False).ids, np.uint32)
            ends = np.flatnonzero(self._last[ids]) + 1
            if len(ends) != len(some):
                raise ValueError("a pre-token of this tokenizer does not end in a word end")
            self._parts.add(some, ids, np.diff(ends, prepend=0))

    def _learn_whole(self, chunks: list[bytes]) -> None:
        """Asks the tokenizer about ``chunks`` as one text, and cuts its ids by their offsets."""
        for at in range(0, len(chunks), 4096):
            part = chunks[at : at + 4096]
            words = [c.decode("utf-8", "replace") for c in part]
            found = self._tok.encode(" ".join(words), add_special_tokens=False)
            ids = np.asarray(found.ids, np.uint32)
            begin = np.cumsum([0] + [len(w) + 1 for w in words[:-1]])
            first = np.fromiter((o[0] for o in found.offsets), np.int64, len(ids))
            self._chunks.add(part, ids, np.bincount(np.searchsorted(begin, first, "right") - 1, minlength=len(part)))

    def _learn(self, chunks: list[bytes]) -> None:
        whole, split, cores, tails = [], [], [], []
        for c in chunks:
            plain = c.rstrip(_TAIL_BYTES)
            if plain.isalpha():  # ASCII letters
                split.append(c)
                cores.append(plain.lower().decode())
                tails.append(c[len(plain) :].decode())
                continue
            s = c.decode("utf-8", "replace")
            core = s.rstrip(_TAIL)
            if core.isalpha() and (core.isascii() or (max(core) < "\u0250" and "\u0130" not in core)):
                split.append(c)
                cores.append(core.lower())
                tails.append(s[len(core) :])
            else:
                whole.append(c)
        if whole:
            self._learn_whole(whole)
        if split:
            index = self._parts.index
            self._learn_parts([p for p in {*cores, *tails} if p and p not in index])
            index[""] = index.get("", -1)
            place = np.fromiter((index[p] for pair in zip(cores, tails, strict=True) for p in pair), np.int64, 2 * len(split))
            index.pop("")
            real = place >= 0
            ids, count = self._parts.take(place[real])
            both = np.zeros(len(place), np.int64)
            both[real] = count
            self._chunks.add(split, ids, both[0::2] + both[1::2])

    def _places(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """For all chunks of ``texts``, their place in the cache; and how many each text has."""
        chunks: list[bytes] = []
        sizes = np.empty(len(texts), np.int64)
        for i, t in enumerate(texts):
            own = t.split()
            sizes[i] = len(own)
            chunks += own
        if len(self._chunks.index) > self._limit:
            self._chunks, self._older = _Runs(), self._chunks
        if len(self._parts.index) > CACHE_PARTS:
            self._parts = _Runs()
        index = self._chunks.index
        place = np.fromiter(map(index.get, chunks, repeat(-1)), np.int64, len(chunks))
        new = np.flatnonzero(place < 0).tolist()
        if new:
            unknown = list(dict.fromkeys([chunks[i] for i in new]))
            if self._older.index:
                back = [c for c in unknown if c in self._older.index]
                if back:
                    self._chunks.add(back, *self._older.take(np.fromiter(map(self._older.index.get, back), np.int64, len(back))))
                    unknown = [c for c in unknown if c not in self._older.index]
            self._learn(unknown)
            place[new] = [index[chunks[i]] for i in new]
        return place, sizes

    def counts(self, texts: list[bytes]) -> np.ndarray:
        """Number of ids of each text."""
        place, sizes = self._places(texts)
        total = np.concatenate([[0], np.cumsum(self._chunks.count[place])])
        ends = np.cumsum(sizes)
        return total[ends] - total[ends - sizes]

    def ids(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """All ids in one array, and how many belong to each text."""
        place, sizes = self._places(texts)
        ids, count = self._chunks.take(place)
        total = np.concatenate([[0], np.cumsum(count)])
        stop = np.cumsum(sizes)
        return ids, total[stop] - total[stop - sizes]


_ENCODERS: dict[str, ChunkEncoder] = {}


def encoder(path: str) -> ChunkEncoder:
    """The worker's encoder for a tokenizer file; it outlives a task."""
    if path not in _ENCODERS:
        _ENCODERS[path] = ChunkEncoder(path)
    return _ENCODERS[path]


def each(column) -> Iterator:
    """Values of an Arrow column; only some rows are Python objects at a time."""
    for at in range(0, len(column), SLICE_ROWS):
        yield from column.slice(at, SLICE_ROWS).to_pylist()


def tidy() -> None:
    """Gives memory that a task has freed back to the system, as its worker lives on."""
    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # not on every libc
        ctypes.CDLL("libc.so.6").malloc_trim(0)


@contextlib.contextmanager
def small_batches(spark: SparkSession, rows: int = BATCH_ROWS) -> Iterator[None]:
    """What runs inside sends whole texts to Python in batches of few rows, so that neither side
    holds thousands of them; the session's own setting is back afterwards."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    if not 0 < int(before) <= rows:
        spark.conf.set(key, str(rows))
    try:
        yield
    finally:
        spark.conf.set(key, before)


def blocks(keys: Iterable, texts: Iterable[str | None], limit: int = BLOCK_BYTES) -> Iterator[tuple[list, list[bytes]]]:
    """Cuts rows into blocks of about ``limit`` bytes; a longer text is a block of its own."""
    ks: list = []
    ts: list[bytes] = []
    size = 0
    for k, t in zip(keys, texts, strict=True):
        b = t.encode("utf-8", "replace") if isinstance(t, str) else (t or b"")
        if ts and size + len(b) > limit:
            yield ks, ts
            ks, ts, size = [], [], 0
        ks.append(k)
        ts.append(b)
        size += len(b)
    if ts:
        yield ks, ts
