"""Exact similarity join of shingle sets by parity sketches.

A set is dealt, by its elements' hashes, into P parts. The XOR of a part's hashes is the parity
sketch of that part: two sets have equal sketches in every part that holds no element of their
symmetric difference. Sets A and B with Jaccard similarity of at least t differ in at most
(1-t)/(1+t) (|A|+|B|) elements, so out of P parts all but that many agree: the pigeonhole keys.
P and the bound are those of the size band of the smaller set; a set near the lower edge of its
band also takes part in the band below.

Only a prefix of a set's keys is emitted. If two sets agree in at least s of P keys, then under
any order that all sets share, the first P-s+r keys of each agree in at least r. Keys of empty
parts come last in that order, so they are (almost) never needed. Keys that only one set has
vanish where the keys meet; a set left with fewer than r keys has no partner and vanishes too,
which frees more keys. So sets that only have a common passage drop out before any pair exists.

Links within a group of near copies need not all be looked at to know its class: each set is first
compared with one smaller set, that with which it shares most keys, then each class with one other
class in the same way, as long as that links many. Of the sets of a key that still lie in different
classes, those outside the key's largest class then ask for partners among all others: first for
the few whose sketches are nearest, and once classes have grown by these, sets with more partners in
other classes ask for many more, until every one has been given all. So a large group of
near copies is joined by some links a set, and only sets that stay apart are compared one by one.

Before two sets are compared, Hamming distances of their parity sketches (every element flips one
bit) bound their difference from below: first of narrow ones, then of wide ones. Widths are those of
the size band, 8 bits for each element in which two of its sets may differ (4 and at most 4,096 in
all for the narrow sketch, which travels with keys), so nearly every pair that is not similar goes.

Equal sets (exact copies) are one set from the start; a set is known by 63 bits of a hash, so the
chance that two of 10^9 sets are taken for one is below 0.06. Nothing is sampled or capped.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from strel.llm.encode import blocks, each, small_batches, tidy
from strel.llm.shingles import WINDOW, mix, shingle_hashes
from strel.runtime import discard, materialize, ranked, ship

_U = np.uint64
#: Ratio of the bounds of a size band.
BAND_RATIO = 4
#: Bits of a band's sketch for each element in which two of its sets may differ; and of the narrow
#: one, that travels with keys, and its width at most.
BITS_AN_ELEMENT, NARROW_BITS, NARROWEST = 8, 4, 4_096
#: Keys that one task joins, bytes of text that give one key, and how many times its share a bucket
#: may hold before it is joined by rows.
KEYS_PER_TASK, BYTES_A_KEY, HOT_FACTOR = 1_000_000, 12, 4
#: Partners that a set asks a bucket for at first, and how many times as many in each further round.
NEAREST, MORE = 4, 16
#: Words of the sketch of a band that still travels with keys in those rounds, instead of the narrow one.
WORDS_SENT = 128
#: Sets of a key beyond which its pairs are joined by rows; pairs that a task holds before it folds
#: them; and words of sketches that it compares at once.
HOT_KEY, PAIRS_HELD, PAIRS_AT_ONCE = 3_000, 500_000, 1_000_000
#: Rows (of a key, a set and its narrow sketch, some 300 bytes) of a bucket in which pairs are looked for.
CANDIDATE_ROWS = 40_000
#: Distinct sets whose keys a task remembers having emitted.
SEEN_SETS = 100_000
#: Rounds of comparing each class with one other go on while they link one set in so many.
FEW_LINKS = 200
#: Ids that may be sent to every executor (8 bytes each); more are joined by a shuffle.
BROADCAST_IDS = 2_000_000


class Bands:
    """Parts, prefixes and needed agreements by set size, for a similarity of num/den or more."""

    def __init__(self, num: int, den: int):
        self.num, self.den = num, den

    def differ(self, total: int) -> int:
        """Elements in which two sets of so many elements together may differ."""
        return (self.den - self.num) * total // (self.den + self.num)

    def of(self, n: int) -> list[tuple[int, int, int]]:
        """(band, its number of parts, elements in which a partner there may differ) of a size."""
        b = int(math.log(n, BAND_RATIO) + 1e-9)
        b += (BAND_RATIO ** (b + 1) <= n) - (BAND_RATIO**b > n)
        out = []
        for band, own in ((b, True), (b - 1, False)):
            if band < 0:
                continue
            top = BAND_RATIO ** (band + 1) - 1
            widest = top * self.den // self.num
            if own or n <= widest:
                most = self.differ(top + widest)
                larger = n if not own else n * self.den // self.num
                out.append((band, most + most // 2 + 64, min(most, self.differ(n + larger))))
        return out

    def bits(self, band: int, each: int = BITS_AN_ELEMENT) -> int:
        """Width of the Hamming sketch of a band: wide enough that its bound is close."""
        top = BAND_RATIO ** (band + 1) - 1
        return 1 << max(6, (each * self.differ(top + top * self.den // self.num) - 1).bit_length())

    def narrow(self, band: int) -> int:
        return min(NARROWEST, self.bits(band, NARROW_BITS))

    def keys(self, s: np.ndarray, band: int, parts: int, differ: int) -> tuple[np.ndarray, int]:
        """The emitted keys of a set and the number of them that any partner shares."""
        part = ((s >> _U(32)) * _U(parts)) >> _U(32)
        first = np.flatnonzero(np.concatenate([[True], part[1:] != part[:-1]]))
        salt = _U((band + 1) << 40)
        found = mix(np.bitwise_xor.reduceat(s, first) ^ mix(part[first] + salt))
        need = need_of(len(first), differ)
        take = differ + need
        if take < len(found):
            found = np.partition(found, take - 1)[:take]
        elif take > len(found):
            empty = np.ones(parts, bool)
            empty[part[first].astype(np.int64)] = False
            zero = np.sort(mix(mix(np.flatnonzero(empty).astype(_U) + salt) + _U(1)))
            found = np.concatenate([found, zero[: take - len(found)]])
        return found, need


def need_of(full: int, differ: int) -> int:
    """Keys that a set with ``full`` filled parts shares with any partner."""
    return max(1, full - differ)


def _sets(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    ship(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def _identity(s: np.ndarray) -> tuple[int, int]:
    """Two hashes of a set; the last bit of the first is free."""
    with np.errstate(over="ignore"):
        return int(np.bitwise_xor.reduce(mix(s + _U(7)))) & ~1, int(mix(s + _U(11)).sum(dtype=_U))


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


#: Rows of documents, and rows of keys, of one pass over the texts.
_READ = "doc_id long, n long, set_a long, set_b long, need_own int, need_low int, bucket long, keys binary, sets binary"


def _read(width: int, bands: Bands, buckets: int):
    """One pass over the texts: a row for each document, and for each block of texts and bucket of
    keys the packed (32 bits of the key, set) pairs. A set that the task has met lately emits none."""

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.binary()]
        names = [c.split()[0] for c in _READ.split(", ")]

        def table(cols: list, first: int) -> pa.RecordBatch:
            n = len(cols[0])
            at = range(first, first + len(cols))
            return pa.RecordBatch.from_arrays([pa.array(cols[k - first], t) if k in at else pa.nulls(n, t) for k, t in enumerate(kinds)], names)

        seen: set[int] = set()
        for b in batches:
            for ids, texts in blocks(each(b.column("doc_id")), each(b.column("text")), WINDOW):
                rows, keys, sets = [], [], []
                for i, s in zip(ids, shingle_hashes(texts, width), strict=True):
                    if not len(s):
                        rows.append((i, 0, None, None, None, None))
                        continue
                    a, c = _identity(s)
                    emit = a not in seen
                    if emit:
                        if len(seen) >= SEEN_SETS:
                            seen.clear()
                        seen.add(a)
                    need = []
                    for low, (band, parts, differ) in enumerate(bands.of(len(s))):
                        if emit:
                            k, least = bands.keys(s, band, parts, differ)
                            keys.append(k)
                            sets.append(np.full(len(k), a | low, _U))
                        else:
                            least = need_of(_filled(s, parts), differ)
                        need.append(least)
                    rows.append((i, len(s), _signed(a), _signed(c), need[0], need[1] if len(need) > 1 else None))
                yield table(list(zip(*rows, strict=True)), 0)
                if not keys:
                    continue
                key, own = np.concatenate(keys), np.concatenate(sets)
                bucket = ((key >> _U(32)) * _U(buckets)) >> _U(32)
                order = np.argsort(bucket, kind="stable")
                bucket, key, own = bucket[order].astype(np.int64), (key[order] & _U(0xFFFFFFFF)).astype("<u4"), own[order].astype("<u8")
                first = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]]))
                ends = list(zip(first.tolist(), [*first[1:].tolist(), len(bucket)], strict=True))
                yield table([bucket[first], [key[i:j].tobytes() for i, j in ends], [own[i:j].tobytes() for i, j in ends]], 6)
        tidy()

    return run


def _filled(s: np.ndarray, parts: int) -> int:
    part = ((s >> _U(32)) * _U(parts)) >> _U(32)
    return 1 + int(np.count_nonzero(part[1:] != part[:-1]))


def _tidied(work):
    """A task's work on one group, after which its memory goes back to the system."""

    def run(tbl):
        out = work(tbl)
        tidy()
        return out

    return run


def _meet(tbl):
    """Keys of a bucket that at least two sets have, each with its sets."""
    import pyarrow as pa

    bucket = tbl.column("bucket")[0].as_py()
    key = np.frombuffer(b"".join(tbl.column("keys").to_pylist()), "<u4")
    own = np.frombuffer(b"".join(tbl.column("sets").to_pylist()), "<u8")
    order = np.argsort(key, kind="stable")
    key, own = key[order], own[order]
    same = np.concatenate([[False], key[1:] == key[:-1]])
    shared = same | np.concatenate([same[1:], [False]])
    key, own = key[shared], own[shared]
    order = np.lexsort((own, key))
    key, own = key[order], own[order]
    if len(key):
        fresh = np.concatenate([[True], (key[1:] != key[:-1]) | (own[1:] != own[:-1])])
        key, own = key[fresh], own[fresh]
        same = np.concatenate([[False], key[1:] == key[:-1]])
        shared = same | np.concatenate([same[1:], [False]])
        key, own = key[shared], own[shared]
    return pa.table({"key": pa.array(key.astype(np.int64) + (bucket << 32), pa.int64()), "reg": pa.array(own.view(np.int64), pa.int64())})


def _unpack(batches: Iterator) -> Iterator:
    """Packed keys as rows."""
    import pyarrow as pa

    for b in batches:
        for at in range(b.num_rows):
            key, own = (np.frombuffer(b.column(c)[at].as_py(), t) for c, t in (("keys", "<u4"), ("sets", "<u8")))
            yield pa.RecordBatch.from_arrays([pa.array(key.astype(np.int64) + (b.column("bucket")[at].as_py() << 32), pa.int64()), pa.array(own.view(np.int64), pa.int64())], ["key", "reg"])


def parity_bits(s: np.ndarray, bits: int) -> np.ndarray:
    """A sketch of ``bits`` (a power of two) parities as words: each element flips one of them."""
    odd = np.bincount((mix(s) & _U(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8)).view("<i8")


_SETS = "id long, n long, elements array<long>, narrow array<long>, wide array<long>, narrow_low array<long>, wide_low array<long>"


def _stored_sets(width: int, bands: Bands):
    """Sets with their sketches: a narrow one, and those of the size bands that they take part in."""

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for b in batches:
            for _, texts in blocks(each(b.column("doc_id")), each(b.column("text")), WINDOW):
                rows = []
                for s in shingle_hashes(texts, width):
                    if len(s):
                        of = [(parity_bits(s, bands.narrow(band)), parity_bits(s, bands.bits(band))) for band, _, _ in bands.of(len(s))]
                        rows.append((_signed(_identity(s)[0]), len(s), s.view(np.int64), *of[0], *(of[1] if len(of) > 1 else (None, None))))
                cols = list(zip(*rows, strict=True)) or [[]] * 7
                longs = pa.list_(pa.int64())
                kinds = [pa.int64(), pa.int64(), longs, longs, longs, longs, longs]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], [c.split()[0] for c in _SETS.split(", ")])
        tidy()

    return run


def by_ids(rows: DataFrame, ids: DataFrame, col: str, limit: int = BROADCAST_IDS) -> DataFrame:
    """``rows`` whose ``col`` is among ``ids`` (a stored table of distinct values of that name).

    The ids go to every executor only if they are counted and few; else both sides are shuffled.
    """
    return rows.join(F.broadcast(ids) if ids.count() <= limit else ids, col, "left_semi")


def components(edges: DataFrame, tag: str = "classes") -> DataFrame:
    """Classes of connected ids: columns id and component (its smallest id), for ids on an edge.

    Rounds of two steps that hang every id below the smallest one it can see. No group is gathered:
    minima are pre-aggregated and joined back. Each round is stored in the shared folder.
    """
    edges = materialize(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u > v").distinct(), tag)
    before = None
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        far = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        far = far.where("u > v").distinct()
        low = far.groupBy("u").agg(F.min("v").alias("m"))
        near = far.join(low, "u")
        near = near.where("v > m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v"))).distinct()
        edges = materialize(near, tag, edges)
        now = tuple(edges.agg(F.count(F.lit(1)), F.sum(F.expr("xxhash64(u, v) div 4096"))).first())
        if now == before:
            break
        before = now
    low = edges.groupBy("u").agg(F.min("v").alias("component"))
    return low.select(F.col("u").alias("id"), "component").unionByName(low.select(F.col("component").alias("id"), "component").distinct())


def _candidates(num: int, den: int, most: int):
    """Distinct pairs of sets of different classes that share a key of a bucket and that sizes and
    narrow sketches allow: of each set ``ra`` that asks, those with the ``most`` nearest ``rb``.

    ``cut`` tells that the set has more. A set asks where ``asks`` is 1, and where it is -1 outside
    its key's largest class; so without cuts no pair is left out.
    """

    def run(tbl):
        import pyarrow as pa

        tbl = tbl.combine_chunks()
        key, reg, c, n, asks = (np.asarray(tbl.column(x), np.int64) for x in ("key", "reg", "c", "n", "asks"))
        order = np.lexsort((n, key))
        key = key[order]
        sketch = tbl.column("narrow").combine_chunks()
        begin, words = np.asarray(sketch.offsets), np.asarray(sketch.values).view(_U)
        first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        found: list[tuple[np.ndarray, ...]] = []
        cut: list[np.ndarray] = []
        held = 0

        def fold() -> tuple[np.ndarray, ...]:
            if not found:
                return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
            u, v, far = (np.concatenate(x) for x in zip(*found, strict=True))
            by = np.lexsort((v, far, u))
            u, v, far = u[by], v[by], far[by]
            fresh = np.concatenate([[True], (u[1:] != u[:-1]) | (v[1:] != v[:-1])])
            u, v, far = u[fresh], v[fresh], far[fresh]
            own = np.flatnonzero(np.concatenate([[True], u[1:] != u[:-1]]))
            place = np.arange(len(u)) - np.repeat(own, np.diff(np.append(own, len(u))))
            cut.append(np.unique(u[place >= most]))
            near = place < most
            return u[near], v[near], far[near]

        for i, j in zip(first.tolist(), [*first[1:].tolist(), len(key)], strict=True):
            at = order[i:j]
            k = c[at]
            if j - i < 2 or (k == k[0]).all():
                continue
            r, m, ask = reg[at], n[at], asks[at]
            several, often = np.unique(k, return_counts=True)
            ask = (ask == 1) | ((ask == -1) & (k != several[np.argmax(often)]))
            width = begin[at + 1] - begin[at]
            for w in np.unique(width).tolist():  # sets of one band, but for collisions of keys
                own = np.flatnonzero(width == w)
                bits = words[begin[at[own]][:, None] + np.arange(w)[None, :]]
                asking = np.flatnonzero(ask[own])
                rows = max(1, PAIRS_AT_ONCE // max(1, len(own) * w))
                for top in range(0, len(asking), rows):
                    some = asking[top : top + rows]
                    x, y = np.repeat(some, len(own)), np.tile(np.arange(len(own)), len(some))
                    p, q = own[x], own[y]
                    fit = (k[p] != k[q]) & ((r[p] & r[q] & 1) == 0) & (np.minimum(m[p], m[q]) * den >= np.maximum(m[p], m[q]) * num)
                    x, y, p, q = x[fit], y[fit], p[fit], q[fit]
                    apart = np.bitwise_count(bits[x] ^ bits[y]).sum(1, dtype=np.int64)
                    fit = apart * (den + num) <= (m[p] + m[q]) * (den - num)
                    if fit.any():
                        p, q = p[fit], q[fit]
                        found.append((r[p], r[q], apart[fit] / (m[p] + m[q])))
                        held += len(p)
                    if held > PAIRS_HELD:
                        found[:] = [fold()]
                        held = len(found[0][0]) // 2
        u, v, _ = fold()
        return pa.table({"ra": pa.array(u), "rb": pa.array(v), "cut": pa.array(np.isin(u, np.concatenate([*cut, np.zeros(0, np.int64)])))})

    return run


def _shared_keys(read: DataFrame, keys_per_task: int) -> DataFrame:
    """key and reg of the keys that at least two sets have.

    A bucket is one task's work. One that holds far more than its share (a key of very many sets)
    is taken apart into rows, and its keys are counted by a pre-aggregated shuffle instead.
    """
    packed = read.where("bucket IS NOT NULL").select("bucket", "keys", "sets")
    hot = packed.groupBy("bucket").agg(F.sum(F.length("keys")).alias("size")).where(F.col("size") > 4 * HOT_FACTOR * keys_per_task).select("bucket")
    hot = materialize(hot, "hot-buckets")
    if not hot.limit(1).count():
        return packed.groupBy("bucket").applyInArrow(_tidied(_meet), "key long, reg long")
    hot = F.broadcast(hot)  # at most one in HOT_FACTOR of the buckets
    usual = packed.join(hot, "bucket", "left_anti").groupBy("bucket").applyInArrow(_tidied(_meet), "key long, reg long")
    rows = packed.join(hot, "bucket", "left_semi").mapInArrow(_unpack, "key long, reg long").distinct()
    often = rows.groupBy("key").agg(F.count(F.lit(1)).alias("c")).where("c > 1").select("key")
    return usual.unionByName(rows.join(often, "key", "left_semi"))


def _jump(pointers: DataFrame) -> DataFrame:
    """c and up: where pointers to ever smaller classes lead in the end."""
    now = materialize(pointers, "pointers")
    before = None
    while True:
        ups = now.select(F.col("c").alias("up"), F.col("up").alias("upper"))
        now = materialize(now.join(ups, "up", "left").select("c", F.coalesce("upper", "up").alias("up")), "pointers", now)
        total = now.agg(F.sum(F.expr("xxhash64(c, up) div 4096"))).first()[0]
        if total == before:
            return now
        before = total


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, num: int = 75, den: int = 100, keys_per_task: int = KEYS_PER_TASK) -> DataFrame:
    """Classes of documents linked by similar sets of word shingles.

    Two documents are linked if den * |A and B| >= num * |A or B| over their distinct shingles of
    ``width`` words. Columns: doc_id, n_shingles, component_id (the smallest doc_id that links
    lead to). A text without words, or null, has no shingle and is linked with nothing. Rows with
    the same doc_id count as one document for each different text; equal texts are linked whatever
    their ids, and null ids are left out of the smallest. An empty table gives no row. Other columns
    are not read.
    """
    with small_batches(docs.sparkSession):
        return _classes(docs, id_col, text_col, width, num, den, keys_per_task)


def _classes(docs: DataFrame, id_col: str, text_col: str, width: int, num: int, den: int, keys_per_task: int) -> DataFrame:
    g = math.gcd(num, den)
    bands = Bands(num // g, den // g)
    rows = _sets(docs, id_col, text_col)
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = max(16, math.ceil(size / BYTES_A_KEY / keys_per_task))
    read = materialize(rows.mapInArrow(_read(width, bands, buckets), _READ), "read")
    doc = materialize(read.where("bucket IS NULL").select("doc_id", "n", "set_a", "set_b"), "sets")
    # a set is known by its first hash from here on
    one = materialize(read.where("set_a IS NOT NULL").groupBy("set_a", "set_b", "need_own", "need_low").agg(F.min("doc_id").alias("doc_id")), "distinct-sets")
    met = materialize(_shared_keys(read, keys_per_task), "keys", read)
    # every set once for each band that it takes part in, with the number of keys a partner shares
    regs = one.selectExpr("stack(2, set_a, need_own, set_a | 1L, need_low) AS (reg, need)").where("need IS NOT NULL")
    live = met.groupBy("reg").agg(F.count(F.lit(1)).alias("have")).join(regs, "reg").where("have >= need")
    live = materialize(live.groupBy("reg").agg(F.min("need").alias("need")), "live")

    def enough(rows: DataFrame) -> DataFrame:
        """Rows of sets that still have at least as many keys as they share with any partner."""
        have = rows.groupBy("reg").agg(F.count(F.lit(1)).alias("have")).join(live, "reg").where("have >= need")
        return by_ids(rows, materialize(have.select("reg"), "enough"), "reg")

    met = materialize(by_ids(met, live.select("reg"), "reg"), "keys", met)
    # keys of sets that are gone leave others alone; two sets from the band above meet there
    again = met.groupBy("key").agg(F.min("reg").alias("lo"), F.max("reg").alias("hi"), F.bit_and(F.col("reg").bitwiseAND(1)).alias("low")).where("lo < hi AND low = 0").select("key")
    met = materialize(met.join(again, "key", "left_semi"), "keys", met)
    met = materialize(enough(met), "keys", met)
    need = materialize(met.select(F.expr("reg & -2L").alias("id")).distinct(), "with-partners")
    few = need.count() <= BROADCAST_IDS
    wanted = F.broadcast(need) if few else need
    first = one.join(wanted.withColumnRenamed("id", "set_a"), "set_a", "left_semi").select(F.col("doc_id").alias("__id")).distinct()
    found = rows.join(F.broadcast(first) if few else first, F.col("doc_id").eqNullSafe(F.col("__id")), "left_semi")
    found = found.mapInArrow(_stored_sets(width, bands), _SETS)
    packed = materialize(found.join(wanted, "id", "left_semi").dropDuplicates(["id"]), "elements")
    own = packed.select(F.col("id").alias("reg"), "n", "narrow", "wide")
    small = own.unionByName(packed.where("wide_low IS NOT NULL").select(F.expr("id | 1L").alias("reg"), "n", F.col("narrow_low").alias("narrow"), F.col("wide_low").alias("wide")))
    small = materialize(small, "sketches")
    apart = lambda c: f"aggregate(zip_with(p.{c}, q.{c}, (x, y) -> bit_count(x ^ y)), 0, (s, x) -> s + x) * {bands.den + bands.num} <= (p.n + q.n) * {bands.den - bands.num}"
    # bounds by sizes, then by the narrow sketch, then by that of the band
    likely = f"least(p.n, q.n) * {bands.den} >= greatest(p.n, q.n) * {bands.num} AND {apart('narrow')} AND {apart('wide')}"

    def bounded(pairs: DataFrame) -> DataFrame:
        """Pairs ra, rb (with a, b) that the bounds allow."""
        p, q = small.alias("p"), small.alias("q")
        return pairs.join(p, pairs["ra"] == F.col("p.reg")).join(q, (pairs["rb"] == F.col("q.reg")) & F.expr(likely)).select("a", "b")

    def similar(pairs: DataFrame) -> DataFrame:
        """Pairs a, b of sets that are similar by their elements."""
        some = materialize(pairs, "pairs")
        light = some.count() <= BROADCAST_IDS
        sized = F.broadcast(some) if light else some
        x = packed.select(F.col("id").alias("a"), F.col("elements").alias("x")).join(sized, "a")
        involved = some.select(F.col("b").alias("id")).distinct()
        y = packed.join(F.broadcast(involved) if light else involved, "id", "left_semi").select(F.col("id").alias("b"), F.col("elements").alias("y"))
        common = F.size(F.array_intersect("x", "y")).cast("long")
        enough_common = common * (bands.den + bands.num) >= bands.num * (F.size("x") + F.size("y")).cast("long")
        return materialize(x.join(y, "b").where(enough_common).select("a", "b"), "links", some)

    # classes are numbered in the order of documents: an original mostly comes before what is made of it
    sets = one.join(wanted.withColumnRenamed("id", "set_a"), "set_a", "left_semi").groupBy(F.col("set_a").alias("id")).agg(F.min("doc_id").alias("d"))
    comp = materialize(ranked(sets, [F.col("d").asc_nulls_last(), F.col("id")], "c", "numbered").select("id", "c"), "classes")
    classes = comp.count()
    sent = F.broadcast if classes <= BROADCAST_IDS else lambda d: d
    tested, open_ = None, met
    with_class = lambda rows: rows.withColumn("id", F.expr("reg & -2L")).join(sent(comp), "id").drop("id")
    while classes:
        # each class against the one smaller class with which one of its sets shares most keys; of
        # the keys only those that classes still share are kept
        known = with_class(open_)
        low = known.groupBy("key").agg(F.min(F.struct("c", "reg")).alias("low"), F.max("c").alias("hi")).where("low.c < hi").select("key", F.col("low.c").alias("hub_c"), F.col("low.reg").alias("hub"))
        joined = materialize(known.join(low, "key"), "split-keys")
        joined = materialize(enough(joined), "open-keys", joined)
        ends = joined.where("c > hub_c AND reg & hub & 1 = 0").groupBy("reg", "c", "hub", "hub_c").agg(F.count(F.lit(1)).alias("shared"))
        ends = ends.withColumn("a", F.expr("least(reg & -2L, hub & -2L)")).withColumn("b", F.expr("greatest(reg & -2L, hub & -2L)"))
        if tested is not None:
            ends = ends.join(tested, ["a", "b"], "left_anti")
        best = materialize(ends.groupBy("c").agg(F.max(F.struct("shared", "hub_c", "a", "b", "reg", "hub")).alias("x")).select("c", "x.hub_c", "x.a", "x.b", F.col("x.reg").alias("ra"), F.col("x.hub").alias("rb")), "best")
        good = similar(bounded(best))
        links = good.count()
        tested = materialize(best.select("a", "b") if tested is None else tested.unionByName(best.select("a", "b")), "tested", tested)
        if links:
            ups = _jump(best.join(good, ["a", "b"], "left_semi").select("c", F.col("hub_c").alias("up")))
            comp = materialize(comp.join(ups, "c", "left").select("id", F.coalesce("up", "c").alias("c")), "classes", comp, ups)
        open_ = materialize(joined.select("key", "reg"), "open-keys", open_, joined)
        discard(good, best)
        if links * FEW_LINKS < classes:
            break
    # what still lies in different classes and shares enough keys: every pair of it. Of all keys of
    # a set but need-1 at least one is shared, so the rarest ones do
    known = with_class(open_)
    often = known.groupBy("key").agg(F.count(F.lit(1)).alias("often"), F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo < hi").select("key", "often")
    known = materialize(known.join(often, "key"), "split-keys", open_)
    have = materialize(known.groupBy("reg").agg(F.count(F.lit(1)).alias("have")).join(live, "reg").where("have >= need"), "have")
    place = F.row_number().over(Window.partitionBy("reg").orderBy("often", "key"))
    rare = known.join(F.broadcast(have) if have.count() <= BROADCAST_IDS else have, "reg").withColumn("place", place).where("place <= have - need + 1")
    rare = materialize(rare.join(small.select("reg", "n", "narrow"), "reg").select("key", "reg", "c", "n", "often", "narrow", F.lit(-1).alias("asks")), "rare-keys", known)
    share = max(8, math.ceil(rare.count() / CANDIDATE_ROWS))
    pair = lambda rows: rows.withColumn("a", F.expr("least(ra & -2L, rb & -2L)")).withColumn("b", F.expr("greatest(ra & -2L, rb & -2L)"))
    untested = lambda rows: rows if tested is None else rows.join(tested, ["a", "b"], "left_anti")
    side = lambda x, y: comp.select(F.col("id").alias(x), F.col("c").alias(y))

    def grown(good: DataFrame) -> DataFrame:
        """Classes after the links ``good``."""
        merged = components(good.join(side("a", "ca"), "a").join(side("b", "cb"), "b").select(F.col("ca").alias("a"), F.col("cb").alias("b")))
        return materialize(comp.join(merged.withColumnRenamed("id", "c"), "c", "left").select("id", F.coalesce("component", "c").alias("c")), "classes", comp)

    # a bucket of keys gives each set its nearest partners, then more of them to those that have more.
    # The sets of a key of very many are dealt anew in each round, so that most of them meet a partner
    very = F.col("often") > HOT_KEY
    hot = rare.where(very).limit(1).count() > 0
    most, turn, spent = NEAREST, 0, []
    while True:
        deal = F.when(very, F.expr(f"pmod(xxhash64(reg, {turn}), CAST(ceil(often / {HOT_KEY}) AS LONG))")).otherwise(F.lit(0))
        dealt = rare.withColumn("key", F.xxhash64("key", deal)).withColumn("bucket", F.expr(f"pmod(key, {share})")).drop("often")
        pairs = dealt.groupBy("bucket").applyInArrow(_tidied(_candidates(bands.num, bands.den, most)), "ra long, rb long, cut boolean")
        pairs = materialize(pair(pairs), "met-pairs")
        good = similar(bounded(untested(pairs.select(F.least("ra", "rb").alias("ra"), F.greatest("ra", "rb").alias("rb"), "a", "b").distinct())).distinct())
        links = good.count()
        if links:
            comp = grown(good)
        asking = materialize(pairs.where("cut").select(F.col("ra").alias("reg")).distinct(), "asking")
        more = asking.count()
        discard(good)
        spent += [pairs, asking]
        if not more and not (hot and links * FEW_LINKS >= classes):
            break
        tested = materialize(pairs.select("a", "b").distinct() if tested is None else tested.unionByName(pairs.select("a", "b")).distinct(), "tested", tested)
        flagged = asking.withColumn("flag", F.lit(1))
        now = with_class(rare.drop("c", "asks")).join(F.broadcast(flagged) if more <= BROADCAST_IDS else flagged, "reg", "left")
        now = now.withColumn("asks", F.when(very, -1).otherwise(F.coalesce("flag", F.lit(0)))).drop("flag")
        live_keys = now.groupBy("key").agg(F.min("c").alias("lo"), F.max("c").alias("hi"), F.max(F.abs("asks")).alias("any")).where("lo < hi AND any = 1").select("key")
        # few keys are left: their sets are told apart by wider sketches, so what is no link is seldom asked for
        closer = small.select("reg", F.expr(f"IF(size(wide) <= {WORDS_SENT}, wide, narrow)").alias("narrow"))
        rare = materialize(now.drop("narrow").join(live_keys, "key", "left_semi").join(closer, "reg"), "rare-keys", rare)
        most, turn = most * MORE, turn + 1
    if hot:
        # what is left of keys of very many sets, by rows: of a key's sets those outside its largest
        # class meet all others, so a large class does not meet itself, and the bounds are in the join
        left = with_class(rare.where(very).select("key", "reg"))
        largest = left.groupBy("key", "c").agg(F.count(F.lit(1)).alias("m")).groupBy("key").agg(F.max(F.struct("m", "c"))["c"].alias("main"))
        full = left.select("key", "reg", "c").join(small, "reg")
        rest = full.join(largest, "key").where("c <> main")
        crossed = rest.alias("p").join(full.alias("q"), F.expr(f"p.key = q.key AND p.c <> q.c AND (q.c = p.main OR p.c < q.c) AND p.reg & q.reg & 1 = 0 AND {likely}"))
        pairs = materialize(crossed.select(F.least("p.reg", "q.reg").alias("ra"), F.greatest("p.reg", "q.reg").alias("rb")).distinct(), "met-pairs")
        good = similar(untested(pair(pairs).select("a", "b")).distinct())
        comp = grown(good)
        spent += [pairs, good]
    comp = comp.select(F.col("id").alias("set_a"), F.col("c").alias("component"))
    least = one.join(comp, "set_a").groupBy("component").agg(F.min("doc_id").alias("component_id"))
    named = comp.join(least, "component").select("set_a", "component_id")
    named = materialize(one.join(named, "set_a", "left").select("set_a", "set_b", F.coalesce("component_id", "doc_id").alias("component_id")), "classes")
    discard(need, packed, small, rare, *spent, *([tested] if tested is not None else []))
    return doc.join(named, ["set_a", "set_b"], "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))
