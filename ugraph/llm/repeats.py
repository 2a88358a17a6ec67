"""Repeated passages by a logarithmic family of sparse suffix arrays.

Every byte covered by a LENGTH-byte string that also starts elsewhere is removed. Suffixes are indexed where they can
matter: a string of LENGTH bytes holds LENGTH - GRAM + 1 grams, and all of the least digest are its anchors, in every
place where the string stands. Anchors whose gram stands once are dropped by a count. The rest are sorted by gram and by
the bytes before it, read backwards, and the sorted run is cut into shards of about SHARD_ROWS suffixes. In a shard,
batches arrive one after another: each gets a suffix array (its suffixes in order of the gram's digest and of the bytes
behind it), is merge-scanned against the existing levels for suffixes with the same gram, and joins the family, in
which levels of equal size class merge. The scan compares, for each start of a string around the anchor, the digests
of the whole strings; their first and last matches bound what is removed.

A cut can part the suffixes of a gram of over NARROW ones: of the first and the last gram of each shard. These are
sorted once more, by the bytes behind the anchor, and scanned in shards of that order. A suffix and one that it met in
neither order share no more bytes before the anchor than the suffix shares with an end of its first shard, and no more
behind it than with an end of its second. Strings within these bounds, few unless the ends are alike, are matched
between shards by counts of their digests, to which a shard adds each digest once.

Equal texts are one text here: those of at least LENGTH bytes with a copy go as wholes, and one of them stands for all.

Passages of PASSAGE words are often shorter than LENGTH bytes. They are found, and reported without being removed, by the
same steps over words in place of bytes (``Unit``): a text is then its words, each with a space behind it, a string is
PASSAGE of them, and places and spans count words.

Defined cases: null text is empty; rows of equal or null doc_id are documents of their own; texts shorter than LENGTH
keep all bytes; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import HEAVY, map_arrow, materialise, slices

LENGTH, GRAM = 400, 128
#: Words of a passage, and of its grams.
PASSAGE, WORD_GRAM = 51, 16
#: Suffixes of one shard, and batches in which they arrive.
SHARD_ROWS, BATCHES = 32768, 4
#: Grams of at most so many suffixes are never cut: their sort key is the gram alone. So only the others' keys are long,
#: which bounds the sample that the sort sends to the driver.
NARROW = 1024
BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(BASE, -1, 1 << 64)


@cache
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE and its inverse to the powers 0 to n, modulo 2**64."""
    up, down = (np.cumprod(np.concatenate((np.ones(1, np.uint64), np.full(n, b, np.uint64)))) for b in (BASE, _INVERSE))
    return up, down


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return (x ^ (x >> np.uint64(32))) * np.uint64(0xA24BAED4963EE407)


def string_digests(data: np.ndarray, length: int) -> np.ndarray:
    """A 64-bit digest of the ``length`` bytes from every position on."""
    n = len(data)
    if n < length:
        return np.empty(0, np.uint64)
    size = 1 << max(12, int(n).bit_length())
    up, down = _powers(size)
    total = np.concatenate((np.zeros(1, np.uint64), np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[:n])))
    return _mix((total[length:] - total[:-length]) * down[: n - length + 1])


@dataclass(frozen=True)
class Unit:
    """What a text is cut into: bytes, or words. A string has ``length`` units, a gram ``gram``."""

    words: bool
    length: int
    gram: int

    @property
    def span(self) -> int:
        return self.length - self.gram

    def form(self, data: bytes) -> bytes:
        """The text as it is compared."""
        return b" ".join([*data.split(), b""]) if self.words else data

    def bounds(self, form: bytes):
        """Where its units start, and its end."""
        if not self.words:
            return range(len(form) + 1)
        return [0, *(np.flatnonzero(np.frombuffer(form, np.uint8) == 32) + 1).tolist()]

    def values(self, form: bytes) -> np.ndarray:
        """A number for each unit."""
        data = np.frombuffer(form, np.uint8)
        if not self.words:
            return data
        if not len(data):
            return np.empty(0, np.uint64)
        starts = np.concatenate((np.zeros(1, np.int64), np.flatnonzero(data[:-1] == 32) + 1))
        up, down = _powers(1 << max(12, len(data).bit_length()))
        return _mix(np.add.reduceat((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], starts) * down[starts])

    def counts(self, forms: list[bytes]) -> np.ndarray:
        """Units of each form."""
        return np.array([x.count(b" ") if self.words else len(x) for x in forms], dtype=np.int64)


BYTES, WORDS = Unit(False, LENGTH, GRAM), Unit(True, PASSAGE, WORD_GRAM)


def _sliding(x: np.ndarray, width: int, take) -> np.ndarray:
    """``take`` (minimum or maximum) over every run of ``width`` values, by doubling."""
    done, out = 1, x
    while done * 2 <= width:
        out = take(out[:-done], out[done:])
        done *= 2
    rest = width - done
    return take(out[: len(out) - rest], out[rest:]) if rest else out


def anchors(data: np.ndarray, unit: Unit = BYTES) -> tuple[np.ndarray, np.ndarray]:
    """Positions and gram digests of the least grams of all strings of a text's units. Long texts go in blocks."""
    n, block, span = len(data), 1 << 22, unit.span
    if n < unit.length:
        return np.empty(0, np.int64), np.empty(0, np.uint64)
    found = []
    for a in range(0, n - unit.length + 1, block):
        h = string_digests(data[a : a + block + unit.length - 1], unit.gram)
        least = _sliding(h, span + 1, np.minimum)
        edge = np.zeros(span, np.uint64)
        chosen = _sliding(np.concatenate((edge, least, edge)), span + 1, np.maximum) == h
        at = np.flatnonzero(chosen)
        found.append((at + a, h[at]))
    pos, keys = (np.concatenate(x) for x in zip(*found, strict=True))
    pos, first = np.unique(pos, return_index=True)
    return pos, keys[first]


SIGNED = "doc_id long, text_hash long, n_bytes long, name binary, sha string, spots binary, grams binary"


def _sign(batches):
    for batch in batches:
        for part in slices(batch, "text"):
            rows = []
            for t in part.column("text").to_pylist():
                data = (t or "").encode()
                pos, keys = anchors(np.frombuffer(data, np.uint8))
                rows.append((len(data), hashlib.blake2b(data, digest_size=16).digest(), hashlib.sha256(data).hexdigest(), pos.astype("<i8").tobytes(), keys.tobytes()))
            kinds = (pa.int64(), pa.binary(), pa.string(), pa.binary(), pa.binary())
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("text_hash"), *(pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True))], names=[f.split()[0] for f in SIGNED.split(", ")])


def _sign_words(batches):
    """What ``_sign`` gives, with the anchors among words."""
    for batch in batches:
        for part in slices(batch, "text"):
            for signed in _sign([part]):
                rows = []
                for t in part.column("text").to_pylist():
                    values = WORDS.values(WORDS.form((t or "").encode()))
                    pos, keys = anchors(values, WORDS)
                    rows.append((len(values), pos.astype("<i8").tobytes(), keys.tobytes()))
                for name, column, kind in zip(("n_words", "word_spots", "word_grams"), zip(*rows, strict=True), (pa.int64(), pa.binary(), pa.binary()), strict=True):
                    signed = signed.append_column(name, pa.array(column, kind))
                yield signed


def _spread(batches):
    for batch in batches:
        spots = [np.frombuffer(x, "<i8") for x in batch.column("spots").to_pylist()]
        counts = np.array([len(x) for x in spots], dtype=np.int64)
        grams = b"".join(batch.column("grams").to_pylist())
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.asarray(batch.column("cid")), counts)), pa.array(np.concatenate([*spots, np.empty(0, np.int64)])), pa.array(np.frombuffer(grams, np.int64))], names=["cid", "pos", "gram"])


REGIONS = "gram long, held long, cid long, pos long, before int, size int, left binary, right binary"


def _regions(unit: Unit):
    """The units before every candidate anchor, backwards, and those from it on, as bytes. Where a text repeats itself (a
    periodic one does at each period), equal regions come once; that all their strings repeat is known already, and rows
    without bytes say so."""

    def run(batches):
        for batch in batches:
            for part in slices(batch, "text"):
                out = []
                for cid, text, spots in zip(*(part.column(c).to_pylist() for c in ("cid", "text", "spots")), strict=True):
                    data, seen = unit.form(text.encode()), {}
                    bounds = unit.bounds(data)
                    n = len(bounds) - 1
                    for s in spots:
                        p = s["pos"]
                        before, last = min(unit.span, p), min(p + unit.length, n)
                        a, at, size = bounds[p - before], bounds[p], last - p + before
                        region = data[a : bounds[last]]
                        known = seen.setdefault((before, region), p)
                        if known is None or known != p:
                            if known is not None:
                                out.append((s["gram"], s["c"], cid, known, before, size, None, None))
                                seen[before, region] = None
                            out.append((s["gram"], s["c"], cid, p, before, size, None, None))
                        else:
                            out.append((s["gram"], s["c"], cid, p, before, size, region[: at - a][::-1], region[at - a :]))
                        if len(out) >= 8192:
                            yield _rows(out, REGIONS)
                            out = []
                if out:
                    yield _rows(out, REGIONS)

    return run


_KINDS = {"long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}


def _rows(out: list[tuple], schema: str) -> pa.RecordBatch:
    fields = [f.split() for f in schema.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(c, _KINDS[k]) for c, (_, k) in zip(zip(*out, strict=True), fields, strict=True)], names=[n for n, _ in fields])


def _totals(regions: list[bytes], before: np.ndarray, unit: Unit) -> tuple[np.ndarray, np.ndarray]:
    """Running sums of the regions' weighted units, a row each, with all anchors in column ``unit.span``; units of each."""
    width = unit.span + unit.length
    values, sizes = unit.values(b"".join(regions)), unit.counts(regions)
    wide = np.zeros((len(regions), width), values.dtype)
    at = 0
    for i, (b, n) in enumerate(zip(before.tolist(), sizes.tolist(), strict=True)):
        wide[i, unit.span - b : unit.span - b + n] = values[at : at + n]
        at += n
    total = np.zeros((len(regions), width + 1), np.uint64)
    np.cumsum((wide.astype(np.uint64) + np.uint64(1)) * _powers(4096)[0][:width], axis=1, out=total[:, 1:])
    return total, sizes


def _placed(digests: np.ndarray, places: np.ndarray) -> np.ndarray:
    """Digests of strings together with their places before the anchor."""
    return _mix(digests ^ ((places.astype(np.uint64) + np.uint64(1)) * np.uint64(BASE))).view(np.int64)


class SuffixFamily:
    """Levels of sparse suffix arrays over one table of regions; ``first`` and ``last`` hold, for each suffix, the
    greatest and the least distance from a matching string's start to the anchor (-1: none, span + 1: none)."""

    #: Suffixes whose strings are held at once, besides a single gram's.
    HELD = 4096

    def __init__(self, grams: np.ndarray, before: np.ndarray, regions: pa.Array, unit: Unit = BYTES):
        n = len(grams)
        self.grams, self.before, self.regions, self.levels, self.unit = grams, before, regions, [], unit
        self.first, self.last = np.full(n, -1, np.int64), np.full(n, unit.span + 1, np.int64)
        behind = []
        for a in range(0, n, self.HELD):
            part = zip(regions.slice(a, self.HELD).to_pylist(), before[a : a + self.HELD].tolist(), strict=True)
            rest = ((r.split(b" ", b + unit.gram)[-1] if unit.words else r[b + unit.gram :]) for r, b in part)
            behind += [int.from_bytes(r[:8].ljust(8, b"\0"), "big") for r in rest]
        self.behind = np.array(behind, dtype=np.uint64)

    def _strings(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Digests of the strings that start span to 0 units before the anchors, and which of them are whole."""
        span, length = self.unit.span, self.unit.length
        strings, real = np.zeros((len(rows), span + 1), np.uint64), np.zeros((len(rows), span + 1), bool)
        down = _powers(4096)[1]
        distance = span - np.arange(span + 1)
        for a in range(0, len(rows), 1024):
            some = rows[a : a + 1024]
            before = self.before[some]
            total, sizes = _totals(self.regions.take(pa.array(some)).to_pylist(), before, self.unit)
            strings[a : a + 1024] = _mix((total[:, length:] - total[:, :-length]) * down[: span + 1])
            real[a : a + 1024] = (distance <= before[:, None]) & (length - distance <= (sizes - before)[:, None])
        return strings, real

    def _sorted(self, rows: np.ndarray) -> np.ndarray:
        return rows[np.lexsort((self.behind[rows], self.grams[rows]))]

    def _match(self, rows: np.ndarray) -> None:
        """Equal strings at equal places among ``rows``, a run of whole grams at a time."""
        rows = self._sorted(rows)
        starts = np.flatnonzero(np.concatenate(([True], self.grams[rows][1:] != self.grams[rows][:-1]))).tolist() + [len(rows)]
        a = 0
        for i, b in enumerate(starts[1:], 1):
            if b == len(rows) or starts[i + 1] - a > self.HELD:
                self._match_run(rows[a:b])
                a = b

    def _match_run(self, rows: np.ndarray) -> None:
        strings, real = self._strings(rows)
        span = self.unit.span
        for k in range(span + 1):
            some = np.flatnonzero(real[:, k])
            if len(some) < 2:
                continue
            x = strings[some, k]
            order = np.argsort(x)
            same = x[order][1:] == x[order][:-1]
            if same.any():
                hit = rows[some[order[np.concatenate((same, [False])) | np.concatenate(([False], same))]]]
                self.first[hit] = np.maximum(self.first[hit], span - k)
                self.last[hit] = np.minimum(self.last[hit], span - k)

    def add(self, rows: np.ndarray) -> None:
        """A new batch: its own suffix array, a merge-scan against every level, and the geometric merges."""
        new = self._sorted(rows)
        keys = self.grams[new]
        inner = np.isin(keys, keys[1:][keys[1:] == keys[:-1]])
        if inner.any():
            self._match(new[inner])
        for level in self.levels:
            old = self.grams[level]
            a = new[np.isin(keys, old)]
            b = level[np.isin(old, keys)]
            if len(a):
                self._match(np.concatenate((a, b)))
        self.levels.append(new)
        while len(self.levels) > 1 and len(self.levels[-2]).bit_length() <= len(self.levels[-1]).bit_length():
            right = self.levels.pop()
            self.levels[-1] = self._sorted(np.concatenate((self.levels[-1], right)))


class Shard:
    """The suffixes of a shard's rows: ``first`` and ``last`` as in their family, which holds equal regions once. Those
    match one another in all their whole strings, which needs no scan."""

    def __init__(self, table: pa.Table, unit: Unit):
        grams, cid, pos = (np.asarray(table.column(c)) for c in ("gram", "cid", "pos"))
        left, right = (table.column(c).to_pylist() for c in ("left", "right"))
        regions, before = [x[::-1] + y for x, y in zip(left, right, strict=True)], unit.counts(left)
        del left, right
        seen: dict[tuple[int, bytes], int] = {}
        each = np.array([seen.setdefault(x, i) for i, x in enumerate(zip(before.tolist(), regions, strict=True))])
        one, self.where, copies = np.unique(each, return_inverse=True, return_counts=True)
        self.family = family = SuffixFamily(grams[one], before[one], pa.array([regions[i] for i in one.tolist()], pa.binary()), unit)
        order = np.lexsort((pos[one], cid[one]))
        for batch in np.array_split(order, min(BATCHES, len(order))):
            family.add(batch)
        most = np.minimum(before[one], unit.span)
        least = np.maximum(unit.length - unit.counts([regions[i] for i in one.tolist()]) + before[one], 0)
        twins = (copies > 1) & (least <= most)
        self.first = np.where(twins, most, family.first)[self.where]
        self.last = np.where(twins, least, family.last)[self.where]


def _common(texts: list[bytes], other: bytes) -> np.ndarray:
    """Bytes that each of ``texts`` shares with the start of ``other``."""
    found = np.zeros(len(texts), np.int64)
    width = len(other)
    for a in range(0, len(texts) if width else 0, 4096):
        some = texts[a : a + 4096]
        wide = np.frombuffer(b"".join(x[:width].ljust(width, b"\0") for x in some), np.uint8).reshape(len(some), width)
        apart = wide != np.frombuffer(other, np.uint8)
        lcp = np.where(apart.any(axis=1), apart.argmax(axis=1), width)
        found[a : a + 4096] = np.minimum(lcp, [len(x) for x in some])
    return found


def _limits(table: pa.Table, order: str, unit: Unit, skip: int = 0, narrow: int = 0) -> np.ndarray:
    """For each suffix of a shard of the run sorted by gram and, in grams of over ``narrow`` suffixes, by ``order``: how
    many units of ``order``, after the first ``skip``, it can share at most with a suffix of its gram in another shard;
    -1 if its gram lies in this one alone, as narrow grams do."""
    grams, held = np.asarray(table.column("gram")), np.asarray(table.column("held"))
    limit = np.full(len(grams), -1, np.int64)
    for gram, end in ((grams.min(), min), (grams.max(), max)):
        rows = np.flatnonzero(grams == gram)
        if held[rows[0]] <= narrow:
            continue
        some = table.column(order).take(pa.array(rows)).to_pylist()
        other = end(some)
        shared = _common(some, other)
        if unit.words:  # each has a space behind it; backwards, before it
            shared = np.concatenate(([0], np.cumsum(np.frombuffer(other, np.uint8) == 32)))[shared]
        limit[rows] = np.maximum(limit[rows], np.clip(shared - skip, 0, unit.span))
    return limit


SCANNED = "gram long, held long, cid long, pos long, left binary, right binary, first int, last int, most int, a long, b long"


def _scan(narrow: int, unit: Unit):
    """A shard in order of what stands before the anchor: the spans found here, and the suffixes whose gram lies in other
    shards too, with what they matched here and the most units that one of another shard can share before the anchor."""

    def run(batches):
        batches = list(batches)
        if not sum(map(len, batches)):
            return
        table = pa.Table.from_batches(batches).combine_chunks()
        shard, most = Shard(table, unit), _limits(table, "left", unit, narrow=narrow)
        cid, pos = np.asarray(table.column("cid")), np.asarray(table.column("pos"))
        hit, parted = np.flatnonzero(shard.first >= 0), np.flatnonzero(most >= 0)
        names = [f.split() for f in SCANNED.split(", ")]
        whole = {"cid": cid[hit], "a": pos[hit] - shard.first[hit], "b": pos[hit] - shard.last[hit] + unit.length}
        yield pa.RecordBatch.from_arrays([pa.array(whole[n], _KINDS[k]) if n in whole else pa.nulls(len(hit), _KINDS[k]) for n, k in names], names=[n for n, _ in names])
        for at in range(0, len(parted), 4096):
            rows = parted[at : at + 4096]
            some = table.select(["gram", "held", "cid", "pos", "left", "right"]).take(pa.array(rows)).combine_chunks()
            more = [pa.array(x[rows], pa.int32()) for x in (shard.first, shard.last, most)]
            columns = [some.column(i).chunk(0) for i in range(6)]
            yield pa.RecordBatch.from_arrays([*columns, *more, *[pa.nulls(len(rows), pa.int64())] * 2], names=[n for n, _ in names])

    return run


STRINGS = "cid long, pos long, a long, b long, key long"


def _scan_again(unit: Unit):
    """A shard in order of what stands behind the anchor: the spans of suffixes that matched more here than in the other
    order (no key), the strings without a match here that could add to them (all columns) and once each of the other
    strings (key alone); of strings, those that a suffix met in neither order can share."""

    def run(batches):
        batches = list(batches)
        if not sum(map(len, batches)):
            return
        table = pa.Table.from_batches(batches).combine_chunks()
        shard, behind, span = Shard(table, unit), _limits(table, "right", unit, unit.gram), unit.span
        cid, pos, first, last, most = (np.asarray(table.column(c)) for c in ("cid", "pos", "first", "last", "most"))
        hit = np.flatnonzero((shard.first > first) | (shard.last < last))
        first, last = np.maximum(shard.first, first), np.minimum(shard.last, last)
        rows, keys = [np.empty((2, 0), np.int64)], [np.empty(0, np.int64)]
        distance = span - np.arange(span + 1)
        wide = np.flatnonzero((behind >= 0) & (span - behind <= most))
        for at in range(0, len(wide), SuffixFamily.HELD):
            some = wide[at : at + SuffixFamily.HELD]
            strings, real = shard.family._strings(shard.where[some])
            i, k = np.nonzero(real & (distance <= most[some][:, None]) & (distance >= span - behind[some][:, None]))
            rows.append(np.stack((some[i], distance[k])))
            keys.append(_placed(strings[i, k], k))
        rows, keys = np.concatenate(rows, axis=1), np.concatenate(keys)
        alone, again = _alone(keys)
        # a match between the first and the last adds no byte: such strings are only there for others to match
        outside = (rows[1] > first[rows[0]]) | (rows[1] < last[rows[0]])
        again = np.concatenate((again, keys[alone & ~outside]))
        (one, d), keys = rows[:, alone & outside], keys[alone & outside]
        columns = (
            [cid[hit], pos[hit], pos[hit] - first[hit], pos[hit] - last[hit] + unit.length, None],
            [cid[one], pos[one], pos[one] - d, pos[one] - d + unit.length, keys],
            [None, None, None, None, again],
        )
        for some, n in zip(columns, (len(hit), len(one), len(again)), strict=True):
            yield pa.RecordBatch.from_arrays([pa.nulls(n, pa.int64()) if c is None else pa.array(c, pa.int64()) for c in some], names=[f.split()[0] for f in STRINGS.split(", ")])

    return run


def _alone(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which keys stand once, and the others once each."""
    each, back, n = np.unique(keys, return_inverse=True, return_counts=True)
    return n[back] == 1, each[n > 1]


def among_repeated(rows: DataFrame, key: str, tag: str, least: int = 2) -> DataFrame:
    """The rows whose key stands in ``least`` or more, with its count ``c``. Heavy keys, fewer than HEAVY, go by broadcast, so
    that no key brings more than that part of the rows into one task."""
    counts = materialise(rows.groupBy(key).agg(F.count(F.lit(1)).alias("c")).filter(F.col("c") >= least), tag)
    share = (counts.agg(F.sum("c")).first()[0] or 0) // HEAVY
    heavy = counts.filter(F.col("c") > share)
    if heavy.isEmpty():
        return rows.join(counts, key)
    few = F.broadcast(heavy)
    return rows.join(few, key).unionByName(rows.join(few.select(key), key, "left_anti").join(counts.filter(F.col("c") <= share), key))


def matched_spans(regions: DataFrame, shard_rows: int = SHARD_ROWS, narrow: int = NARROW, unit: Unit = BYTES) -> DataFrame:
    """cid, a, b: the spans around the suffixes of ``regions``, shard by shard in two orders, then across shards."""
    shards = -(-regions.count() // shard_rows)
    wide = F.col("held") > narrow
    sorted_ = regions.repartitionByRange(max(1, shards), "gram", *[F.when(wide, F.col(c)) for c in ("left", "cid", "pos")])
    scanned = materialise(map_arrow(sorted_, _scan(narrow, unit), SCANNED), "repeat-scan")
    parted = scanned.filter("gram is not null").drop("a", "b")
    shards = -(-parted.count() // shard_rows)
    again = map_arrow(parted.repartitionByRange(max(1, shards), "gram", "right", "cid", "pos"), _scan_again(unit), STRINGS)
    again = materialise(again, "repeat-scan-again")
    across = among_repeated(again.filter("key is not null"), "key", "repeat-strings").filter("cid is not null")
    found = again.filter("key is null").drop("key").unionByName(across.select("cid", "pos", "a", "b"))
    return scanned.filter("gram is null").select("cid", "a", "b").unionByName(found.select("cid", "a", "b"))


def merged_spans(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Spans in order, with those that touch or overlap joined."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


KEPT = "cid long, n_removed long, n_spans long, kept_sha256 string, spans array<struct<a:long,b:long>>"


def _cut(batches):
    kind = pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())]))
    for batch in batches:
        for part in slices(batch, "text"):
            rows = []
            for cid, text, found in zip(*(part.column(c).to_pylist() for c in ("cid", "text", "found")), strict=True):
                data = text.encode()
                spans = merged_spans([(s["a"], s["b"]) for s in found])
                keep, at = hashlib.sha256(), 0
                for a, b in spans:
                    keep.update(data[at:a])
                    at = b
                keep.update(data[at:])
                rows.append((cid, sum(b - a for a, b in spans), len(spans), keep.hexdigest(), [{"a": a, "b": b} for a, b in spans]))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.string(), kind), strict=True)], names=["cid", "n_removed", "n_spans", "kept_sha256", "spans"])


COVERED = "cid long, n_passage_words long, passages array<struct<a:long,b:long>>"


def _covered(batches):
    """The words that the found spans of words cover, and the spans joined."""
    kind = pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())]))
    for batch in batches:
        spans = [merged_spans([(s["a"], s["b"]) for s in found]) for found in batch.column("found").to_pylist()]
        columns = pa.array([sum(b - a for a, b in x) for x in spans], pa.int64()), pa.array([[{"a": a, "b": b} for a, b in x] for x in spans], kind)
        yield pa.RecordBatch.from_arrays([batch.column("cid"), *columns], names=["cid", "n_passage_words", "passages"])


def document_rows(docs: DataFrame) -> DataFrame:
    """doc_id, text (never null) and text_hash of every row."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).withColumn("text_hash", F.xxhash64("text"))


def spots_by_text(spots: DataFrame) -> DataFrame:
    """cid and its ``spots``, from a row for each of them (cid, pos, gram, count c of the gram)."""
    return spots.groupBy("cid").agg(F.collect_list(F.struct("pos", "gram", "c")).alias("spots"))


def spans_of(held: DataFrame, shard_rows: int = SHARD_ROWS, narrow: int = NARROW, unit: Unit = BYTES) -> DataFrame:
    """cid, a, b: the spans of ``held`` (cid, text, spots)."""
    regions = materialise(map_arrow(held, _regions(unit), REGIONS), "repeat-regions")
    found = matched_spans(regions.filter("left is not null").drop("before", "size"), shard_rows, narrow, unit)
    inside = regions.filter("left is null").select("cid", (F.col("pos") - F.col("before")).alias("a"), (F.col("pos") - F.col("before") + F.col("size")).alias("b"))
    return found.unionByName(inside)


def result_rows(members: DataFrame, named: DataFrame, *more) -> DataFrame:
    """What is removed of every document: ``members`` has its name, ``named`` for each name the copies and what was cut."""
    out = members.join(named, "name")
    whole = (F.col("copies") > 1) & (F.col("n_bytes") >= LENGTH)
    nothing = hashlib.sha256(b"").hexdigest()
    return out.select(
        "doc_id",
        "n_bytes",
        F.when(whole, F.col("n_bytes")).otherwise(F.coalesce("n_removed", F.lit(0))).alias("n_removed"),
        F.when(whole, F.lit(1)).otherwise(F.coalesce("n_spans", F.lit(0))).cast("long").alias("n_spans"),
        F.when(whole, F.lit(nothing)).otherwise(F.coalesce("kept_sha256", "sha")).alias("kept_sha256"),
        F.when(whole, F.array(F.struct(F.lit(0).cast("long").alias("a"), F.col("n_bytes").alias("b")))).otherwise(F.col("spans")).alias("spans"),
        *more,
    )


def _candidates(texts: DataFrame, spots: str, grams: str, tag: str) -> DataFrame:
    """cid and the anchors whose gram stands in two places or more, by text."""
    each = map_arrow(texts.select("cid", F.col(spots).alias("spots"), F.col(grams).alias("grams")), _spread, "cid long, pos long, gram long")
    return spots_by_text(materialise(among_repeated(each, "gram", f"{tag}-grams"), f"{tag}-spots")).withColumnRenamed("spots", spots)


def repeated_spans(docs: DataFrame, shard_rows: int = SHARD_ROWS, narrow: int = NARROW) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and the removed byte ``spans`` of every document; then
    n_passage_words, the words covered by a string of PASSAGE words that also starts elsewhere, same document included, and
    their ``passages``, spans of words. Of these, only what is in ``spans`` too is removed."""
    texts = document_rows(docs)
    schema = f"{SIGNED}, n_words long, word_spots binary, word_grams binary"
    signed = materialise(map_arrow(texts.select("doc_id", "text_hash", "text"), _sign_words, schema).withColumn("rid", F.monotonically_increasing_id()), "repeat-signed")
    classes = materialise(signed.groupBy("name").agg(F.min("rid").alias("cid"), F.count(F.lit(1)).alias("copies")), "repeat-classes")
    long_ = signed.filter(f"n_bytes >= {LENGTH} or n_words >= {PASSAGE}").drop("name").join(classes.select(F.col("cid").alias("rid")), "rid", "left_semi").withColumnRenamed("rid", "cid")
    spots = _candidates(long_, "spots", "grams", "repeat").join(_candidates(long_, "word_spots", "word_grams", "repeat-word"), "cid", "full")
    key = F.coalesce("doc_id", F.lit(-(1 << 63))).alias("k")
    wanted = long_.select("cid", key, "text_hash").join(spots, "cid")
    held = materialise(texts.select(key, "text_hash", "text").join(wanted, ["k", "text_hash"]).dropDuplicates(["cid"]).select("cid", "text", "spots", "word_spots"), "repeat-texts")
    found, passages = (
        materialise(spans_of(held.filter(F.col(c).isNotNull()).select("cid", "text", F.col(c).alias("spots")), shard_rows, narrow, unit).groupBy("cid").agg(F.collect_list(F.struct("a", "b")).alias("found")), f"repeat-found-{c}")
        for c, unit in (("spots", BYTES), ("word_spots", WORDS))
    )
    cut = materialise(map_arrow(held.select("cid", "text").join(found, "cid"), _cut, KEPT), "repeat-cut")
    covered = map_arrow(passages, _covered, COVERED)
    named = materialise(classes.join(cut, "cid", "left").join(covered, "cid", "left").drop("cid"), "repeat-named")
    whole = (F.col("copies") > 1) & (F.col("n_words") >= PASSAGE)
    words = F.when(whole, F.col("n_words")).otherwise(F.coalesce("n_passage_words", F.lit(0))).alias("n_passage_words")
    at = F.when(whole, F.array(F.struct(F.lit(0).cast("long").alias("a"), F.col("n_words").alias("b")))).otherwise(F.col("passages")).alias("passages")
    return result_rows(signed.select("doc_id", "n_bytes", "n_words", "sha", "name"), named, words, at)


def repeats_digest(docs: DataFrame) -> DataFrame:
    """op9: the contract's columns, and n_passage_words."""
    return repeated_spans(docs).drop("spans", "passages")
