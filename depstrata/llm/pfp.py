"""Exact removal of repeated passages by prefix-free parsing.

Every window of `length` bytes has one trigger: the leftmost place in it whose rolling hash is smallest.  Windows that follow each other
with one trigger make a phrase, so a document is a sequence of phrases that overlap by length - 1 bytes, and every window lies in just one.
The choice depends on the window's own bytes alone: equal windows have equal triggers at equal offsets, wherever they are.

The dictionary holds the distinct phrases; the parse says where each stands.  A phrase whose trigger stands nowhere else has no repeated window
and drops out at once.  Of the occurrences of one phrase the first in corpus order stays and the others are repeats as a whole, so
long copies cost one row for each phrase.

Different phrases can share windows as well.  Equal windows reach past their trigger on the same side, so their phrases agree in the 32 bytes of the
trigger and the 32 next to it; the dictionary is dealt by these 64 bytes, and each share of it gets its suffix array: the suffixes of its
phrases in the order of their bytes, with the places of the parse in corpus order where bytes are equal.  Neighbours with a common prefix of `length` bytes are
one window, of which the first place stays.  As phrases overlap, no window goes on into the next phrase, and order among phrases (the suffix array
of the parse) is needed for first places only, which is a minimum.

A share of more than max_share phrases, so a trigger that very many different phrases have, is not sorted in one task: its suffixes become rows,
counted by a hash of 128 bits with partial sums.  Both ways find the same.

Edge cases: NULL and empty texts have 0 bytes; rows with a NULL doc_id are left as they are and make no other row a repeat; rows with one doc_id and one text count as
one document, those with different texts as documents of their own in the order of a hash of their texts; texts shorter than length have no window; an empty table
gives an empty result; other columns are ignored; lengths from 64 to 150 bytes are possible.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from depstrata.llm.common import discard, release, staged

_U = np.uint64
_GRAM, _HALF = 32, 64
_BYTE = np.random.default_rng(5).integers(0, 2**63, 256, dtype=np.int64).astype(np.uint64) * _U(2) + _U(1)
_STEP = [_U(c) for c in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB)]
_HIGH = _U(0xFFFFFFFF00000000)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(32))) * _U(0xD6E8FEB86659FD93)
    return x ^ (x >> _U(32))


def _hashes(b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the 32 and of the 64 bytes from each place."""
    h, short = _BYTE[b], None
    for i, c in enumerate(_STEP):
        m = 1 << i
        h = h[: len(h) - m] * c + h[m:] if len(h) > m else h[:0]
        if 2 * m == _GRAM:
            short = h
    return short, h


class Parse:
    """Phrases of a run of documents: number of the document, start in it, windows, trigger hash, phrase hash."""

    def __init__(self, texts: list[bytes], length: int, content: bool = True):
        size = np.array([len(t) for t in texts], np.int64)
        end = np.cumsum(size)
        b = np.frombuffer(b"".join(texts), np.uint8)
        self.doc = self.start = self.count = np.zeros(0, np.int64)
        self.off = np.zeros(0, np.int64)  # from the phrase's start to its trigger
        self.trigger = self.phrase = self.left = self.right = np.zeros(0, np.uint64)
        self.has_left = self.has_right = np.zeros(0, bool)
        if len(b) < length:
            return
        short, long_ = _hashes(b)
        key = _mix(short) & _HIGH | np.arange(len(short), dtype=np.uint64)
        width = length - _GRAM + 1
        low, span = key, 1
        while 2 * span <= width:
            low = np.minimum(low[:-span], low[span:])
            span *= 2
        if span < width:
            low = np.minimum(low[: len(low) - (width - span)], low[width - span :])
        at = (low & ~_HIGH).astype(np.int64)  # trigger of the window from each place
        doc = np.repeat(np.arange(len(texts)), size)[: len(at)]
        fits = np.arange(len(at)) + length <= end[doc]
        new = np.r_[True, (at[1:] != at[:-1]) | (doc[1:] != doc[:-1])]
        first = np.nonzero(new & fits)[0]
        # A phrase ends where the next begins, or with the last window of its document.
        begin = np.nonzero(new)[0]
        stop = np.r_[begin[1:], len(at)][np.searchsorted(begin, first)]
        self.doc = doc[first]
        self.count = np.minimum(stop, end[self.doc] - length + 1) - first
        self.start = first - (end - size)[self.doc]
        self.trigger = short[at[first]]
        self.off = at[first] - first
        if content:
            last = first + self.count + length - 1 - _HALF
            middle = np.minimum(first + _HALF, last)
            self.phrase = _mix(_mix(_mix(long_[first]) + long_[middle]) + long_[last]) + self.count.astype(np.uint64)
            # A window reaches 34 bytes or more to one side of its trigger: the gram on that side, where a window of the phrase has it.
            side = (length - _GRAM + 1) // 2
            a = at[first]
            self.has_left, self.has_right = a - first >= side, last + _HALF - a - _GRAM >= side
            self.left = short[np.where(self.has_left, a - _GRAM, a)]
            self.right = short[np.where(self.has_right, a + _GRAM, a)]


def _bytes(text: str | None) -> bytes:
    return (text or "").encode("utf-8", "surrogatepass")


def _parses(batch: pa.RecordBatch, length: int, content: bool) -> Iterator[tuple[np.ndarray, Parse]]:
    for at in range(0, batch.num_rows, 256):
        part = batch.slice(at, 256)
        yield part.column(0).to_numpy(zero_copy_only=False), Parse([_bytes(t) for t in part.column(1).to_pylist()], length, content)


def _i64(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64) if x.dtype == np.uint64 else x.astype(np.int64))


def triggers(docs: DataFrame, length: int) -> DataFrame:
    """h: the trigger of each phrase."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, p in _parses(batch, length, False):
                yield pa.RecordBatch.from_arrays([_i64(p.trigger)], names=["h"])

    return docs.mapInArrow(run, "h long")


def slots(repeated: DataFrame, bits: int) -> np.ndarray:
    """A bitmap of fixed size of the hashes: what is not in it is not repeated."""
    slot = F.shiftrightunsigned("h", 64 - bits)
    word = repeated.groupBy(F.shiftright(slot, 6).alias("w")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), (slot % 64).cast("int"))).alias("m"))
    got = word.toArrow()
    out = np.zeros(1 << (bits - 6), np.int64)
    out[got.column("w").to_numpy()] = got.column("m").to_numpy()
    return out.view(np.uint64)


def _in(seen: np.ndarray, bits: int, h: np.ndarray) -> np.ndarray:
    slot = h >> _U(64 - bits)
    return (seen[(slot >> _U(6)).astype(np.int64)] >> (slot & _U(63))) & _U(1) == 1


def phrases(docs: DataFrame, length: int, seen: np.ndarray, bits: int) -> DataFrame:
    """h, ph, doc, place (start, windows and offset of the trigger, packed), lh, rh (hashes beside the trigger) of the phrases whose trigger the bitmap has."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for ids, p in _parses(batch, length, True):
                keep = _in(seen, bits, p.trigger)
                sides = [pa.array(x[keep].view(np.int64), mask=~m[keep]) for x, m in ((p.left, p.has_left), (p.right, p.has_right))]
                arrays = [_i64(p.trigger[keep]), _i64(p.phrase[keep]), _i64(ids[p.doc[keep]]), _i64((p.start << 16 | p.count << 8 | p.off)[keep]), *sides]
                yield pa.RecordBatch.from_arrays(arrays, names=["h", "ph", "doc", "place", "lh", "rh"])

    return docs.mapInArrow(run, "h long, ph long, doc long, place long, lh long, rh long")


def _gathered(parts: Iterator[tuple[np.ndarray, ...]], rows: int = 100_000) -> Iterator[tuple[np.ndarray, ...]]:
    """The same rows in fewer, larger parts."""
    held: list[tuple[np.ndarray, ...]] = []
    for part in parts:
        held.append(part)
        if sum(len(p[0]) for p in held[-64:]) >= rows or len(held) >= 1024:
            yield tuple(map(np.concatenate, zip(*held)))
            held = []
    if held:
        yield tuple(map(np.concatenate, zip(*held)))


class SuffixArray:
    """The suffixes of some phrases, of those that have a window left, in the order of their first `length` bytes, equal ones in corpus order.

    Suffixes whose window stands once among them are left out before sorting: pieces must be all phrases of their shares.
    """

    def __init__(self, pieces: list[bytes], doc: np.ndarray, at: np.ndarray, length: int):
        by = np.lexsort([at, doc])
        if len(by):
            # A repeated row of one document brings its phrases once more.
            by = by[np.r_[True, (doc[by][1:] != doc[by][:-1]) | (at[by][1:] != at[by][:-1])]]
        pieces, doc, at = [pieces[i] for i in by], doc[by], at[by]
        size = np.array([len(p) for p in pieces], np.int64)
        b = np.frombuffer(b"".join(pieces), np.uint8)
        n = np.maximum(size - length + 1, 0)
        piece = np.repeat(np.arange(len(n)), n)
        inner = np.arange(len(piece)) - np.repeat(np.cumsum(n) - n, n)
        where = (np.cumsum(size) - size)[piece] + inner
        if len(where):
            h = _hashes(b)[1]
            h = _mix(h[where]) + h[where + length - _HALF]
            order = np.argsort(h)
            same = h[order][1:] == h[order][:-1]
            again = np.zeros(len(h), bool)
            again[order[1:][same]] = again[order[:-1][same]] = True
            piece, inner, where = piece[again], inner[again], where[again]
        self.doc, self.at = doc[piece], at[piece] + inner
        rows = np.lib.stride_tricks.sliding_window_view(b, length)[where] if len(where) else np.zeros((0, length), np.uint8)
        self.order = np.argsort(rows.view(f"S{length}").ravel(), kind="stable")
        rows = rows[self.order]
        self.same = np.r_[False, (rows[1:] == rows[:-1]).all(1)] if len(rows) else np.zeros(0, bool)  # common prefix with the suffix before: all

    def repeats(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """doc, start and number of windows of the runs of suffixes that have an equal one before them."""
        later = np.sort(self.order[self.same])
        doc, at = self.doc[later], self.at[later]
        by = np.lexsort([at, doc])
        doc, at = doc[by], at[by]
        new = np.r_[True, (doc[1:] != doc[:-1]) | (at[1:] - at[:-1] > 1)] if len(at) else np.zeros(0, bool)
        start = np.nonzero(new)[0]
        return doc[start], at[start], (at[np.r_[start[1:], len(at)] - 1] - at[start] + 1) if len(at) else at


def _pieces(text: bytes, place: int, sides: int, length: int) -> Iterator[tuple[int, int, bytes]]:
    """(share, start, bytes) of the windows of a phrase that reach far to the left of its trigger, and of the others."""
    start, n, off = place >> 16, place >> 8 & 255, place & 255
    side = (length - _GRAM + 1) // 2
    left = min(n, off - side + 1)  # windows with a whole gram and more left of the trigger
    share = lambda b, which: int.from_bytes(hashlib.blake2b(b, digest_size=8, person=which).digest(), "little", signed=True)
    at = start + off
    if sides & 1 and left > 0:
        yield share(text[at - _GRAM : at + _GRAM], b"left"), start, text[start : start + left + length - 1]
    right = max(left, 0)
    if sides & 2 and right < n:
        yield share(text[at : at + 2 * _GRAM], b"right"), start + right, text[start + right : start + n + length - 1]


def sorted_shares(docs: DataFrame, wanted: DataFrame, length: int, rows: int = 400_000) -> DataFrame:
    """doc, run: repeats among the phrases wanted (doc, place, sides), by the suffix arrays of the dictionary's shares."""
    lists = wanted.groupBy("doc").agg(F.collect_list(F.struct("place", "sides")).alias("places"))
    both = docs.join(lists, F.col("doc_id") == F.col("doc")).select("doc", "text", "places")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 64):
                out: list[tuple] = []
                for doc, text, places in zip(*(batch.column(i).slice(lo, 64) for i in range(3))):
                    b, doc = _bytes(text.as_py()), doc.as_py()
                    flat = places.values
                    for place, sides in zip(flat.field("place").to_pylist(), flat.field("sides").to_pylist()):
                        out += [(k, doc, at, piece) for k, at, piece in _pieces(b, place, sides, length)]
                if out:
                    types = (pa.int64(), pa.int64(), pa.int64(), pa.binary())
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], names=["share", "doc", "at", "piece"])

    dealt = both.mapInArrow(cut, "share long, doc long, at long, piece binary").repartition("share").sortWithinPartitions("share")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        size = 0

        def found(t: pa.Table) -> pa.RecordBatch:
            sa = SuffixArray(t.column("piece").to_pylist(), t.column("doc").to_numpy(), t.column("at").to_numpy(), length)
            doc, at, n = sa.repeats()
            return pa.RecordBatch.from_arrays([_i64(doc), _i64(at * _RUN + n + (length - 1))], names=["doc", "run"])

        for batch in batches:
            for lo in range(0, batch.num_rows, 2048):
                part = batch.slice(lo, 2048)
                held.append(part)
                size += part.column(3).nbytes
                if size >= rows * 4:
                    # The last share may go on in the next batch.
                    t = pa.Table.from_batches(held)
                    share = t.column("share").to_numpy()
                    end = int(np.nonzero(share == share[-1])[0][0])
                    if end:
                        yield found(t.slice(0, end))
                        held = t.slice(end).to_batches()
                        size = sum(x.column(3).nbytes for x in held)
        if held:
            yield found(pa.Table.from_batches(held))

    return dealt.mapInArrow(run, "doc long, run long")


def suffixes(docs: DataFrame, wanted: DataFrame, length: int, bits: int) -> DataFrame:
    """w1, w2 (hash of the window), doc, at: windows of the phrases wanted (doc, place) that may stand elsewhere too."""
    lists = wanted.groupBy("doc").agg(F.collect_list("place").alias("places"))
    both = staged(docs.join(lists, F.col("doc_id") == F.col("doc")).select("doc", "text", "places"), "phrase-texts")

    def windows(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, ...]]:
        for batch in batches:
            for doc, text, places in zip(*(batch.column(i) for i in range(3))):
                h = _hashes(np.frombuffer(_bytes(text.as_py()), np.uint8))[1]
                place = np.array(places.as_py(), np.int64)
                n = place >> 8 & 255
                at = np.repeat(place >> 16, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                yield np.full(len(at), doc.as_py(), np.int64), at, h[at], h[at + length - _HALF]

    def short(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, _, a, b in _gathered(windows(batches)):
            yield pa.RecordBatch.from_arrays([_i64(_mix(a) + b)], names=["h"])

    again = staged(both.mapInArrow(short, "h long").groupBy("h").count().where("count > 1").select("h"), "windows")
    seen = slots(again, bits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for doc, at, a, b in _gathered(windows(batches)):
            keep = _in(seen, bits, _mix(a) + b)
            yield pa.RecordBatch.from_arrays([_i64(x[keep]) for x in (a, b, doc, at)], names=["w1", "w2", "doc", "at"])

    out = staged(both.mapInArrow(run, "w1 long, w2 long, doc long, at long"), "suffixes")
    discard(both, again)
    return out


#: A run of bytes as one number: start times this, plus length.
_RUN = 1024


def repeats(docs: DataFrame, length: int = 100, bits: int = 26, max_share: int = 2_000) -> DataFrame:
    """doc, run: runs of bytes that repeat an earlier window; they may overlap."""
    if not _HALF <= length <= 150:
        raise ValueError("a length from 64 to 150 bytes is possible")
    docs = docs.where("doc_id is not null")
    again = staged(triggers(docs, length).groupBy("h").count().where("count > 1").select("h"), "triggers")
    release(docs.sparkSession)
    found = phrases(docs, length, slots(again, bits), bits)
    found = staged(found.join(again, "h", "left_semi"), "phrases")
    discard(again)
    release(docs.sparkSession)
    # The dictionary: first place of each phrase, and how often it stands.
    book = found.groupBy("h", "ph").agg(F.min(F.struct("doc", "place")).alias("first"), F.count("*").alias("n"), F.first("lh").alias("lh"), F.first("rh").alias("rh"))
    book = staged(book.select("h", "ph", "first.doc", "first.place", "n", "lh", "rh"), "dictionary")
    later = found.join(book.where("n > 1").select("h", "ph", F.col("doc").alias("d0"), F.col("place").alias("p0")), ["h", "ph"]).where("doc <> d0 or place <> p0")
    windows = F.shiftright("place", 8).bitwiseAND(255)
    whole = staged(later.select("doc", (F.shiftright("place", 16) * _RUN + windows + (length - 1)).alias("run")), "copies")
    # Different phrases of one trigger can share a window only if they agree beside the trigger too.
    side = lambda c, bit: F.struct(F.col(c).alias("x"), F.lit(bit).alias("side"))
    both = book.select("h", "doc", "place", F.explode(F.array(side("lh", 1), side("rh", 2))).alias("s")).select("h", "doc", "place", "s.x", "s.side").where("x is not null")
    shared = both.groupBy("h", "x", "side").count().where("count > 1")
    wanted = both.join(shared, ["h", "x", "side"]).groupBy("doc", "place")
    sides = lambda test: F.bit_or(F.when(test, F.col("side")).otherwise(0)).cast("int")
    wanted = staged(wanted.agg(sides(F.col("count") <= max_share).alias("sides"), sides(F.col("count") > max_share).alias("hot")), "wanted")
    discard(found, book)
    release(docs.sparkSession)
    out = whole.unionByName(staged(sorted_shares(docs, wanted.where("sides > 0"), length), "repeats"))
    release(docs.sparkSession)
    if wanted.where("hot > 0").limit(1).count():
        ranked = suffixes(docs, wanted.where("hot > 0"), length, bits)
        first = ranked.groupBy("w1", "w2").agg(F.min(F.struct("doc", "at")).alias("f"), F.count("*").alias("n")).where("n > 1").select("w1", "w2", F.col("f.doc").alias("d0"), F.col("f.at").alias("a0"))
        single = ranked.join(first, ["w1", "w2"]).where("doc <> d0 or at <> a0").select("doc", (F.col("at") * _RUN + length).alias("run"))
        out = out.unionByName(staged(single, "hot-repeats"))
        discard(ranked)
        release(docs.sparkSession)
    discard(wanted)
    return out


def _merged(runs: np.ndarray) -> list[tuple[int, int]]:
    """(start, end) of runs in order, those that overlap or touch made one."""
    if not len(runs):
        return []
    runs = np.sort(runs)
    start = runs // _RUN
    end = np.maximum.accumulate(start + runs % _RUN)
    new = np.r_[True, start[1:] > end[:-1]]
    return list(zip(start[new].tolist(), end[np.r_[np.nonzero(new)[0][1:] - 1, len(runs) - 1]].tolist()))


def _numbered(docs: DataFrame) -> DataFrame:
    """The same rows with number: the doc_id, if all rows of one have one text, else numbers in the same order that tell texts apart."""
    keyed = docs.withColumn("th", F.xxhash64("text"))
    clash = keyed.where("doc_id is not null").groupBy("doc_id").agg((F.min("th") != F.max("th")).alias("two")).where("two")
    if not clash.limit(1).count():
        return docs.withColumn("number", F.col("doc_id"))
    pairs = keyed.where("doc_id is not null").select(F.col("doc_id").alias("d"), F.col("th").alias("t")).distinct().orderBy("d", "t")
    pairs = staged(pairs.withColumn("number", F.monotonically_increasing_id()), "numbers")
    return keyed.join(pairs, (F.col("doc_id") == F.col("d")) & (F.col("th") == F.col("t")), "left").select("doc_id", "text", "number")


def dedup(docs: DataFrame, length: int = 100, bits: int = 26, with_bytes: bool = True, max_share: int = 2_000) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, and kept: the bytes that are left (NULL if not with_bytes)."""
    docs = _numbered(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")))
    runs = repeats(docs.select(F.col("number").alias("doc_id"), "text"), length, bits, max_share).groupBy("doc").agg(F.collect_list("run").alias("runs"))
    both = docs.join(runs, F.col("number") == F.col("doc"), "left").select("doc_id", "text", "runs")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                out: list[tuple] = []
                for doc, text, own in zip(*(part.column(i) for i in range(3))):
                    doc, b = doc.as_py(), _bytes(text.as_py())
                    kept, pos, spans = [], 0, 0
                    end = -1
                    for s, e in _merged(own.values.to_numpy() if own.is_valid else np.zeros(0, np.int64)):
                        if s > end:  # touching runs are one
                            kept.append(b[pos:s])
                            spans += 1
                        pos = end = max(end, e)
                    left = b"".join([*kept, b[pos:]])
                    out.append((doc, len(b), len(b) - len(left), spans, hashlib.sha256(left).hexdigest(), left if with_bytes else None))
                columns = [pa.array(c, t) for c, t in zip(zip(*out), (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary()))]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    return both.mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")
