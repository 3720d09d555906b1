"""Best-fit packing of token sequences.

Bounded-space online best-fit: a fixed number of open bins; a bitset with one bit for each amount of free
space finds the tightest bin that still takes a piece; when a bin more than allowed would be open, the fullest
one closes.  Pieces come as they arrive, through a look-ahead of bounded size from which the longest go first: that fills what short pieces
in front of long ones would leave open.  Pieces are dealt to groups of bounded size, each packed alone, so that work and memory do
not depend on the size of the corpus.

Edge cases: a NULL or empty text has no tokens but the closing id 0, hence one piece of length 1.  NULL doc_ids are kept as
NULL.  Repeated rows are packed each by itself; groups are dealt by row, so however many rows share a doc_id, or have none, they are spread.  An empty table gives an empty result.
Other columns are ignored.
"""

from __future__ import annotations

import re
import sys
import types
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from depstrata.llm.common import staged

# Letters and numbers of the Latin blocks, as the vocabulary's own pattern splits them.
_LETTERS = "a-zA-ZªµºÀ-ÖØ-öø-ſ"
_NUMBERS = "0-9²³¹¼-¾"
_SPLIT = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d|[{_LETTERS}]+|[{_NUMBERS}]|[^\s{_LETTERS}{_NUMBERS}]+")
#: Texts with anything else go through the library as a whole.
_OTHER = re.compile("[^\t-\r -~ -įı-ſ]|<\\|")
_CACHE = 250_000
#: The vocabulary writes each byte as one character: itself if it prints, else the next one from 256 on.
_PRINTS = [*range(33, 127), *range(161, 173), *range(174, 256)]
_AS_CHARACTER = {b: 256 + i for i, b in enumerate(b for b in range(256) if b not in _PRINTS)}


class Encoder:
    """Token ids of a text as little-endian 32-bit bytes, with a cache of the ids of each pre-token."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        # Python workers serve many tasks: what one has learned stays for the next.
        kept = sys.modules.setdefault("_depstrata_encoders", types.ModuleType("_depstrata_encoders")).__dict__
        if path not in kept:
            kept[path] = Tokenizer.from_file(path), {}
        self.library, self.known = kept[path]

    def _raw(self, text: str) -> bytes:
        ids = self.library.encode(text, add_special_tokens=False).ids
        return b"".join(i.to_bytes(4, "little") for i in ids)

    def __call__(self, text: str) -> bytes:
        if _OTHER.search(text):
            return self._raw(text)
        parts, known = _SPLIT.findall(text.lower()), self.known
        try:
            return b"".join([known[p] for p in parts])
        except KeyError:
            if len(known) > _CACHE:
                known.clear()
            merge = self.library.model.tokenize  # the merges alone, without the library's alignments
            for p in set(parts):
                if p not in known:
                    ids = merge(p.encode().decode("latin-1").translate(_AS_CHARACTER))
                    known[p] = b"".join([t.id.to_bytes(4, "little") for t in ids])
            return b"".join([known[p] for p in parts])


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def pieces(docs: DataFrame, path: str | None = None, limit: int = 2048, closing: int = 0) -> DataFrame:
    """One row for each piece of each document: doc_id, piece, start, length, ids_crc32."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = Encoder(path or tokenizer_path())
        end, step = closing.to_bytes(4, "little"), 4 * limit
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                out: list[list] = [[], [], [], [], []]
                for doc_id, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    ids = encode(text or "") + end
                    for k, lo in enumerate(range(0, len(ids), step)):
                        chunk = ids[lo : lo + step]
                        for col, v in zip(out, (doc_id, k, lo // 4, len(chunk) // 4, zlib.crc32(chunk))):
                            col.append(v)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(c, t) for c, t in zip(out, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()))],
                    names=["doc_id", "piece", "start", "length", "ids_crc32"],
                )

    two = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return two.mapInArrow(cut, "doc_id long, piece int, start long, length long, ids_crc32 long")


def arrivals(lengths: list[int], look_ahead: int) -> list[int]:
    """The order in which pieces are placed: those of each look-ahead from the longest down."""
    return [i for at in range(0, len(lengths), look_ahead) for i in sorted(range(at, min(at + look_ahead, len(lengths))), key=lambda i: (-lengths[i], i))]


def best_fit(lengths: list[int], size: int, open_bins: int) -> list[tuple[int, int]]:
    """(bin, offset) for each length, in the order given."""
    free: list[list[int]] = [[] for _ in range(size + 1)]  # bins by free space
    bits, live, made, out = 0, 0, 0, []
    for n in lengths:
        fits = bits >> n
        if fits:
            f = n + (fits & -fits).bit_length() - 1
            b = free[f].pop()
            if not free[f]:
                bits ^= 1 << f
            live -= 1
        else:
            f, b, made = size, made, made + 1
            if live >= open_bins:
                full = (bits & -bits).bit_length() - 1
                free[full].pop()
                if not free[full]:
                    bits ^= 1 << full
                live -= 1
        out.append((b, size - f))
        f -= n
        if f:
            free[f].append(b)
            bits |= 1 << f
            live += 1
    return out


def pack(table: DataFrame, size: int = 2048, open_bins: int = 64, look_ahead: int = 256, group_rows: int = 16_384) -> DataFrame:
    """Add sequence_id and offset to the pieces."""
    table = staged(table.withColumn("row", F.monotonically_increasing_id()), "pieces")
    groups = max(1, round(table.count() / group_rows))

    def place(t: pa.Table) -> pa.Table:
        t = t.sort_by("row")
        lengths = t.column("length").to_pylist()
        order = arrivals(lengths, look_ahead)
        where: list[tuple[int, int]] = [(0, 0)] * len(lengths)
        for i, at in zip(order, best_fit([lengths[i] for i in order], size, open_bins)):
            where[i] = at
        first = (t.column("group")[0].as_py() if t.num_rows else 0) << 32
        t = t.drop_columns(["group", "row"])
        t = t.append_column("sequence_id", pa.array([first + b for b, _ in where], pa.int64()))
        return t.append_column("offset", pa.array([o for _, o in where], pa.int64()))

    dealt = table.withColumn("group", F.pmod(F.xxhash64("row"), F.lit(groups)))
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"
    return dealt.groupBy("group").applyInArrow(place, schema)
