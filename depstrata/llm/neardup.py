"""Near-duplicates: improved consistent weighted sampling over TF-IDF shingles, banded, verified by weighted Jaccard similarity.

A shingle is five consecutive words of the lower-cased text (a shorter text is one shingle); its weight is its count in the text times the
mean inverse document frequency of its words.  The frequencies cover all documents; they are held in a table of
fixed size that is indexed by a hash of the word, so what every task gets does not grow with the corpus.  Frequencies of
words rather than shingles keep a large group of near copies from making its own shingles cheap.

Texts that are equal word for word form one class first.  Of the rest, every bucket of a band is compared with its first document; those that are
too different from it are compared again among themselves, and what is left after some rounds in blocks, where
the triangle inequality of the Jaccard distance tells which pairs may still be linked.  So two texts of a bucket never lose their link because both
met a third one, and a group of copies costs one comparison for each member, not one for each pair.  Links are joined to classes
by label propagation.

Texts have numbers of their own here, so rows that share a doc_id but not a text are documents of their own, and so are rows without a doc_id: no
text stands in for another.

Edge cases: texts without words (NULL, empty, white space) are classes of their own; the class_id is the smallest doc_id of the class, NULL if none has one;
repeated rows come back as often; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from depstrata.llm.common import WORD, apart, staged

_U = np.uint64
#: Plain and weighted similarity differ by less than this where a link is in doubt.
_MARGIN = 0.05
_MIX = (_U(0xFF51AFD7ED558CCD), _U(0xC4CEB9FE1A85EC53))


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers in which every bit depends on all others."""
    x = (x ^ (x >> _U(33))) * _MIX[0]
    x = (x ^ (x >> _U(33))) * _MIX[1]
    return x ^ (x >> _U(33))


def word_hashes(text: str | None) -> tuple[list[bytes], np.ndarray]:
    import xxhash

    ws = (text or "").lower().encode("utf-8", "surrogatepass").split()
    return ws, np.fromiter(map(xxhash.xxh3_64_intdigest, ws), np.uint64, len(ws))


def word_frequencies(docs: DataFrame, bits: int = 18) -> tuple[np.ndarray, int]:
    """Documents that hold a word of each slot, and documents with words; 2 ** bits numbers whatever the corpus."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, total = np.zeros(1 << bits, np.int64), 0
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                for text in batch.column(0).slice(at, 1024).to_pylist():
                    slots = np.unique(word_hashes(text)[1] >> _U(64 - bits)).astype(np.int64)
                    n[slots] += 1
                    total += len(slots) > 0
        at = np.nonzero(n)[0]
        yield pa.RecordBatch.from_arrays([pa.array(np.r_[-1, at], pa.int32()), pa.array(np.r_[total, n[at]], pa.int64())], names=["slot", "n"])

    got = docs.select(F.col("text").cast("string").alias("text")).mapInArrow(count, "slot int, n long").groupBy("slot").agg(F.sum("n").alias("n")).toArrow()
    slot, n = got.column("slot").to_numpy(), got.column("n").to_numpy()
    out = np.zeros(1 << bits, np.int64)
    out[slot[slot >= 0]] = n[slot >= 0]
    return out, int(n[slot < 0].sum())


@dataclass
class Weigher:
    """Distinct shingles of a text, sorted, and their weights."""

    idf: np.ndarray
    bits: int
    span: int = 5

    @staticmethod
    def of(docs: DataFrame, bits: int = 18) -> Weigher:
        df, n = word_frequencies(docs, bits)
        return Weigher((np.log((n + 1) / (df + 1)) + 1).astype(np.float32), bits)

    def __call__(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not len(h):
            return h, np.zeros(0)
        span = min(self.span, len(h))
        k = len(h) - span + 1
        idf = self.idf[(h >> _U(64 - self.bits)).astype(np.int64)]
        s, w = np.zeros(k, np.uint64), np.zeros(k)
        for i in range(span):
            s = mix(s * _U(31) + h[i : i + k])
            w += idf[i : i + k]
        s, first, count = np.unique(s, return_index=True, return_counts=True)
        return s, w[first] * count / span


def similarity(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Weighted Jaccard similarity."""
    total = a[1].sum() + b[1].sum()
    _, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    both = np.minimum(a[1][i], b[1][j]).sum()
    return float(both / (total - both)) if total > both else 1.0


def linked(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray], least: float) -> tuple[float, bool]:
    """Weighted similarity, and whether it or that of the plain sets of shingles is enough."""
    s = similarity(a, b)
    if least - _MARGIN <= s < least:
        both = len(np.intersect1d(a[0], b[0], assume_unique=True))
        return s, both >= least * (len(a[0]) + len(b[0]) - both)
    return s, s >= least


class Sampler:
    """Consistent weighted samples: two texts agree in one with their weighted Jaccard similarity as probability.

    The gamma and uniform variates of a shingle and sample come from a hash; gammas through tables of quantiles.
    """

    def __init__(self, n: int, seed: int = 11):
        rng = np.random.default_rng(seed)
        self.seeds = rng.integers(1, 2**63, n, dtype=np.int64).astype(np.uint64)
        self.r = rng.gamma(2, 1, 1 << 16)
        self.log_c = np.log(rng.gamma(2, 1, 1 << 16))

    def __call__(self, s: np.ndarray, w: np.ndarray) -> np.ndarray:
        out = np.empty(len(self.seeds), np.uint64)
        log_w = np.log(w)
        low = _U(0xFFFF)
        step = max(1, 65536 // max(1, len(s)))
        for at in range(0, len(self.seeds), step):
            u = mix(s[None, :] ^ self.seeds[at : at + step, None])
            r = self.r[(u & low).astype(np.intp)]
            beta = (u >> _U(32)).astype(np.float64) * 2.0**-32
            t = np.floor(log_w / r + beta)
            a = self.log_c[((u >> _U(16)) & low).astype(np.intp)] - r * (t - beta + 1)
            best = np.argmin(a, axis=1)
            out[at : at + step] = mix(s[best] ^ mix(t[np.arange(len(best)), best].astype(np.int64).astype(np.uint64) + self.seeds[at : at + step]))
        return out


def signatures(docs: DataFrame, weigher: Weigher, bands: int = 10, rows: int = 3) -> DataFrame:
    """doc_id, th (hash of the text), k1, k2 (a 128-bit hash of the words) and the bucket of each band."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        sampler = Sampler(bands * rows)
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                keys, buckets = [[], []], []
                for text in part.column(1).to_pylist():
                    ws, h = word_hashes(text)
                    if not ws:
                        keys[0].append(None)
                        keys[1].append(None)
                        buckets.append(None)
                        continue
                    k = xxhash.xxh3_128_intdigest(b" ".join(ws))
                    keys[0].append((k >> 64) - 2**63)
                    keys[1].append((k & (2**64 - 1)) - 2**63)
                    sample = sampler(*weigher(h)).reshape(bands, rows)
                    b = np.arange(bands, dtype=np.uint64)
                    for i in range(rows):
                        b = mix(b * _U(31) + sample[:, i])
                    buckets.append(b.view(np.int64))
                arrays = [part.column(0), part.column(2), *(pa.array(k, pa.int64()) for k in keys), pa.array(buckets, pa.list_(pa.int64()))]
                yield pa.RecordBatch.from_arrays(arrays, names=["doc_id", "th", "k1", "k2", "buckets"])

    rows_ = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.xxhash64(F.col("text").cast("string")).alias("th"))
    return rows_.mapInArrow(sign, "doc_id long, th long, k1 long, k2 long, buckets array<long>")


def _compare(pairs: DataFrame, texts: DataFrame, weigher: Weigher, least: float) -> DataFrame:
    """(a, b, sim, link) for pairs (a, b) of ids."""
    left = texts.select(F.col("id").alias("a"), F.col("text").alias("text_a"))
    right = texts.select(F.col("id").alias("b"), F.col("text").alias("text_b"))
    both = pairs.join(left, "a").join(right, "b").select("a", "b", "text_a", "text_b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, known = None, None
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                out = []
                for b, x, y in zip(*(part.column(i).to_pylist() for i in (1, 2, 3))):
                    if b != last:
                        last, known = b, weigher(word_hashes(y)[1])
                    out.append(linked(weigher(word_hashes(x)[1]), known, least))
                arrays = [pa.array([o[i] for o in out], t) for i, t in ((0, pa.float64()), (1, pa.bool_()))]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *arrays], names=["a", "b", "sim", "link"])

    return both.mapInArrow(run, "a long, b long, sim double, link boolean")


def classes(links: DataFrame) -> DataFrame:
    """id, class_id: the smallest id of the connected component of each linked id."""
    both = links.select("a", "b").union(links.select("b", "a")).distinct()
    both = staged(both, "links")
    label = staged(both.groupBy(F.col("a").alias("id")).agg(F.least(F.min("b"), F.first("a")).alias("c")), "labels")
    while True:
        # The smallest label next to each id, then the label of that label.
        near = both.join(label.withColumnRenamed("id", "b"), "b").groupBy("a").agg(F.min("c").alias("n"))
        new = label.join(near, label.id == near.a).select("id", "c", F.least("c", "n").alias("m"))
        jump = label.select(F.col("id").alias("m"), F.col("c").alias("mm"))
        new = staged(new.join(jump, "m", "left").select("id", F.least("m", "mm").alias("c"), (F.least("m", "mm") < F.col("c")).alias("moved")), "labels")
        if not new.where("moved").limit(1).count():
            return new.select("id", F.col("c").alias("class_id"))
        label = new.select("id", "c")


def _blocks(left: DataFrame, texts: DataFrame, weigher: Weigher, least: float, block: int) -> DataFrame:
    """Links among the rows (bucket, id, loose, d, c) of buckets that star rounds left open: blocks of members by blocks of loose ones.

    Only pairs with a loose member, of different components, and with distances to the bucket's first document
    that differ by no more than a link allows, are compared.
    """
    most = 1.0 - least + _MARGIN
    chunks = lambda n: F.ceil(n / block).cast("long")
    size = left.groupBy("bucket").agg(chunks(F.count("*")).alias("n"), chunks(F.count_if("loose")).alias("m"))
    part = left.join(size, "bucket")
    spread = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), n - 1))
    dealt = lambda n: F.pmod(F.xxhash64("id", F.lit(5)), n)
    own = ("bucket", "id", "loose", "d", "c")
    members = part.select(*own, F.lit(False).alias("probe"), dealt(F.col("n")).alias("i"), spread(F.col("m")).alias("j"))
    probes = part.where("loose").select(*own, F.lit(True).alias("probe"), dealt(F.col("m")).alias("j"), spread(F.col("n")).alias("i"))
    both = members.unionByName(probes).join(texts, "id")

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("id")
        ids, d, c, probe, text = (t.column(x).to_pylist() for x in ("id", "d", "c", "probe", "text"))
        known: dict[int, tuple] = {}

        def of(p: int) -> tuple:
            if ids[p] not in known:
                x = weigher(word_hashes(text[p])[1])
                known[ids[p]] = x, x[1].sum()
            return known[ids[p]]

        out: list[tuple[int, int, float]] = []
        group = list(c)  # links found here join groups, and joined ones need no more
        for p in range(len(ids)):
            for q in range(len(ids)):
                if not probe[p] or probe[q] or group[p] == group[q] or abs(d[p] - d[q]) > most:
                    continue
                (x, nx), (y, ny) = of(p), of(q)
                if min(nx, ny) < (least - _MARGIN) * max(nx, ny):
                    continue
                s, link = linked(x, y, least)
                if link:
                    out.append((ids[p], ids[q], s))
                    old = group[p]
                    group = [group[q] if g == old else g for g in group]
        a, b, s = zip(*out) if out else ((), (), ())
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64()), "sim": pa.array(s, pa.float64())})

    return both.groupBy("bucket", "i", "j").applyInArrow(run, "a long, b long, sim double")


def grouped(docs: DataFrame, least: float = 0.8, bands: int = 10, rows: int = 3, rounds: int = 2, block: int = 256) -> DataFrame:
    """doc_id, th, and of the first document of the class class_id and class_th; one row for each row of docs."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    weigher = Weigher.of(docs)
    signed = staged(signatures(docs, weigher, bands, rows), "signatures")
    some = signed.where("k1 is not null")
    # Texts that are equal word for word; of each the row with the smallest doc_id.
    row = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "th")
    same = some.groupBy("k1", "k2").agg(F.min(row).alias("row"), F.any_value("buckets").alias("buckets"))
    same = staged(same.withColumn("id", F.monotonically_increasing_id()), "representatives")
    open_ = same.select("id", F.explode("buckets").alias("bucket"))
    met, texts = None, None
    for _ in range(rounds):
        first = open_.groupBy("bucket").agg(F.min("id").alias("b"), F.count("*").alias("n")).where("n > 1").drop("n")
        pairs = staged(open_.join(first, "bucket").where("id <> b").select("bucket", F.col("id").alias("a"), "b"), "pairs")
        wanted = pairs.select("a", "b").distinct()
        if texts is None:
            ids = wanted.select("a").union(wanted.select("b")).distinct().withColumnRenamed("a", "id")
            ids = same.join(ids, "id").select("id", F.col("row.doc_id").alias("d"), F.col("row.th").alias("t"))
            found = docs.withColumn("th", F.xxhash64("text")).join(ids, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("th") == F.col("t")))
            texts = staged(found.select("id", "text").dropDuplicates(["id"]), "texts")
        sims = staged(_compare(wanted, texts, weigher, least), "similarities")
        # Distances to the first document of the bucket in the first round; later ones only tell who is linked.
        now = pairs.join(sims, ["a", "b"]).select("bucket", "a", "b", "sim", "link")
        met = staged(now if met is None else met.unionByName(now), "met")
        open_ = staged(now.where("not link").select(F.col("a").alias("id"), "bucket"), "open")
        if not open_.limit(1).count():
            break
    links = met.where("link").select("a", "b")
    joined = classes(links)
    rest = _left(met, joined, least)
    if rest.limit(1).count():
        more = staged(_blocks(rest, texts, weigher, least, block), "links")
        if more.limit(1).count():
            joined = classes(links.union(more.select("a", "b")))
    # Back to all rows, by the first row of the class.
    linked_ = joined.join(same.select("id", "row"), "id")
    first = linked_.groupBy("class_id").agg(F.min("row").alias("first"))
    of = same.drop("buckets").join(joined.join(first, "class_id").drop("class_id"), "id", "left").select("k1", "k2", F.coalesce("first", "row").alias("first"))
    mine = some.select("doc_id", "th", "k1", "k2").join(of, ["k1", "k2"]).select("doc_id", "th", F.col("first.doc_id").alias("class_id"), F.col("first.th").alias("class_th"))
    return mine.unionByName(signed.where("k1 is null").select("doc_id", "th", F.col("doc_id").alias("class_id"), F.col("th").alias("class_th")))


def near_duplicates(docs: DataFrame, **how) -> DataFrame:
    """doc_id, class_id: the smallest doc_id of the class; one row for each row of docs."""
    return grouped(docs, **how).select("doc_id", "class_id")


def _left(met: DataFrame, joined: DataFrame, least: float) -> DataFrame:
    """(bucket, id, loose, d, c): members of buckets where a link may still be missing."""
    first = met.groupBy("bucket").agg(F.min("b").alias("first"), F.count("*").alias("n"))
    # Members by their distance to the bucket's first document; loose: not linked to it.
    own = met.join(first, "bucket").where("b = first").select("bucket", "first", F.col("a").alias("id"), (1 - F.col("sim")).alias("d"))
    label = joined.select(F.col("id").alias("i"), F.col("class_id").alias("c"))
    own = own.join(label, F.col("id") == F.col("i"), "left").select("bucket", "first", "id", "d", F.coalesce("c", "id").alias("c"))
    head = joined.select(F.col("id").alias("first"), F.col("class_id").alias("fc"))
    own = own.join(head, "first", "left").withColumn("loose", F.col("c") != F.coalesce("fc", "first"))
    span = own.where("loose").groupBy("bucket").agg(F.min("d").alias("lo"), F.countDistinct("c").alias("kinds"))
    own = own.join(span, "bucket")
    # A linked member can be near a loose one only if its distance is within reach; loose members of one class need nothing.
    reach = F.col("loose") | (F.col("d") >= F.col("lo") - (1 - least) - _MARGIN)
    own = own.where(reach).select("bucket", "id", "loose", "d", "c")
    more = own.groupBy("bucket").agg(F.countDistinct("c").alias("k")).where("k > 1").select("bucket")
    return staged(own.join(more, "bucket", "left_semi"), "left")


def keep_one(docs: DataFrame, **how) -> DataFrame:
    """One row of each class, that of the smallest doc_id, with the columns it has; rows without words stay as they are."""
    # Keys without NULLs: one shuffle serves the join and the distinct rows.
    key = lambda d, t: [d.isNull().alias("near__dn"), F.coalesce(d, F.lit(0)).alias("near__d"), t.alias("near__t")]
    names = ["near__dn", "near__d", "near__t"]
    first = grouped(docs, **how).select(*key(F.col("class_id"), F.col("class_th"))).distinct()
    text = F.col("text").cast("string")
    worded = F.coalesce(text.rlike(WORD), F.lit(False))
    own, back = apart(docs)
    known = docs.where(worded).select(*own, *key(F.col("doc_id").cast("long"), F.xxhash64(text))).join(first, names, "left_semi").dropDuplicates(names)
    return known.select(*back).unionByName(docs.where(~worded))
