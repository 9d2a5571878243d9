"""Near-duplicate documents by MinHash bands, full-set confirmation and components (operator 8).

A document's set holds the distinct shingles of SHINGLE consecutive words; a shorter text
is one shingle, a text without words is the empty set and linked with nothing.

1. One pass over the texts gives each document its set's size, a 128-bit fingerprint of
   the set, HASHES universal-hash minima and the keys of bands of them: 24 bands of 5
   minima for a threshold of 85 % or more, 30 bands of 4 from 80 %.
2. Documents with equal sets form a class, represented by its smallest id; only classes
   go on, so groups of copies never meet pair by pair.
3. In each band bucket the class with the smallest id is the centre; every other class
   of the bucket is paired with it once. The signature check removes poor pairs, and
   whole texts of the rest decide.
4. Components of these links. A bucket whose classes are then all in one component can add
   nothing. Of the others, classes outside the centre's component are compared with all
   classes of other components, in blocks of about BLOCK rows a side, first by signature, then
   on whole texts. A block gives back links, not pairs; no link is lost, and members
   of one component are never compared with each other.

At a similarity of 0.85 a pair shares no bucket with probability (1 - 0.85**5)**24 < 1e-6, at
0.8 with (1 - 0.8**4)**30 < 2e-7; the signature check drops it with probability < 1e-6.

Null ids take no part in linking; their rows come back with their class's id, or null.
Rows that share an id are documents of their own, with their own sets, linked under that id;
`stays` names one row of each component, also where rows are repeated. A null text has the empty set.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from termatlas.functions.scratch import materialize
from termatlas.llm.components import connected_components
from termatlas.llm.tables import bounded_batches

SHINGLE, HASHES, SEED, BLOCK = 5, 120, 20240229, 256


def rows_of_band(percent: int) -> int:
    """Minima of a band; of the same HASHES, a lower threshold has more and shorter bands."""
    if percent < 80:
        raise ValueError("bands are made for thresholds of 80 % or more")
    return 5 if percent >= 85 else 4


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


class Shingler:
    """Sorted distinct 64-bit shingle hashes of a text."""

    def __init__(self, k: int = SHINGLE):
        self.k, self.words = k, _Hashes()
        self.odd = np.random.default_rng(7).integers(1 << 62, 1 << 63, k + 1, dtype=np.uint64) | np.uint64(1)

    def __call__(self, text: str | None) -> np.ndarray:
        words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # of bytes: only A-Z, only ASCII space
        if len(self.words) > 100_000:
            self.words.clear()
        h = np.fromiter(map(self.words.__getitem__, words), np.uint64, len(words))
        if not len(h):
            return h
        k = min(self.k, len(h))
        out = np.full(len(h) - k + 1, k, np.uint64)
        for i in range(k):
            out = (out ^ h[i : i + len(out)]) * self.odd[i]
            out ^= out >> np.uint64(31)
        return np.unique(out * self.odd[k])


class MinHasher:
    """Minima of multiply-add hash functions modulo 2**64, upper halves."""

    def __init__(self, hashes: int = HASHES, seed: int = SEED):
        rng = np.random.default_rng(seed)
        self.a = (rng.integers(0, 1 << 63, (hashes, 1), dtype=np.uint64) << np.uint64(1)) | np.uint64(1)
        self.b = rng.integers(0, 1 << 63, (hashes, 1), dtype=np.uint64)

        self.room = np.empty((hashes, 256), np.uint64)  # stays in the processor's cache

    def __call__(self, shingles: np.ndarray) -> np.ndarray:
        low = np.full(len(self.a), ~np.uint64(0))
        for at in range(0, len(shingles), 256):
            part = shingles[at : at + 256]
            room = self.room[:, : len(part)]
            np.multiply(self.a, part, out=room)
            room += self.b
            np.minimum(low, room.min(axis=1), out=low)
        return (low >> np.uint64(32)).astype(np.uint32)


def similar(x: np.ndarray, y: np.ndarray, percent: int) -> bool:
    """Whether 100 * intersection >= percent * union of two sorted sets; empty sets are similar to none."""
    if 100 * min(len(x), len(y)) < percent * max(len(x), len(y)) or not len(x):
        return False
    both = len(np.intersect1d(x, y, assume_unique=True))
    return 100 * both >= percent * (len(x) + len(y) - both)


def least_agreement(percent: int, hashes: int = HASHES) -> int:
    """Five standard deviations below the agreement expected at the threshold."""
    p = percent / 100
    return max(1, int(hashes * p - 5 * (hashes * p * (1 - p)) ** 0.5))


def signatures(docs: DataFrame, key: str = "doc_id", text: str = "text", percent: int = 85) -> DataFrame:
    """doc, t (a hash of the text), n, fp (null for the empty set), sig (low bytes of the minima), bands (bucket keys)."""
    band = rows_of_band(percent)
    schema = "doc long, t long, n long, fp binary, sig binary, bands array<long>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler, hasher = Shingler(), MinHasher()
        for batch in batches:
            n, fp, sig, bands = [], [], [], []
            for value in batch.column(2):
                s = shingler(value.as_py())
                n.append(len(s))
                if not len(s):
                    fp.append(None), sig.append(None), bands.append(None)
                    continue
                low = hasher(s)
                fp.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest())
                sig.append(low.astype(np.uint8).tobytes())
                rows = low.reshape(-1, band)
                bands.append([xxhash.xxh3_64_intdigest(r.tobytes(), i) - (1 << 63) for i, r in enumerate(rows)])
            made = [pa.array(n, pa.int64()), pa.array(fp, pa.binary()), pa.array(sig, pa.binary()), pa.array(bands, pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *made], names=["doc", "t", "n", "fp", "sig", "bands"])

    given = bounded_batches(docs).select(F.col(key).cast("long").alias("doc"), F.xxhash64(text).alias("t"), F.col(text).alias("text"))
    return given.mapInArrow(run, schema).withColumn("row", F.monotonically_increasing_id())


def _agreeing(least: int):
    @F.pandas_udf("boolean")
    def agree(x: pd.Series, y: pd.Series) -> pd.Series:
        if not len(x):
            return pd.Series([], dtype=bool)
        a, b = (np.frombuffer(b"".join(s), np.uint8).reshape(len(s), -1) for s in (x, y))
        return pd.Series((a == b).sum(axis=1) >= least)

    return agree


def _confirming(percent: int):
    @F.pandas_udf("boolean")
    def confirm(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        shingler = Shingler()
        for x, y in parts:
            yield pd.Series([similar(shingler(a), shingler(b), percent) for a, b in zip(x, y, strict=True)], dtype=bool)

    return confirm


#: Bits of the map of wanted ids; with the 4 KB rows of Spark's bitmaps, a broadcast of at most 8 MB.
MAP_BITS = 1 << 26


def _wanted(texts: DataFrame, ids: DataFrame) -> DataFrame:
    """The rows of texts whose doc is in ids (column doc), and a few others: a bitmap of hashed ids spares the others' shuffle.

    Of fixed size however many ids there are; when many, it lets more rows pass.
    """
    place = F.pmod(F.xxhash64("doc"), F.lit(MAP_BITS))
    maps = ids.select(F.bitmap_bucket_number(place).alias("part"), F.bitmap_bit_position(place).alias("at")).groupBy("part").agg(F.bitmap_construct_agg("at").alias("map"))
    at = F.bitmap_bit_position(place)
    byte = F.conv(F.hex(F.substring("map", (F.floor(at / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    rows = texts.withColumn("part", F.bitmap_bucket_number(place)).join(F.broadcast(maps), "part")
    return rows.where(F.getbit(byte, F.pmod(at, F.lit(8)).cast("int")) == 1).select(*texts.columns)


def _links(pairs: DataFrame, sigs: DataFrame, texts: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) that hold on whole texts."""
    x, y = sigs.select("doc", "sig").alias("x"), sigs.select("doc", "sig").alias("y")
    near = pairs.join(x, F.col("a") == F.col("x.doc")).join(y, F.col("b") == F.col("y.doc"))
    near = near.where(_agreeing(least_agreement(percent))(F.col("x.sig"), F.col("y.sig"))).select("a", "b")
    near = materialize(near, "near")
    texts = _wanted(texts, near.select(F.explode(F.array("a", "b")).alias("doc")))
    s, t = texts.alias("s"), texts.alias("t")
    both = near.join(s, F.col("a") == F.col("s.doc")).join(t, F.col("b") == F.col("t.doc"))
    return materialize(both.where(_confirming(percent)(F.col("s.text"), F.col("t.text"))).select("a", "b"), "links")


def _dealt(buckets: DataFrame, found: DataFrame) -> DataFrame:
    """Members of buckets with several components, by blocks of rows to compare: bucket, i, j, chunk, rep, n, component.

    Chunks below `outer` hold the members outside the centre's component, the others the rest.
    A block pairs chunk i with chunk j >= i; two chunks of the rest never meet.
    """
    own = buckets.join(found.select(F.col("node").alias("rep"), "component"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))
    home = own.groupBy("bucket").agg(F.min_by("component", "rep").alias("home"), F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo < hi")
    own = own.join(home.select("bucket", "home"), "bucket").withColumn("outside", F.col("component") != F.col("home"))
    parts = (F.ceil(F.sum(F.when(c, 1).otherwise(0)) / F.lit(BLOCK)).cast("int").alias(k) for k, c in (("outer", F.col("outside")), ("inner", ~F.col("outside"))))
    own = own.join(own.groupBy("bucket").agg(*parts), "bucket")
    h = F.xxhash64("rep")
    chunk = F.when(F.col("outside"), F.pmod(h, F.col("outer"))).otherwise(F.col("outer") + F.pmod(h, F.greatest("inner", F.lit(1)))).cast("int")
    others = F.sequence(F.lit(0), F.when(F.col("outside"), F.col("outer") + F.col("inner")).otherwise(F.col("outer")) - 1)
    rows = own.withColumn("chunk", chunk).withColumn("other", F.explode(others))
    return rows.select("bucket", F.least("chunk", "other").alias("i"), F.greatest("chunk", "other").alias("j"), "chunk", "rep", "n", "component")


BLOCK_KEY = ("bucket", "i", "j")


def _grouped(frames: Iterator[pd.DataFrame], each) -> Iterator[pd.DataFrame]:
    """each(block) -> DataFrame or None, over the whole blocks of sorted frames."""
    open_ = None
    for frame in frames:
        if open_ is not None:
            frame = pd.concat([open_, frame], ignore_index=True)
        keys = frame[list(BLOCK_KEY)].to_numpy()
        cuts = [0, *(np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1)]
        out = [r for a, b in zip(cuts, cuts[1:], strict=False) if (r := each(frame.iloc[a:b])) is not None]
        open_ = frame.iloc[cuts[-1] :]
        if out:
            yield pd.concat(out, ignore_index=True)
    if open_ is not None and len(open_) and (r := each(open_)) is not None:
        yield r


def _sides(block: pd.DataFrame) -> Iterator[tuple[int, np.ndarray]]:
    """(x, ys) of row places to compare: each pair of the block's two chunks once, across components."""
    chunk, comp = block.chunk.to_numpy(), block.component.to_numpy()
    i, j = block.i.iloc[0], block.j.iloc[0]
    right = np.flatnonzero(chunk == j)
    for x in np.flatnonzero(chunk == i):
        y = right[comp[right] != comp[x]]
        yield x, y[y > x] if i == j else y


def _near(rows: DataFrame, sigs: DataFrame, percent: int) -> DataFrame:
    """The rows of blocks that have a partner with a similar signature and size."""
    least = least_agreement(percent)

    def each(block: pd.DataFrame) -> pd.DataFrame | None:
        sig, n = np.frombuffer(b"".join(block.sig), np.uint8).reshape(len(block), -1), block.n.to_numpy()
        keep = np.zeros(len(block), bool)
        for x, y in _sides(block):
            y = y[100 * np.minimum(n[y], n[x]) >= percent * np.maximum(n[y], n[x])]
            if len(y) and len(y := y[(sig[y] == sig[x]).sum(axis=1) >= least]):
                keep[x] = keep[y] = True
        return block[keep].drop(columns="sig") if keep.any() else None

    given = rows.join(sigs.select(F.col("doc").alias("rep"), "sig"), "rep").select(*rows.columns, "sig")
    return given.repartition(*BLOCK_KEY).sortWithinPartitions(*BLOCK_KEY).mapInPandas(lambda frames: _grouped(frames, each), rows.schema)


def _block_links(rows: DataFrame, texts: DataFrame, percent: int) -> DataFrame:
    """Links (a, b) across components in blocks, confirmed on whole texts; of links within a block, enough to connect what they connect."""

    def confirm(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shingler = Shingler()

        def each(block: pd.DataFrame) -> pd.DataFrame | None:
            sets = [shingler(t) for t in block.text]
            rep, comp, n = block.rep.to_numpy(), list(block.component), np.array([len(x) for x in sets])
            flat, place = np.unique(np.concatenate(sets), return_inverse=True)
            starts = np.concatenate([[0], np.cumsum(n)])
            mark, top, links = np.zeros(len(flat), np.int32), {c: c for c in comp}, []

            def root(c):
                while top[c] != c:
                    c = top[c]
                return c

            for x, ys in _sides(block):
                ys = ys[100 * np.minimum(n[ys], n[x]) >= percent * np.maximum(n[ys], n[x])]
                if not len(ys):
                    continue
                own = place[starts[x] : starts[x + 1]]
                mark[own] = 1
                both = np.array([mark[place[starts[y] : starts[y + 1]]].sum() for y in ys])
                mark[own] = 0
                for y in ys[100 * both >= percent * (n[ys] + n[x] - both)]:
                    p, q = root(comp[x]), root(comp[y])
                    if p != q:
                        top[max(p, q)] = min(p, q)
                        links.append((max(rep[x], rep[y]), min(rep[x], rep[y])))
            return pd.DataFrame(links, columns=["a", "b"], dtype="int64") if links else None

        yield from _grouped(frames, each)

    texts = _wanted(texts, rows.select(F.col("rep").alias("doc")))
    given = rows.join(texts.withColumnRenamed("doc", "rep"), "rep").select(*rows.columns, "text")
    return given.repartition(*BLOCK_KEY).sortWithinPartitions(*BLOCK_KEY).mapInPandas(confirm, "a long, b long").distinct()


def near_duplicates(docs: DataFrame, percent: int = 85, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id, kept (its id names its component), stays, text_hash for each row.

    Links hold at 100 * intersection >= percent * union, percent >= 80. Of the rows with an id, one of each component stays;
    so do rows with the empty set, or without an id.
    """
    sigs = materialize(signatures(docs, key, text, percent), "signatures")
    texts = docs.where(F.col(key).isNotNull() & F.col(text).isNotNull()).select(F.col(key).cast("long").alias("doc"), text).toDF("doc", "text")
    least = sigs.where("doc is not null and n > 0").groupBy("fp").agg(F.min(F.struct("doc", "row")).alias("least"))
    classes = materialize(least.select("fp", F.col("least.doc").alias("rep"), F.col("least.row").alias("rep_row")), "classes")
    c = classes.select("rep_row")
    reps = materialize(sigs.join(c, F.col("row") == F.col("rep_row")).select(F.col("doc"), "n", "sig", "bands", "fp"), "representatives")
    bands = reps.select(F.col("doc").alias("rep"), "n", F.explode("bands").alias("bucket"))
    shared = bands.groupBy("bucket").agg(F.min(F.struct("rep", "n")).alias("centre"), F.max("rep").alias("last")).where("centre.rep < last").select("bucket", "centre")
    buckets = materialize(bands.join(shared, "bucket").select("bucket", "rep", "n", "centre"), "buckets")
    star = buckets.where((F.col("rep") != F.col("centre.rep")) & (F.least("n", "centre.n") * 100 >= F.greatest("n", "centre.n") * percent))
    star = materialize(star.select(F.col("rep").alias("a"), F.col("centre.rep").alias("b")).distinct(), "pairs")
    sig = reps.select("doc", "sig")
    links = _links(star, sig, texts, percent)
    found = connected_components(links)
    rest = materialize(_near(_dealt(buckets.select("bucket", "rep", "n"), found), sig, percent), "rest")
    if not rest.isEmpty():
        links = links.unionByName(materialize(_block_links(rest, texts, percent), "links"))
        found = connected_components(links)
    named = classes.join(found.withColumnRenamed("node", "rep"), "rep", "left").select("fp", "rep_row", F.coalesce("component", "rep").alias("component"))
    out = sigs.join(named, "fp", "left").select(F.col("doc").alias("doc_id"), F.col("n").alias("n_shingles"), F.coalesce("component", "doc").alias("component_id"), "row", "rep_row", F.col("t").alias("text_hash"))
    out = out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(False)))
    stays = F.col("doc_id").isNull() | F.col("rep_row").isNull() | (F.col("kept") & (F.col("row") == F.col("rep_row")))
    return out.withColumn("stays", stays).drop("row", "rep_row")


def drop_near_duplicates(docs: DataFrame, percent: int = 80, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of docs, with all their columns, that stay."""
    judged = materialize(near_duplicates(docs, percent, key, text).where("doc_id is not null").select(F.col("doc_id").alias("_nd_id"), F.col("text_hash").alias("_nd_hash"), "stays"), "judged")
    by = judged.groupBy("_nd_id", "_nd_hash").agg(F.sum(F.col("stays").cast("int")).alias("_nd_stay"), F.count("*").alias("_nd_n")).where("_nd_stay < _nd_n")
    by = materialize(by.select("_nd_id", "_nd_hash", "_nd_stay"), "gone")
    same = (F.col(f"`{key}`").cast("long") == F.col("_nd_id")) & (F.xxhash64(text) == F.col("_nd_hash"))
    out = docs.join(by.drop("_nd_stay"), same, "left_anti").select(*docs.columns)
    repeated = by.where("_nd_stay > 0")
    if repeated.isEmpty():
        return out
    # of repeated rows one stays, the least in its other columns
    row = F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_nd_row")
    one = docs.select(row, F.col(f"`{key}`").cast("long").alias("_nd_i"), F.xxhash64(text).alias("_nd_h"))
    one = one.join(repeated, (F.col("_nd_i") == F.col("_nd_id")) & (F.col("_nd_h") == F.col("_nd_hash")), "left_semi")
    return out.unionByName(one.groupBy("_nd_i", "_nd_h").agg(F.min("_nd_row").alias("_nd_row")).select("_nd_row.*"))
