"""Near-duplicate detection by circulant MinHash.

Two permutations make the whole signature: the first scatters shingles over positions 0..D-1, the
second, shifted circularly by k, gives coordinate k, so a shingle's contribution to all coordinates is
one contiguous slice of a table. Coordinates are cut into bands; documents that share a band are
candidates, and every link is confirmed on the full shingle sets.

Texts with the same words are one class, represented by its smallest id, before any candidate is
made. Within a band's bucket candidates are first tested against its smallest member only.
Buckets whose members are then one component are settled, however large; that is what groups of
copies are. What is left are texts that resemble each other and yet are not linked so far. Those are
gathered by family (or by bucket, where families are large), cut into blocks of bounded size, and each
pair of blocks is joined exactly as a product of two small set matrices. No pair is emitted that is not a
link, and no bucket is capped.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import broadcast_if_small, pick, stored, table
from .components import components
from .memory import released

SHINGLE = 5
#: A pair at a similarity of 0.75 shares none of 32 bands of 4 rows with probability 5e-6.
BANDS, ROWS = 32, 4
DOMAIN = 1 << 20
SEED = 20_011
#: Members and bytes of sets in a block; members up to which a family is joined as one.
BLOCK, BLOCK_BYTES, FAMILY = 192, 8 << 20, 4096
#: Columns of the set matrices that are multiplied at once.
COLUMNS = 8192
MEMO = 400_000

_MIX = [np.uint64(c) for c in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD)]


def words(text: str | None) -> list[bytes]:
    """Lower-cased (A-Z only) words between ASCII white space."""
    return text.encode("utf-8", "surrogatepass").lower().split() if text else []


def shingle_set(text: str | None, size: int = SHINGLE) -> set[tuple[bytes, ...]]:
    """The distinct word shingles; fewer words than size are one shingle, no words none."""
    w = words(text)
    if not w:
        return set()
    return set(zip(*(w[i:] for i in range(size)), strict=False)) if len(w) >= size else {tuple(w)}


class WordHashes(dict):
    """64-bit hashes of words, remembered up to a bound."""

    def __init__(self, seed: int = SEED):
        super().__init__()
        self.seed = seed

    def __missing__(self, w: bytes) -> int:
        if len(self) >= MEMO:
            self.clear()
        self[w] = h = xxhash.xxh3_64_intdigest(w, self.seed)
        return h


def shingle_hashes(w: list[bytes], memo: WordHashes, size: int = SHINGLE) -> np.ndarray:
    """Distinct 64-bit hashes of the shingles, sorted."""
    if not w:
        return np.empty(0, np.uint64)
    if len(w) < size:
        return np.array([xxhash.xxh3_64_intdigest(b" ".join(w), memo.seed + len(w))], np.uint64)
    h = np.fromiter(map(memo.__getitem__, w), np.uint64, len(w))
    n = len(w) - size + 1
    out = np.zeros(n, np.uint64)
    for i in range(size):
        out += (h[i : i + n] ^ (h[i : i + n] >> np.uint64(31))) * _MIX[i % len(_MIX)]
        out = (out << np.uint64(13)) | (out >> np.uint64(51))
    out ^= out >> np.uint64(32)
    out *= _MIX[1]
    out ^= out >> np.uint64(29)
    return np.unique(out)


@lru_cache(maxsize=2)
def _circulant(coordinates: int, seed: int) -> np.ndarray:
    """Row p: the second permutation's values at positions p, p+1, ... (circular), for all coordinates."""
    second = np.random.Generator(np.random.PCG64(seed)).permutation(DOMAIN).astype(np.uint32)
    return np.lib.stride_tricks.sliding_window_view(np.concatenate([second, second[:coordinates]]), coordinates)


def signature(hashes: np.ndarray, coordinates: int = BANDS * ROWS, seed: int = SEED) -> np.ndarray:
    """The circulant MinHash coordinates of a set of shingle hashes."""
    at = (hashes >> np.uint64(64 - DOMAIN.bit_length() + 1)).astype(np.int64)
    rows = _circulant(coordinates, seed)
    out = np.full(coordinates, DOMAIN, np.uint32)
    for i in range(0, len(at), 2048):
        np.minimum(out, rows[at[i : i + 2048]].min(axis=0), out=out)
    return out


def band_keys(sig: np.ndarray, bands: int = BANDS, rows: int = ROWS) -> np.ndarray:
    parts = sig.reshape(bands, rows).astype(np.uint64)
    out = np.arange(1, bands + 1, dtype=np.uint64) * _MIX[2]
    for i in range(rows):
        out = (out ^ parts[:, i]) * _MIX[i]
        out ^= out >> np.uint64(29)
    return out.view(np.int64)


def _signed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    memo = WordHashes()
    for batch in batches:
        n, k1, k2, bands = [], [], [], []
        for text in batch.column("text"):
            w = words(text.as_py())
            h = shingle_hashes(w, memo)
            n.append(len(h))
            low, high = divmod(xxhash.xxh3_128_intdigest(b" ".join(w)), 1 << 64)
            k1.append(low - (1 << 63))
            k2.append(high - (1 << 63))
            bands.append(band_keys(signature(h)) if len(h) else np.empty(0, np.int64))
        yield pa.RecordBatch.from_arrays(
            [
                batch.column("key"),
                pa.array(n, pa.int64()),
                pa.array(k1, pa.int64()),
                pa.array(k2, pa.int64()),
                pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, bands)]), pa.int32()), pa.array(np.concatenate([*bands, np.empty(0, np.int64)]))),
            ],
            names=["key", "n_shingles", "k1", "k2", "bands"],
        )


def _linked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The pairs (a, b) whose sets have at least 0.75 of their union in common."""
    kept: tuple[object, set] = (None, set())
    for batch in batches:
        a, b, = batch.column("a"), batch.column("b")
        ta, tb = batch.column("ta"), batch.column("tb")
        good = []
        for i in range(batch.num_rows):
            if (key := b[i].as_py()) != kept[0]:
                kept = (key, shingle_set(tb[i].as_py()))
            x, y = shingle_set(ta[i].as_py()), kept[1]
            both = len(x & y)
            good.append(100 * both >= 75 * (len(x) + len(y) - both))
        yield pa.RecordBatch.from_arrays([a, b], names=["a", "b"]).filter(pa.array(good, pa.bool_()))


def _verified(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """The pairs that are links. Only texts that occur in pairs move; a hub's pairs are split by the skew-aware join."""
    pairs = stored(pairs, "pairs")
    ids = pairs.select(F.explode(F.array("a", "b")).alias("key")).distinct()
    few = texts.join(broadcast_if_small(stored(ids, "pair-ids"), 16), "key", "left_semi")
    full = pairs.join(few.select(F.col("key").alias("a"), F.col("text").alias("ta")), "a").join(
        few.select(F.col("key").alias("b"), F.col("text").alias("tb")), "b"
    )
    return stored(full.select("a", "b", "ta", "tb").mapInArrow(released(_linked), "a long, b long"), "links")


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, n_shingles, component_id, kept for each row of docs.

    component_id is the smallest key reachable over links (Jaccard similarity of five-word shingle
    sets of at least 0.75), the row's own included; kept marks the row that has it. Null and empty
    texts have no shingles and are linked with nothing. Rows with a null key are returned with a null
    component and kept. Rows that repeat a key are one document each if their words agree; if not, each is
    linked by its own words, and as both have one id they are in one component. Empty tables give empty results;
    extra columns are ignored.
    """
    rows = pick(docs, key, text).toDF("key", "text").withColumn("key", F.col("key").cast("long"))
    signed = stored(rows.mapInArrow(released(_signed), "key long, n_shingles long, k1 long, k2 long, bands array<long>"), "signatures")
    linkable = signed.filter("n_shingles > 0 and key is not null")
    classes = stored(linkable.groupBy("k1", "k2").agg(F.min(F.struct("key", "bands", "n_shingles")).alias("first")).select("k1", "k2", F.col("first.key").alias("rep"), "first.bands", F.col("first.n_shingles").alias("size")), "classes")
    member = classes.select("rep", "size", F.explode("bands").alias("bucket"))
    shared = member.groupBy("bucket").agg(F.count("*").alias("n"), F.min(F.struct("rep", "size")).alias("p")).filter("n > 1").select("bucket", F.col("p.rep").alias("pivot"), F.col("p.size").alias("pivot_size"))
    open_ = stored(member.join(shared, "bucket"), "buckets")
    texts = rows.filter("key is not null and text is not null")

    alike = "4 * least(size, pivot_size) >= 3 * greatest(size, pivot_size)"  # else the sets are too unequal for a link
    open_ = open_.filter("rep <> pivot")
    links = _verified(open_.filter(alike).select(F.col("rep").alias("a"), F.col("pivot").alias("b")).distinct(), texts)
    label = stored(components(links), "labels")
    named = open_.join(label.select(F.col("node").alias("rep"), "component"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))
    named = stored(named, "named")
    several = named.groupBy("bucket").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.min("rep").alias("lead")).filter("low <> high")
    rest = stored(named.join(several.select("bucket", "lead"), "bucket"), "open")
    seed = SEED
    while not rest.isEmpty():
        # blocks count common hashes; what they name is confirmed on full sets, and if any is not, blocks are joined again under other hashes
        found = _joined_in_blocks(rest, texts, seed)
        links = _verified(found, texts)
        label = stored(_merged(label, components(_relabelled(links, label))), "labels")
        if links.count() == found.count():
            break
        seed += 1
        rest = stored(rest.drop("component").join(label.select(F.col("node").alias("rep"), "component"), "rep", "left").withColumn("component", F.coalesce("component", "rep")), "open")

    reps = classes.select("k1", "k2", "rep").join(label.select(F.col("node").alias("rep"), "component"), "rep", "left")
    reps = reps.select("k1", "k2", F.coalesce("component", "rep").alias("component"))
    out = signed.select("key", "n_shingles", "k1", "k2").join(reps, ["k1", "k2"], "left")
    own = F.when((F.col("n_shingles") > 0) & F.col("key").isNotNull(), F.col("component")).otherwise(F.col("key"))
    return out.select(F.col("key").alias(key), "n_shingles", own.alias("component_id")).withColumn(
        "kept", F.coalesce(F.col(key) == F.col("component_id"), F.lit(True))
    )


def _sets(seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo = WordHashes(seed)
        for batch in batches:
            for i in range(0, batch.num_rows, 1000):
                part = batch.slice(i, 1000)
                sets = [shingle_hashes(words(t.as_py()), memo).tobytes() for t in part.column("text")]
                yield pa.RecordBatch.from_arrays([part.column("key"), pa.array(sets, pa.binary())], names=["key", "hashes"])

    return run


def common_counts(a: list[np.ndarray], b: list[np.ndarray]) -> np.ndarray:
    """How many elements each set of a has in common with each of b."""
    shared = np.intersect1d(np.concatenate(a), np.concatenate(b))
    out = np.zeros((len(a), len(b)), np.float32)
    for at in range(0, len(shared), COLUMNS):
        names = shared[at : at + COLUMNS]
        sides = []
        for side in (a, b):
            matrix = np.zeros((len(side), len(names)), np.float32)
            for row, x in zip(matrix, side, strict=True):
                x = x[np.searchsorted(x, names[0]) : np.searchsorted(x, names[-1], "right")]
                where = np.searchsorted(names, x)
                row[where[names[where] == x]] = 1
            sides.append(matrix)
        out += sides[0] @ sides[1].T
    return out


def _block_links(rows: pd.DataFrame) -> pd.DataFrame:
    """Links between two blocks, or within one, between different components: as many as it takes to join what they join."""
    rows = rows.drop_duplicates("rep")
    sides = []
    for i in (rows["i"].iloc[0], rows["j"].iloc[0]):
        part = rows[rows["own"] == i]
        sides.append((part["rep"].to_numpy(), part["component"].to_numpy(), [np.frombuffer(h, np.uint64) for h in part["hashes"]]))
    (ra, ca, a), (rb, cb, b) = sides
    if not len(ra) or not len(rb) or (ca[0] == cb[0] and (ca == ca[0]).all() and (cb == cb[0]).all()):
        return pd.DataFrame({"a": [], "b": []}, dtype="int64")
    both = common_counts(a, b)
    whole = np.array(list(map(len, a)))[:, None] + np.array(list(map(len, b)))[None, :] - both
    x, y = np.nonzero((100 * both >= 75 * whole) & (ca[:, None] != cb[None, :]))
    few = _spanning(ca[x], cb[y])
    return pd.DataFrame({"a": ra[x[few]], "b": rb[y[few]]})


def _spanning(a: np.ndarray, b: np.ndarray) -> list[int]:
    """The places of links that are enough to join what all links (a, b) join."""
    up: dict[int, int] = {}

    def root(x: int) -> int:
        while (y := up.setdefault(x, x)) != x:
            up[x] = up[y]
            x = up[x]
        return x

    out = []
    for i, (x, y) in enumerate(zip(a.tolist(), b.tolist(), strict=True)):
        if (x := root(x)) != (y := root(y)):
            up[x] = y
            out.append(i)
    return out


def _joined_in_blocks(rest: DataFrame, texts: DataFrame, seed: int = SEED) -> DataFrame:
    """All links within the open buckets between different components; rest: bucket, lead, rep, size, component."""
    family = stored(components(rest.select(F.col("rep").alias("a"), F.col("lead").alias("b"))), "families").withColumnRenamed("node", "rep").withColumnRenamed("component", "family")
    small = family.groupBy("family").agg(F.count("*").alias("members")).filter(F.col("members") <= FAMILY).select("family")
    families = family.join(small.withColumn("whole", F.lit(True)), "family", "left")
    placed = rest.join(families, "rep").withColumn("by_bucket", F.col("whole").isNull())
    placed = placed.select("by_bucket", F.when(F.col("by_bucket"), F.col("bucket")).otherwise(F.col("family")).alias("group"), "rep", "size", "component").distinct()
    placed = stored(placed, "placed")
    sizes = placed.groupBy("by_bucket", "group").agg(F.count("*").alias("n"), F.sum("size").alias("total"))
    blocks = F.greatest(F.ceil(F.col("n") / BLOCK), F.ceil(F.col("total") * 8 / BLOCK_BYTES)).cast("int")
    dealt = placed.join(sizes.withColumn("blocks", blocks).drop("n", "total"), ["by_bucket", "group"])
    dealt = dealt.withColumn("own", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    ids = stored(placed.select(F.col("rep").alias("key")).distinct(), "open-ids")
    sets = texts.join(broadcast_if_small(ids, 16), "key", "left_semi").mapInArrow(released(_sets(seed)), "key long, hashes binary")
    full = dealt.join(sets.withColumnRenamed("key", "rep"), "rep").select(
        "by_bucket", "group", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "rep", "component", "hashes"
    )
    return stored(full.groupBy("by_bucket", "group", "i", "j").applyInPandas(_block_links, "a long, b long"), "block-links")


def _relabelled(links: DataFrame, label: DataFrame) -> DataFrame:
    """Links between components instead of nodes."""
    for c in ("a", "b"):
        links = links.join(label.select(F.col("node").alias(c), F.col("component").alias(f"c{c}")), c, "left").withColumn(f"c{c}", F.coalesce(f"c{c}", c))
    return stored(links.select(F.col("ca").alias("a"), F.col("cb").alias("b")).filter("a <> b").distinct(), "merges")


def _merged(label: DataFrame, found: DataFrame) -> DataFrame:
    """Labels after components themselves have been joined."""
    up = found.select(F.col("node").alias("component"), F.col("component").alias("top"))
    old = label.join(up, "component", "left").select("node", F.coalesce("top", "component").alias("component"))
    return old.union(found.join(label.select("node"), "node", "left_anti"))


def op1_circulant_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
