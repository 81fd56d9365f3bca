"""SimHash near-duplicates with covering locality-sensitive hashing.

Every text gets a 64-bit fingerprint (majority of its shingles' hash bits).
For a radius r, each of the 64 positions draws a vector of r+1 bits; for every
non-zero vector v a mask drops the positions whose vector is orthogonal to v.
At most r differing positions span at most r dimensions, so some v is
orthogonal to all of them: each pair within the radius agrees on all kept bits
of one of the 2^(r+1)-1 masks. No pair is missed.

Null and empty texts have no word: fingerprint zero. Repeated rows and ties
give equal fingerprints and fall into one class; an empty table gives no row;
further columns of the input are not looked at.
"""

from __future__ import annotations

import random
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tiersort.llm.common import components, discard, least_joined, staged, with_least

BITS = 64
_LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))


def shingle_hashes(text: str | None, size: int) -> np.ndarray:
    """XXH64 (seed 42) of the word shingles of a text, repeats included."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()
    if not words:
        return np.zeros(0, np.uint64)
    joined, digest = b" ".join(words), xxhash.xxh64_intdigest
    ends = np.cumsum([len(w) + 1 for w in words]).tolist()
    n = max(1, len(words) - size + 1)
    last = ends[min(size, len(words)) - 1:]
    starts = [0, *ends]
    return np.fromiter((digest(joined[a:b - 1], 42) for a, b in zip(starts, last)), np.uint64, n)


def fingerprint(hashes: np.ndarray) -> int:
    """Majority bit of the hashes at each position (none: zero)."""
    if not len(hashes):
        return 0
    ones = np.zeros(BITS, np.int64)
    for at in range(0, len(hashes), 1 << 16):
        part = hashes[at:at + (1 << 16)].astype(">u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(part, axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(ones * 2 > len(hashes)).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """Rows (id, fp): the fingerprint as a signed long with the same bits."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.fromiter((fingerprint(shingle_hashes(t.as_py(), shingle)) for t in b.column(1)), np.uint64, b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps.view(np.int64))], names=["id", "fp"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"id {kind}, fp long")


def covering_masks(radius: int, seed: int = 7) -> list[int]:
    """2^(radius+1)-1 masks of 64 bits such that any ``radius`` positions are outside of one of them."""
    rng = random.Random(seed)
    width = radius + 1
    vectors = [1 + i % ((1 << width) - 1) for i in range(BITS)]  # as even as can be; zero would be kept by none
    rng.shuffle(vectors)
    return [sum(1 << i for i, m in enumerate(vectors) if (m & v).bit_count() % 2) for v in range(1, 1 << width)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def links(fps: DataFrame, radius: int = 2, pairwise: int = 24, seed: int = 7) -> DataFrame:
    """Edges (u, v) between distinct fingerprints, with the components of the radius.

    ``fps`` has one column ``fp``. Buckets of up to ``pairwise`` fingerprints
    are compared pair by pair. Larger ones never are: for a radius of 2 each
    member stands for itself and for its neighbours with one flipped bit
    outside of the mask; two fingerprints share such a neighbour just if they
    differ in at most 2 bits, and everybody at a neighbour is linked to the
    smallest one there. That is exact and linear in the bucket, whatever its size.
    """
    if radius != 2:
        raise ValueError("the exact way for large buckets is built for radius 2")
    masks = covering_masks(radius, seed)
    entry = F.array(*[F.struct(F.lit(i).alias("t"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("key"))
                      for i, m in enumerate(masks)])
    rows = fps.distinct().select("fp", F.explode(entry).alias("e")).select("fp", "e.t", "e.key")
    sizes = rows.groupBy("t", "key").agg(F.count("*").alias("n"), F.min("fp").alias("low")).where("n > 1")
    # low: the bucket's smallest fingerprint; of two members one at least isn't it
    held = staged(rows.join(sizes, ["t", "key"]), "buckets")
    small = held.where(F.col("n") <= pairwise)
    group = small.groupBy("t", "key").agg(F.sort_array(F.collect_list("fp")).alias("all"))
    pair = (group.select(F.posexplode("all").alias("i", "u"), "all")
            .select("u", F.explode(F.expr("slice(all, i + 2, size(all))")).alias("v"))
            .where(F.bit_count(F.col("u").bitwiseXOR(F.col("v"))) <= radius))
    flips = F.array(*[F.lit(_signed(1 << i)) for i in range(BITS)])
    kept = F.element_at(F.array(*[F.lit(_signed(m)) for m in masks]), F.col("t") + 1)
    near = F.concat(F.array(F.lit(0).cast("long")), F.filter(flips, lambda x: x.bitwiseAND(kept) == 0))
    star = held.where(F.col("n") > pairwise).select("fp", "t", F.explode(near).alias("x")).select(
        "fp", F.col("fp").bitwiseXOR(F.col("x")).alias("at")).distinct()
    centre = star.groupBy("at").agg(F.min("fp").alias("low"), F.count("*").alias("n")).where("n > 1")
    spoke = star.join(centre, "at").where("fp <> low").select(F.col("fp").alias("u"), F.col("low").alias("v"))
    return pair.unionByName(spoke).distinct()


def classes(fps: DataFrame, radius: int = 2) -> DataFrame:
    """Rows (id, fp, component) for rows (id, fp): linked fingerprints share the smallest id."""
    first = fps.groupBy("fp").agg(F.min("id").alias("first"))
    first = staged(first, "distinct")
    joined = components(links(first.select("fp"), radius))
    by_fp = first.join(joined.withColumnRenamed("id", "fp"), "fp", "left").select(
        "fp", "first", F.coalesce("component", "fp").alias("root"))
    low = by_fp.groupBy("root").agg(F.min("first").alias("component"))
    return fps.join(by_fp.join(low, "root").select("fp", "component"), "fp").select("id", "fp", "component")


def hex_of(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def sketches(docs: DataFrame, text_col: str, shingle: int, bands: int, rows: int, seed: int = 11) -> DataFrame:
    """Rows (h1, h2, fp, keys, bits, shingles) for every row of ``docs``.

    ``h1`` and ``h2`` (96 bits) name the text, ``keys`` has a 64-bit key for
    each band of minima, ``bits`` the last bit of each minimum (packed into
    longs), ``shingles`` the distinct hashes of its shingles. Texts without a
    word have none of these.
    """
    rng = np.random.default_rng(seed)
    mul = rng.integers(0, 1 << 32, (bands * rows, 1), np.uint64).astype(np.uint32) | np.uint32(1)
    add = rng.integers(0, 1 << 32, (bands * rows, 1), np.uint64).astype(np.uint32)

    def keys(h: np.ndarray) -> tuple[list[int], list[int]]:
        low = np.full(bands * rows, 0xFFFFFFFF, np.uint32)
        small = np.unique(((h ^ (h >> np.uint64(29))) & np.uint64(0xFFFFFFFF)).astype(np.uint32))
        for at in range(0, len(small), 4096):
            x = small[at:at + 4096] * mul + add
            low = np.minimum(low, (x ^ (x >> np.uint32(15))).min(1))
        last = np.zeros(-(-bands * rows // BITS) * BITS, np.uint8)
        last[:bands * rows] = low & np.uint32(1)
        return [xxhash.xxh64_intdigest(low[i * rows:(i + 1) * rows].tobytes(), i) - (1 << 63) for i in range(bands)], np.packbits(last).view(np.int64).tolist()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        longs = pa.list_(pa.int64())
        for b in batches:
            out, fps, held, bits = [], [], [], []
            for t in b.column(2):
                h = shingle_hashes(t.as_py(), shingle)
                fps.append(_signed(fingerprint(h)))
                held.append(np.unique(h).view(np.int64))
                band, last = keys(held[-1].view(np.uint64)) if len(h) else ([], [])
                out.append(band)
                bits.append(last)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(fps, pa.int64()), pa.array(out, longs), pa.array(bits, longs), pa.array(held, longs)],
                                             names=["h1", "h2", "fp", "keys", "bits", "shingles"])

    h1, h2 = text_key(text_col)
    return docs.select(h1.alias("h1"), h2.alias("h2"), text_col).mapInArrow(run, "h1 long, h2 int, fp long, keys array<long>, bits array<long>, shingles array<long>")


def text_key(text_col: str) -> tuple[Column, Column]:
    """A text's name in 96 bits; null is the empty text."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    return F.xxhash64(text), F.hash(F.reverse(text))


def bits_apart(a: str, b: str) -> Column:
    """Number of positions in which two packed bit vectors differ."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)


def most_apart(minima: int, tenths: int) -> int:
    """Last bits of minima in which texts of ``tenths`` / 10 differ, but for two of a million such pairs (4.6 standard deviations above the mean)."""
    share = (1 - tenths / 10) / 2
    return int(minima * share + 4.6 * (minima * share * (1 - share)) ** 0.5)


def similar(pairs: DataFrame, facts: DataFrame, shingles: DataFrame, tenths: int, apart: int, most_broadcast: int = 500_000) -> DataFrame:
    """Those of ``pairs`` (u, v) whose sets, rows (id, n, shingles), have a Jaccard similarity of ``tenths`` / 10 or more, exactly.

    Pairs that sizes or last bits (``facts``) rule out are not looked up.
    """
    a, b = (facts.select(F.col("id").alias(x), F.col("n").alias(f"n{x}"), F.col("bits").alias(f"b{x}")) for x in "uv")
    fits = (10 * F.least("nu", "nv") >= tenths * F.greatest("nu", "nv")) & (bits_apart("bu", "bv") <= apart)
    pairs = staged(pairs.distinct().join(a, "u").join(b, "v").where(fits).select("u", "v"), "pairs")
    asked = pairs.select(F.col("u").alias("id")).unionByName(pairs.select(F.col("v").alias("id"))).distinct()
    few = 2 * pairs.count() <= most_broadcast
    sets = shingles.join(F.broadcast(asked) if few else asked, "id", "left_semi")
    both = pairs.join(sets.toDF("u", "nu", "su"), "u").join(sets.toDF("v", "nv", "sv"), "v")
    shared = F.size(F.array_intersect("su", "sv"))
    return both.where(10 * shared >= tenths * (F.col("nu") + F.col("nv") - shared)).select("u", "v")


def alike(tenths: int) -> Callable[[pa.Table], pa.Table]:
    """For ``applyInArrow``: links of a table (a, b, id, block, shingles) between its blocks a and b, in full, as a forest (u, v).

    Intersections are counted exactly by products of 0/1 matrices, in bounded
    pieces, over the shingles that two sets at least hold. Of the links found,
    those of each member to the smallest it reaches leave: a row a member at most.
    """
    def run(t: pa.Table) -> pa.Table:
        ids, block, held = t["id"].to_numpy(), t["block"].to_numpy(), t["shingles"].combine_chunks()
        n = held.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
        _, code, many = np.unique(held.flatten().to_numpy(), return_inverse=True, return_counts=True)
        common = many[code] > 1
        owner, code = np.repeat(np.arange(len(ids)), n)[common], (np.cumsum(many > 1) - 1)[code[common]]
        order = np.argsort(code, kind="stable")
        owner, code = owner[order], code[order]
        left, right = (np.flatnonzero(block == t[x][0].as_py()) for x in "ab")
        low, width, step = np.arange(len(ids)), max(1, (1 << 22) // len(ids)), max(1, (1 << 22) // max(1, len(right)))
        cuts = np.searchsorted(code, np.arange(0, code[-1] + width + 1, width)).tolist() if len(code) else []
        for at in range(0, len(left), step):
            mine = left[at:at + step]
            shared = np.zeros((len(mine), len(right)), np.float32)
            for k, (lo, hi) in enumerate(zip(cuts, cuts[1:])):
                has = np.zeros((len(ids), width if hi < len(code) else int(code[-1]) - k * width + 1), np.float32)
                has[owner[lo:hi], code[lo:hi] - k * width] = 1
                shared += has[mine] @ has[right].T
            i, j = np.nonzero(10 * shared >= tenths * (n[mine][:, None] + n[right][None, :] - shared))
            low = least_joined(len(ids), np.concatenate([np.arange(len(ids)), mine[i]]), np.concatenate([low, right[j]]))
        tied = np.flatnonzero(low != np.arange(len(ids)))
        return pa.table({"u": ids[tied], "v": ids[low[tied]]})

    return run


#: Edges that the driver joins as arrays (16 bytes each), rows that are broadcast, members of a block and blocks of a group at most.
FEW_EDGES, MOST_SENT, BLOCK, BLOCKS = 200_000, 500_000, 128, 32


def near_texts(docs: DataFrame, text_col: str = "text", shingle: int = 5, bands: int = 40, rows: int = 6, radius: int = 2, tenths: int = 8,
               most: int = 10_000, few: int = FEW_EDGES) -> DataFrame:
    """Rows (h1, h2, class), one for each distinct text; a class is a number without further meaning.

    Two texts are linked if they share ``tenths`` / 10 or more of their
    distinct shingles. Candidates have an equal band of minima (40 bands of 6:
    five of a million pairs at 0.8 have none) or equal or linked fingerprints
    (within ``radius`` bits); each link is checked on the whole sets. What
    candidates join falls into groups, each text in one. In a group of up to
    ``most`` texts all are held against all, in pairs of blocks, so a text's
    set moves once for each block of its group; links leave as a forest.
    Larger groups are taken apart: each text is held against the first of its
    bands (what last bits of minima rule out, two of a million links, aside),
    and bands that still have several components are compared in blocks.
    """
    raw = sketches(docs, text_col, shingle, bands, rows).withColumn("id", F.monotonically_increasing_id())
    sketch = staged(raw, "sketch")  # written once, so the numbers stay
    first = staged(sketch.groupBy("h1", "h2").agg(F.min("id").alias("id")), "texts")
    own = sketch.select("id", F.size("shingles").alias("n"), "bits", "fp", "keys").join(first.select("id"), "id", "left_semi").where("n > 0")
    own, n = staged(own, "own"), first.count()
    close = links(own.select("fp"), radius).select(F.xxhash64("u", "v").alias("key"), F.explode(F.array("u", "v")).alias("fp"))
    shared = own.select(F.explode(F.concat("keys", F.array(F.xxhash64("fp")))).alias("key"), "id").unionByName(
        close.join(own.select("fp", "id"), "fp").select("key", "id"))
    held = staged(with_least(shared, "key", "id", (bands + 1) * n, "low", alone=False), "bands")

    def sized(found: DataFrame, group: str) -> DataFrame:
        """``found`` with the number m of its group's rows, where that is over a block."""
        return found.join(F.broadcast(found.groupBy(group).agg(F.count("*").alias("m")).where(F.col("m") > BLOCK)), group, "left")

    joined = components(held.where("id <> low").select(F.col("id").alias("u"), F.col("low").alias("v")), few=few)
    groups = staged(sized(joined, "component").select("id", F.col("component").alias("unit"), "m"), "groups")
    units, stars = groups.where(f"m is null or m <= {most}"), None
    if groups.where(f"m > {most}").limit(1).count():
        mine = held.join(groups.where(f"m > {most}").select("id"), "id", "left_semi")
        tried = mine.where("id <> low").select(F.col("id").alias("u"), F.col("low").alias("v"))
        stars = staged(similar(tried, own, sketch.select("id", F.size("shingles").alias("n"), "shingles"), tenths, most_apart(bands * rows, tenths)), "stars")
        placed = mine.select("id", "key").join(components(stars, few=few), "id", "left").withColumn("c", F.coalesce("component", "id"))
        same = [F.bit_xor(F.xxhash64("id", F.lit(k))).alias(f"x{k}") for k in (0, 1)]  # bands of the same members are compared once
        some = placed.groupBy("key").agg(F.min("c").alias("a"), F.max("c").alias("b"), F.count("*").alias("m"), *same).where("a < b").dropDuplicates(["m", "x0", "x1"])
        units = staged(units.unionByName(placed.join(some.select("key", "m"), "key").select("id", F.col("key").alias("unit"), "m")), "units")
    parts = F.least(F.lit(BLOCKS), F.ceil(F.coalesce("m", F.lit(1)) / BLOCK)).cast("int")
    units = units.select("id", "unit", parts.alias("parts"), F.pmod(F.xxhash64("id"), parts).cast("int").alias("block"))
    sets = sketch.select("id", "shingles").join(F.broadcast(units) if units.count() <= MOST_SENT else units, "id")
    dealt = sets.withColumn("other", F.explode(F.expr("sequence(0, parts - 1)"))).select(
        "unit", F.least("block", "other").alias("a"), F.greatest("block", "other").alias("b"), "id", "block", "shingles")
    edges = staged(dealt.groupBy("unit", "a", "b").applyInArrow(alike(tenths), "u long, v long"), "links")
    found = components(edges if stars is None else edges.unionByName(stars), few=few)
    for done in (sketch, own, held, groups, edges):
        discard(done)
    return first.join(found, "id", "left").select("h1", "h2", F.coalesce("component", "id").alias("class"))


def near_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """Rows (id, component), one for each row of ``docs``: rows of a class of ``near_texts`` share its smallest id."""
    h1, h2 = text_key(text_col)
    found = near_texts(docs, text_col, **options)
    named = staged(docs.select(F.col(id_col).alias("id"), h1.alias("h1"), h2.alias("h2")).join(found, ["h1", "h2"]).select("id", "class"), "classes")
    return named.join(named.groupBy("class").agg(F.min("id").alias("component")), "class").select("id", "component")
