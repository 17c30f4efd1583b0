"""Candidate pairs from shared keys, and their exact verification in tiles.

Works on classes of equal texts (``sid``), which a key-sorted stream reduces to the keys that
two or more classes share. Pairs are then verified in tiles: one text, the tile's pivot,
against a bounded number of others of like size.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import components
from .shared import arrow_map, discard, small_batches, to_batch, written
from .wordhash import shingle_set

PERCENT = 80
# Elements of the sets that one block holds, about, and classes that meet a block in one part.
ELEMENTS, PART = 1 << 17, 1024
LONG_RUN = 16
SHARED = 8
BLOOM_BITS = 1 << 25


def like_sizes(a: str, b: str):
    """Column: sets of these sizes can reach the similarity."""
    return F.least(a, b) * 100 >= F.greatest(a, b) * PERCENT


def sure_keys(n: str, most: int = SHARED):
    """Column: how many keys a set of this size shares at least with any similar set of no smaller such number."""
    return F.least(F.lit(most), F.ceil(F.col(n) * PERCENT / 100))


def one_key(n: str, most: int = SHARED):
    """Column: the same where a single shared key makes a pair a candidate."""
    return F.lit(1)


def band_of(n: np.ndarray) -> np.ndarray:
    """Sets that can be similar lie in the same size band or in neighbouring ones."""
    return np.floor(np.log(np.maximum(n, 1)) / np.log(100 / PERCENT) + 1e-9).astype(np.int64)


def shared_keys(rows: DataFrame) -> DataFrame:
    """(key, band, sid, n) of the rows (key, sid, n) whose key two or more classes have, each with the first class of its key and band.

    A band holds classes of like size. A stream over rows sorted by key holds one row at a time,
    whatever the length of a key's run.
    """

    def run(batches):
        held = None  # the only row so far of the open key
        last = np.zeros(3, np.int64)  # key, band and sid of the last row
        pivot = np.zeros(2, np.int64)  # sid and n of the open band's first row
        started = False
        for batch in batches:
            key, sid, n = (np.asarray(batch.column(i)).astype(np.int64) for i in range(3))
            if not len(key):
                continue
            band = band_of(n)
            before = [np.concatenate([[last[i]], c[:-1]]) for i, c in enumerate((key, band, sid))]
            new_key = key != before[0]
            new_band = new_key | (band != before[1])
            again = ~new_band & (sid == before[2])
            if not started:
                new_key[0] = new_band[0] = True
                again[0] = False
            started, last = True, np.array([key[-1], band[-1], sid[-1]])
            keep = ~again
            key, band, sid, n, new_key, new_band = (c[keep] for c in (key, band, sid, n, new_key, new_band))
            if not len(key):
                continue
            at = np.maximum.accumulate(np.where(new_band, np.arange(len(key)), -1))
            pivots = np.where(at >= 0, sid[at], pivot[0]), np.where(at >= 0, n[at], pivot[1])
            pivot = np.array([pivots[0][-1], pivots[1][-1]])
            opens = np.flatnonzero(new_key)
            ends = np.append(opens[1:], len(key))
            shared = np.ones(len(key), bool)
            for_one = opens[ends - opens == 1]
            shared[for_one] = False
            columns = [key, band, sid, n, *pivots]
            extra = None
            if held is not None and (not len(opens) or opens[0] > 0):
                extra = held
            if not (len(opens) == 0 and held is None):
                held = None
            if len(opens) and opens[-1] == len(key) - 1:
                held = [c[-1:] for c in columns]
            out = [c[shared] for c in columns]
            if extra is not None:
                out = [np.concatenate([e, c]) for e, c in zip(extra, out)]
            yield to_batch(dict(zip(("key", "band", "sid", "n", "pivot", "pivot_n"), map(pa.array, out))))

    ordered = rows.select("key", "sid", "n").repartition("key").sortWithinPartitions("key", "n", "sid")
    return arrow_map(ordered, run, "key long, band long, sid long, n long, pivot long, pivot_n long")


class Bloom:
    """A set of 64-bit hashes in at most ``BLOOM_BITS`` bits, made by the executors; false positives only cost time."""

    def __init__(self, hashes: DataFrame, column: str):
        size = max(1 << 16, min(BLOOM_BITS, 1 << max(1, 16 * hashes.count() - 1).bit_length()))
        place = F.col(column).bitwiseAND(F.lit(size - 1))
        rows = hashes.select(F.shiftright(place, 6).alias("word"), F.call_function("shiftleft", F.lit(1).cast("long"), place.bitwiseAND(F.lit(63)).cast("int")).alias("bit"))
        got = rows.groupBy("word").agg(F.bit_or("bit").alias("bits")).toArrow()
        words = np.zeros(size // 64, np.int64)
        words[got["word"].to_numpy()] = got["bits"].to_numpy()
        self.mask, self.sent = size - 1, hashes.sparkSession.sparkContext.broadcast(words)

    def holds(self, hashes: np.ndarray) -> np.ndarray:
        place = hashes & self.mask
        return self.sent.value[place >> 6] >> (place & 63) & 1 == 1


def bitmap(values: np.ndarray) -> np.ndarray:
    """One bit for each element by the first bits of its hash, in a width of two to four times the size of the set."""
    width = max(6, (2 * len(values)).bit_length())
    bits = np.zeros(1 << width, bool)
    bits[(values >> np.uint64(64 - width)).astype(np.int64)] = True
    return np.packbits(bits)


def folded(bits: np.ndarray, size: int) -> np.ndarray:
    """The same set's bitmap in fewer bytes: neighbouring bits are joined."""
    while len(bits) > size:
        bits = np.packbits(np.unpackbits(bits).reshape(-1, 2).any(1))
    return bits


def may_be_similar(n: int, bits: np.ndarray, sizes: np.ndarray, table: np.ndarray) -> np.ndarray:
    """For each row of ``table``: whether its set and this one can be similar, by their bitmaps.

    Each bit that only one bitmap has stands for at least one element that only this set has;
    that bounds the intersection from above.
    """
    only_this, only_that = np.bitwise_count(bits & ~table).sum(1, dtype=np.int64), np.bitwise_count(table & ~bits).sum(1, dtype=np.int64)
    return np.minimum(n - only_this, sizes - only_that) >= -(-PERCENT * (n + sizes) // (100 + PERCENT))


def needed_overlap(n: int, m: int) -> int:
    """The least intersection with which sets of these sizes are similar."""
    return -(-PERCENT * (n + m) // (100 + PERCENT))


def common(a: np.ndarray, b: np.ndarray) -> int:
    """Size of the intersection of two sorted arrays, the second not empty."""
    small, large = (a, b) if len(a) <= len(b) else (b, a)
    return int((large[np.minimum(np.searchsorted(large, small), len(large) - 1)] == small).sum())


def similar(a: np.ndarray, b: np.ndarray) -> bool:
    """Exact test of 100 * intersection >= 80 * union on sorted sets."""
    need = needed_overlap(len(a), len(b))
    return min(len(a), len(b)) >= max(need, 1) and common(a, b) >= need


def laid_out(pairs: DataFrame, tiles: DataFrame) -> DataFrame:
    """(tile, part, role, sid, one): a tile's own classes (role 0) and those that meet it, in parts of about ``PART``."""
    parts = pairs.groupBy("tile").agg(F.ceil(F.count("*") / PART).cast("int").alias("parts"))
    members = pairs.join(parts, "tile").select("tile", F.pmod(F.xxhash64("a"), F.col("parts")).cast("int").alias("part"), F.lit(1).alias("role"), F.col("a").alias("sid"), F.lit(True).alias("one"))
    own = tiles.join(parts, "tile").select("tile", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(0).alias("role"), "sid", "one")
    return members.unionAll(own)


def sift(pairs: DataFrame, tiles: DataFrame, signatures: DataFrame) -> DataFrame:
    """The pairs (a, tile) that the bitmaps of (sid, n, bits) do not rule out."""
    rows = laid_out(pairs, tiles).join(signatures.select("sid", "n", "bits"), "sid").select("tile", "part", "role", "sid", "n", "bits")
    dealt = rows.repartition("tile", "part").sortWithinPartitions("tile", "part", "role", "sid")

    def run(batches):
        tile, block = None, Block()
        for batch in small_batches(batches, rows=4096):
            found: tuple[list, list] = ([], [])
            names, parts, roles, sids, sizes, maps = (batch.column(i).to_pylist() for i in range(6))
            for i, raw in enumerate(maps):
                if tile != (names[i], parts[i]):
                    tile, block = (names[i], parts[i]), Block()
                bits = np.frombuffer(raw, np.uint8)
                if roles[i] == 0:
                    block.add(sids[i], sizes[i], bits)
                elif len(block.possible(sids[i], sizes[i], bits)):
                    found[0].append(sids[i])
                    found[1].append(names[i])
            yield to_batch({"a": pa.array(found[0], pa.int64()), "tile": pa.array(found[1], pa.int64())})

    return arrow_map(dealt, run, "a long, tile long").distinct()


class Block:
    """The bitmaps of a tile's own classes, stacked by width as they are first compared with."""

    def __init__(self):
        self.rows: list[tuple[int, int, np.ndarray]] = []
        self.tables: dict[int, list] = {}

    def add(self, sid: int, n: int, bits: np.ndarray) -> None:
        self.rows.append((sid, n, bits))
        self.tables.clear()

    def possible(self, sid: int, n: int, bits: np.ndarray) -> np.ndarray:
        """The places of the classes, other than ``sid``, that the bitmaps do not rule out."""
        if len(bits) not in self.tables:
            by_width: dict[int, list[int]] = {}
            for i, row in enumerate(self.rows):
                by_width.setdefault(min(len(bits), len(row[2])), []).append(i)
            self.tables[len(bits)] = [(w, np.array(at), np.array([self.rows[i][0] for i in at]), np.array([self.rows[i][1] for i in at]), np.stack([folded(self.rows[i][2], w) for i in at])) for w, at in by_width.items()]
        found = [at[may_be_similar(n, folded(bits, w), sizes, table) & (ids != sid)] for w, at, ids, sizes, table in self.tables[len(bits)]]
        return np.sort(np.concatenate(found)) if found else np.zeros(0, np.int64)


def verify(pairs: DataFrame, tiles: DataFrame, owners: DataFrame, texts: Callable[[Bloom], DataFrame]) -> DataFrame:
    """Links (a, b) of classes a to a member b of the tile that ``pairs`` (a, tile) names, where the sets are similar.

    ``tiles`` (tile, sid, one) lists the tiles' own classes. Where ``one`` is true they are one
    pivot, or a block of one component, of which one link is as good as all. ``owners`` has sid, ``doc`` and ``where``, hashes that
    name the document and the place of the class's text; ``texts`` gives (sid, text) for the
    places in a Bloom filter.
    """
    needed = written(pairs.select(F.col("a").alias("sid")).unionAll(tiles.select("sid")).distinct().join(owners.select("sid", "doc", "where"), "sid"), "needed")
    bloom = Bloom(needed.select("where").unionAll(needed.select("doc")), "where")
    discard(needed)
    rows = laid_out(pairs, tiles).join(texts(bloom), "sid").select("tile", "part", "role", "sid", "one", "text")
    dealt = rows.repartition("tile", "part").sortWithinPartitions("tile", "part", "role", "sid")

    def run(batches):
        tile = last = union = None
        one = True
        block, sets = Block(), []
        for batch in small_batches(batches):
            found: tuple[list, list] = ([], [])
            names, parts, roles, sids, ones = (batch.column(i).to_pylist() for i in range(5))
            for i, text in enumerate(batch.column(5).to_pylist()):
                at = (names[i], parts[i], roles[i], sids[i])
                if at == last:
                    continue
                last = at
                values = shingle_set(text)
                if tile != at[:2]:
                    tile, union, block, sets = at[:2], None, Block(), []
                if roles[i] == 0:
                    one = ones[i]
                    block.add(sids[i], len(values), bitmap(values))
                    sets.append(values)
                    continue
                if len(sets) > 1:
                    union = np.unique(np.concatenate(sets)) if union is None else union
                    if common(values, union) < needed_overlap(len(values), max(min(map(len, sets)), -(-PERCENT * len(values) // 100))):
                        continue
                for k in block.possible(sids[i], len(values), bitmap(values)).tolist():
                    if similar(values, sets[k]):
                        found[0].append(sids[i])
                        found[1].append(block.rows[k][0])
                        if one:
                            break
            yield to_batch({"a": pa.array(found[0], pa.int64()), "b": pa.array(found[1], pa.int64())})

    return arrow_map(dealt, run, "a long, b long")


def single(pairs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Pairs (a, b) as pairs with tiles of one pivot each."""
    return pairs.select("a", F.col("b").alias("tile")), pairs.select(F.col("b").alias("tile"), F.col("b").alias("sid"), F.lit(True).alias("one")).distinct()


def mixed_rows(keys: DataFrame, roots: DataFrame) -> DataFrame:
    """A written table of the rows of keys that hold two or more components, with the component and its size, and the key's least and last band."""
    sized = roots.join(roots.groupBy("root").agg(F.count("*").alias("size")), "root").select(F.col("id").alias("sid"), "root", "size")
    marked = keys.join(sized, "sid", "left").withColumn("root", F.coalesce("root", "sid")).withColumn("size", F.coalesce("size", F.lit(1).cast("long")))
    mixed = marked.groupBy("key").agg(F.min("root").alias("r0"), F.max("root").alias("r1"), F.count("*").alias("run"), F.sum("n").alias("weight"), F.min("band").alias("from_band"), F.max("band").alias("to_band")).where("r0 <> r1").drop("r0", "r1")
    return written(marked.join(mixed, "key").select("key", "run", "weight", "band", "from_band", "to_band", "sid", "n", "root", "size"), "mixed")


def near_bands(rows: DataFrame) -> DataFrame:
    """(key, a, n, ar, as, band): each row once for its band and each neighbouring one, within those that its key has at all."""
    bands = F.sequence(F.greatest(F.col("band") - 1, "from_band"), F.least(F.col("band") + 1, "to_band"))
    return rows.select("key", F.col("sid").alias("a"), "n", F.col("root").alias("ar"), F.col("size").alias("as"), F.explode(bands).alias("band"))


def other_pivots(rows: DataFrame, seed: int) -> DataFrame:
    """Pairs (a, b) of the classes with a pivot of another component in their key and band."""
    by = F.struct(F.xxhash64("sid", F.lit(seed)).alias("o"), "sid", "n", "root")
    ends = rows.groupBy("key", "band").agg(F.min(by).alias("x"), F.max(by).alias("y")).where("x.root <> y.root")
    chosen = rows.join(ends, ["key", "band"]).select("sid", "n", F.when(F.col("root") != F.col("x.root"), F.col("x")).otherwise(F.col("y")).alias("z"))
    return chosen.select(F.col("sid").alias("a"), F.col("z.sid").alias("b"), F.col("n").alias("an"), F.col("z.n").alias("bn")).where(like_sizes("an", "bn")).select("a", "b").distinct()


def cross_tiles(rows: DataFrame, sure: Callable = sure_keys) -> tuple[DataFrame, DataFrame]:
    """(a, tile) for all classes and blocks of other components of like size that share enough keys, and the tiles.

    A block is classes of one component with up to about ``ELEMENTS`` elements, so two large components
    of near copies meet block by block; the class comes from the smaller of the two components.
    Classes still alone form blocks by the longest run of keys that they are in.
    """
    top = rows.groupBy("sid").agg(F.max(F.struct("run", "key", "weight")).alias("top"))
    alone = F.col("size") == 1
    elements, label = F.when(alone, F.col("top.weight")).otherwise(F.col("size") * F.col("n")), F.when(alone, F.col("top.key")).otherwise(F.col("root"))
    marked = rows.join(top, "sid").withColumn("tile", F.xxhash64(alone, label, F.pmod(F.xxhash64("sid"), F.ceil(elements / ELEMENTS)))).withColumn("one", ~alone)
    blocks = marked.groupBy("key", "band", "tile", "one", "size", F.when(~alone, F.col("root")).alias("root")).agg(F.min("n").alias("least"), F.max("n").alias("most"), F.min("sid").alias("low"), F.max("sid").alias("high"))
    smaller = (F.col("as") < F.col("size")) | ((F.col("as") == F.col("size")) & (F.col("ar") < F.col("root")))
    singles = ~F.col("one") & (F.col("as") == 1) & ((F.col("low") != F.col("a")) | (F.col("high") != F.col("a")))
    fits = (F.col("n") * 100 >= F.col("least") * PERCENT) & (F.col("most") * 100 >= F.col("n") * PERCENT)
    pairs = near_bands(rows).join(blocks, ["key", "band"]).where(fits & (singles | (F.col("one") & smaller & (F.col("ar") != F.col("root")))))
    enough = F.count("*") >= F.min(F.least(sure("n"), sure("least")))
    pairs = pairs.groupBy("a", "tile").agg(enough.alias("enough")).where("enough").select("a", "tile")
    return pairs, marked.select("tile", "sid", "one").distinct()


def linked_classes(keys: DataFrame, owners: DataFrame, texts: Callable[[Bloom], DataFrame], rounds: int = 1, sure: Callable = sure_keys) -> DataFrame:
    """(id, root) of the classes joined by similarity, from a written table of :func:`shared_keys`.

    First every class meets the pivot of each of its keys; then, for some rounds, those in
    long runs meet pivots of other components; last, all that still lie in different
    components meet. By then a group of near copies is one component, so it yields few pairs.
    ``sure`` tells how many keys similar classes of a size share at least.
    """

    def grown(roots: DataFrame | None, pairs: DataFrame, tiles: DataFrame) -> DataFrame | None:
        if pairs.isEmpty():
            return roots
        sifted = written(sift(pairs, tiles, owners), "sifted")
        links = None
        if not sifted.isEmpty():
            links = written(verify(sifted, tiles.join(sifted.select("tile").distinct(), "tile", "left_semi"), owners, texts), "links")
        discard(sifted)
        if links is None or (links.isEmpty() and roots is not None):
            return roots
        both = links if roots is None else links.unionAll(roots.select(F.col("id").alias("a"), F.col("root").alias("b")))
        more = components(both)
        discard(links, roots)
        return more

    met = keys.where("sid <> pivot").where(like_sizes("n", "pivot_n")).groupBy(F.col("sid").alias("a"), F.col("pivot").alias("b"))
    pairs = met.agg(F.count("*").alias("times"), F.min(F.least(sure("n", 2), sure("pivot_n", 2))).alias("least")).where("times >= least").select("a", "b")
    start = keys.sparkSession.createDataFrame([], "id long, root long")
    pairs = written(pairs, "pairs")
    roots = grown(None, *single(pairs)) or start
    discard(pairs)
    long_runs = keys.groupBy("key").agg(F.count("*").alias("run")).where(F.col("run") > LONG_RUN).select("key")
    for r in range(rounds):
        rows = mixed_rows(keys.join(long_runs, "key", "left_semi"), roots)
        pairs = written(other_pivots(rows, r), "pairs")
        roots = grown(roots, *single(pairs))
        discard(rows, pairs)
    rows = mixed_rows(keys, roots)
    pairs, tiles = cross_tiles(rows, sure)
    pairs = written(pairs, "pairs")
    roots = grown(roots, pairs, tiles)
    discard(rows, pairs)
    discard(keys)
    return roots
