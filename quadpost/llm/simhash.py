"""SimHash near-duplicate classes by tiled exact comparison.

A fingerprint bit is set where over half of the shingles' hashes have it. Distinct
fingerprints are laid out in tiles by the population counts of their four
16-bit parts. Two fingerprints within the radius differ by at most the radius in
the sum of those counts' differences, so tile pairs beyond it are skipped and
all other pairs are compared whole: exclusive-or and bit counts in numpy.
A task keeps only a spanning forest of the links it finds; components join them.

Defined cases: a null, empty or blank text has no shingle and fingerprint zero,
which links like any other; fewer words than a shingle has make one shingle of
all words; repeated rows give as many rows with one class; a class is named by
its least non-null doc_id; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import product

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from quadpost.llm.components import stars
from quadpost.llm.staging import shuffle_parts, written

SHINGLE, SEED, RADIUS = 3, 42, 2
PARTS, PART_BITS = 4, 16
#: Fingerprints of a tile that one task's block holds; larger tiles are cut into blocks.
BLOCK = 4096
#: Links that a task holds before it reduces them to a forest.
HELD_LINKS = 200_000


def shingle_hashes(text: str | None, shingle: int) -> np.ndarray:
    """The unsigned XXH64 of every shingle of the text, repeats included."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    digest = xxhash.xxh64_intdigest
    joined = b" ".join(words)
    if len(words) <= shingle:
        return np.array([digest(joined, SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = np.concatenate([[0], ends[:-1]])[: len(words) - shingle + 1].tolist()
    stops = (ends[shingle - 1 :] - 1).tolist()
    return np.fromiter((digest(joined[a:b], SEED) for a, b in zip(starts, stops, strict=True)), np.uint64, len(starts))


def majority(hashed: np.ndarray, even: bool = False) -> int:
    """The bits that over half of the hashes have; zero of none. ``even``: a tied bit is the least hash's, so that few shingles do not mean few bits."""
    votes = np.zeros(64, np.int64)
    for i in range(0, len(hashed), 8192):
        votes += np.unpackbits(hashed[i : i + 8192].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = 2 * votes > len(hashed)
    if even and len(hashed):
        bits |= (2 * votes == len(hashed)) & np.unpackbits(hashed.min(keepdims=True).view(np.uint8), bitorder="little").astype(bool)
    return int(np.packbits(bits, bitorder="little").view("<u8")[0])


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    """The unsigned 64-bit fingerprint."""
    return majority(shingle_hashes(text, shingle))


def _fingerprints(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            marks = np.array([fingerprint(t.as_py(), shingle) for t in batch.column(1)], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(marks, pa.int64())], ["doc_id", "fp"])

    return run


def fingerprints(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """(doc_id, fp): the fingerprint's bits as a signed long."""
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(_fingerprints(shingle), "doc_id long, fp long")


def _part_counts(fp: Column) -> list[Column]:
    return [F.bit_count(F.shiftrightunsigned(fp, PART_BITS * k).bitwiseAND(F.lit((1 << PART_BITS) - 1))) for k in range(PARTS)]


def _tile(counts: list[Column]) -> Column:
    out = F.lit(0)
    for c in counts:
        out = out * (PART_BITS + 1) + c
    return out.cast("int")


def _steps(radius: int) -> list[int]:
    """Differences of tile numbers, the positive half and zero, that the radius allows (a superset at the edges)."""
    found = set()
    for d in product(range(-radius, radius + 1), repeat=PARTS):
        if sum(map(abs, d)) <= radius and d >= (0,) * PARTS:
            n = 0
            for x in d:
                n = n * (PART_BITS + 1) + x
            found.add(n)
    return sorted(found)


class Forest:
    """Union-find over fingerprints; ``edges`` gives what joins each of them to its root."""

    def __init__(self):
        self.up: dict[int, int] = {}

    def root(self, x: int) -> int:
        up = self.up
        while (y := up.get(x, x)) != x:
            up[x] = up.get(y, y)
            x = y
        return x

    def join(self, a: np.ndarray, b: np.ndarray) -> None:
        for x, y in zip(a.tolist(), b.tolist(), strict=True):
            x, y = self.root(x), self.root(y)
            if x != y:
                self.up[max(x, y)] = min(x, y)

    def edges(self) -> pa.RecordBatch:
        rows = [(x, r) for x in list(self.up) if (r := self.root(x)) != x]
        u, v = zip(*rows, strict=True) if rows else ((), ())
        self.up = {}
        return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])


def _compare(radius: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forest = Forest()
        for batch in batches:
            for i in range(batch.num_rows):
                a, b = (batch.column(k)[i].values.to_numpy(zero_copy_only=False) for k in (0, 1))
                step = max(1, (1 << 20) // max(1, len(b)))
                for at in range(0, len(a), step):
                    part = a[at : at + step]
                    x, y = np.nonzero(np.bitwise_count(part[:, None].view(np.uint64) ^ b[None, :].view(np.uint64)) <= radius)
                    apart = part[x] != b[y]
                    forest.join(part[x[apart]], b[y[apart]])
                    if len(forest.up) >= HELD_LINKS:
                        yield forest.edges()
        if forest.up:
            yield forest.edges()

    return run


def links(distinct: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Edges (u, v) between the distinct fingerprints of column ``fp``: a forest of each task's links within the radius."""
    tiled = distinct.select("fp", _tile(_part_counts(F.col("fp"))).alias("tile"))
    sizes = tiled.groupBy("tile").count()  # at most 17^4 rows, whatever the input
    blocked = tiled.join(F.broadcast(sizes), "tile").select("fp", "tile", F.pmod(F.xxhash64("fp"), F.ceil(F.col("count") / BLOCK)).cast("int").alias("block"))
    tiles = blocked.groupBy("tile", "block").agg(F.collect_list("fp").alias("fps"))
    ask = tiles.select(F.col("tile").alias("own"), F.col("block").alias("own_block"), F.col("fps").alias("left"), F.explode(F.array(*[F.col("tile") + s for s in _steps(radius)])).alias("tile"))
    pairs = ask.join(tiles, "tile").where((F.col("own") != F.col("tile")) | (F.col("own_block") <= F.col("block")))
    return pairs.select("left", "fps").mapInArrow(_compare(radius), "u long, v long")


def classes(docs: DataFrame, shingle: int = SHINGLE, radius: int = RADIUS) -> DataFrame:
    """(doc_id, fp, component_id) for every row of (doc_id, text)."""
    marks = written(fingerprints(docs, shingle), "fingerprints")
    least = marks.groupBy("fp").agg(F.min("doc_id").alias("least"))
    roots = stars(links(least, radius))
    rooted = least.join(roots, F.col("fp") == F.col("node"), "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    named = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    return marks.join(rooted.select("fp", "root").join(named, "root").drop("root"), "fp").select("doc_id", "fp", "component_id")


# --- wide fingerprints: near copies by similarity ---------------------------------------------------------------------

#: Two texts are near copies from this Jaccard similarity of their sets of five-word shingles on. At 0.8 the cosine
#: is 0.889 at least, and the fingerprints differ in arccos(0.889) / pi of their bits, 19.3 of 128 on average with a
#: deviation of 4 (24 for sets of four and five shingles). Unrelated texts differ in 64 with a deviation of 5.7.
#: Fingerprints within the radius are candidates only; the sets themselves are compared before two texts are linked.
SIMILARITY = 0.8
WIDE_SHINGLE, WIDE_RADIUS = 5, 40
#: Tiles hold sets that agree in one of so many bands of so many least hashes: at 0.8 two sets miss each other with
#: (1 - 0.8^4)^16 = 2 in 10,000, at 0.3 they meet with 13 in 100, at 0.1 with 2 in 1000.
BANDS, BAND_ROWS = 16, 4
#: Sets of one tile that a block holds; every pair of blocks of a tile is one comparison.
BAND_BLOCK = 8192
#: Sets, and shingles of all sets, that one block of a candidate class holds; every pair of blocks is one task.
CHECKED, CHECKED_SHINGLES = 1024, 1 << 21
_TILE = 1024
#: Groups of up to so many sets are compared together with others of their batch, and rows that are read before comparing.
_SMALL_GROUP, _HELD_ROWS = 64, 1 << 16
_MASKS, _ODDS = np.random.default_rng(29).integers(0, 1 << 32, (2, BANDS * BAND_ROWS), np.uint32) | np.array([[0], [1]], np.uint32)


def _second(hashed: np.ndarray) -> np.ndarray:
    """Hashes for the second 64 bits from those for the first, by the multipliers of the public splitmix64 generator."""
    x = (hashed ^ (hashed >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(32))


def shingle_set(text: str | None, shingle: int = WIDE_SHINGLE) -> np.ndarray:
    """The distinct shingle hashes, ascending."""
    return np.unique(shingle_hashes(text, shingle))


def wide_fingerprint(text: str | None, shingle: int = WIDE_SHINGLE) -> tuple[int, int]:
    """Of distinct shingles, as the similarity is."""
    found = shingle_set(text, shingle)
    return majority(found, True), majority(_second(found), True)


def band_keys(found: np.ndarray) -> np.ndarray:
    """One key per band from the least hashes of the set under BANDS * BAND_ROWS orders."""
    least = np.full(BANDS * BAND_ROWS, 0xFFFFFFFF, np.uint32)
    short = (found ^ (found >> np.uint64(32))).astype(np.uint32)
    for i in range(0, len(short), 512):
        least = np.minimum(least, ((short[i : i + 512, None] ^ _MASKS) * _ODDS).min(axis=0))
    halves = least.view(np.uint64).reshape(BANDS, -1)
    keys = np.zeros(BANDS, np.uint64)
    for half in halves.T:
        keys = _second(keys ^ half)
    return keys.view(np.int64)


def alike(a: np.ndarray, b: np.ndarray, similarity: float = SIMILARITY) -> bool:
    """Whether two sets of ascending distinct hashes reach the Jaccard similarity."""
    few, many = sorted((len(a), len(b)))
    if few < similarity * many:
        return False
    both = np.concatenate([a, b])
    both.sort(kind="stable")
    common = int(np.count_nonzero(both[1:] == both[:-1]))
    return common >= similarity * (few + many - common)


def _wide(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            marks, keys = np.zeros((batch.num_rows, 4), np.uint64), np.zeros((batch.num_rows, BANDS), np.int64)
            for i, t in enumerate(batch.column(2)):
                found = shingle_set(t.as_py(), shingle)
                marks[i] = majority(found, True), majority(_second(found), True), xxhash.xxh64_intdigest(found.tobytes(), SEED), len(found)
                keys[i] = band_keys(found)
            bands = pa.ListArray.from_arrays(pa.array(np.arange(batch.num_rows + 1) * BANDS, pa.int32()), pa.array(keys.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *map(pa.array, marks.view(np.int64).T.copy()), bands], ["doc_id", "row", "a", "b", "id", "n", "keys"])

    return run


def _sets(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [shingle_set(t.as_py(), shingle).tobytes() for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.binary())], ["row", "hashes"])

    return run


def _near_pairs(left: tuple, right: tuple, within: bool, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Rows of two sides within the radius, and how far they are apart, tile by tile; ``within``: the sides are one."""
    for i in range(0, len(left[0]), _TILE):
        a, b, count = (x[i : i + _TILE] for x in left[1:4])
        begin, end = np.searchsorted(right[3], [count[0] - radius, count[-1] + radius + 1])
        for j in range(max(begin, i) if within else begin, end, _TILE):
            z = min(end, j + _TILE)
            far = np.bitwise_count(a[:, None] ^ right[1][None, j:z])
            far += np.bitwise_count(b[:, None] ^ right[2][None, j:z])
            x, y = np.nonzero(far <= radius)
            far, x, y = far[x, y], x + i, y + j
            other = x < y if within else left[0][x] != right[0][y]
            yield x[other], y[other], far[other]


class Parts:
    """Which of the sets 0..n-1 are joined: each points at a smaller one of its part, or at itself."""

    def __init__(self, n: int):
        self.up = np.arange(n)

    def flatten(self) -> None:
        while not np.array_equal(above := self.up[self.up], self.up):
            self.up = above

    def apart(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        return self.up[x] != self.up[y]

    def join(self, x: np.ndarray, y: np.ndarray) -> None:
        """Joins all pairs at once: the larger root of each pair points at the smaller, until no pair is apart."""
        while len(x):
            p, q = self.up[x], self.up[y]
            np.minimum.at(self.up, np.maximum(p, q), np.minimum(p, q))
            self.flatten()
            still = self.apart(x, y)
            x, y = x[still], y[still]

    def edges(self, ids: np.ndarray) -> pa.RecordBatch:
        moved = np.flatnonzero(self.up != np.arange(len(self.up)))
        return _edges(ids[moved], ids[self.up[moved]])


def _edges(u: np.ndarray, v: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])


class Side:
    """Sets in the order of their fingerprints' population counts; ``at``: their numbers in what they come from."""

    def __init__(self, at: np.ndarray, ids: np.ndarray, a: np.ndarray, b: np.ndarray):
        count = np.bitwise_count(a).astype(np.int64) + np.bitwise_count(b)
        order = np.argsort(count, kind="stable")
        self.at, self.ids, self.a, self.b, self.count = at[order], ids[order], a[order], b[order], count[order]

    def __len__(self) -> int:
        return len(self.at)


def _near_pairs(left: Side, right: Side, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Rows of two sides within the radius, and how far they are apart, tile by tile; tiles whose counts differ more are skipped. A side against itself gives each pair once."""
    within = left is right
    for i in range(0, len(left), _TILE):
        a, b, count = (x[i : i + _TILE] for x in (left.a, left.b, left.count))
        begin, end = np.searchsorted(right.count, [count[0] - radius, count[-1] + radius + 1])
        for j in range(max(begin, i) if within else begin, end, _TILE):
            z = min(end, j + _TILE)
            far = np.bitwise_count(a[:, None] ^ right.a[None, j:z])
            far += np.bitwise_count(b[:, None] ^ right.b[None, j:z])
            x, y = np.nonzero(far <= radius)
            far, x, y = far[x, y], x + i, y + j
            other = x < y if within else left.ids[x] != right.ids[y]
            yield x[other], y[other], far[other]


def _sides(table: dict[str, np.ndarray], rows: np.ndarray) -> tuple[Side, Side]:
    """The two blocks of a comparison, or twice the one."""
    group, low, high = table["g"][rows], table["low"][rows[0]], table["high"][rows[0]]
    side = lambda at: Side(at, *(table[n][rows[at]] for n in ("id", "a", "b")))
    left = side(np.flatnonzero(group == low))
    return left, left if low == high else side(np.flatnonzero(group == high))


def _columns(table: pa.Table) -> dict[str, np.ndarray]:
    held = {n: table.column(n).to_numpy() for n in table.column_names if n != "hashes"}
    return held | {n: held[n].view(np.uint64) for n in ("a", "b")}


def _compared(table: pa.Table, radius: int) -> Iterator[pa.RecordBatch]:
    """Edges of whole groups: small ones all together, row against later row; larger ones tile by tile."""
    t = _columns(table)
    heads = np.flatnonzero(np.concatenate([[True], (np.diff(t["key"]) != 0) | (np.diff(t["low"]) != 0) | (np.diff(t["high"]) != 0)]))
    sizes = np.diff(np.append(heads, table.num_rows))
    group = np.repeat(np.arange(len(heads)), sizes)
    small = np.flatnonzero((sizes <= _SMALL_GROUP)[group])
    for d in range(1, _SMALL_GROUP):
        x = small[small + d < table.num_rows]
        x = x[group[x] == group[x + d]]
        if not len(x):
            break
        y = x + d
        near = np.bitwise_count(t["a"][x] ^ t["a"][y]) + np.bitwise_count(t["b"][x] ^ t["b"][y]) <= radius
        near &= t["id"][x] != t["id"][y]
        yield _edges(t["id"][x[near]], t["id"][y[near]])
    for k in np.flatnonzero(sizes > _SMALL_GROUP).tolist():
        rows = np.arange(heads[k], heads[k] + sizes[k])
        left, right = _sides(t, rows)
        parts = Parts(len(rows))
        for x, y, _ in _near_pairs(left, right, radius):
            parts.join(left.at[x], right.at[y])
        yield parts.edges(t["id"][rows])


def _compare_bands(radius: int):
    """Reads rows in the order of their groups and compares whole groups."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            held.append(batch)
            size += batch.num_rows
            if size < _HELD_ROWS:
                continue
            table = pa.Table.from_batches(held).combine_chunks()
            last = np.ones(table.num_rows, bool)
            for n in ("key", "low", "high"):
                column = table.column(n).to_numpy()
                last &= column == column[-1]
            cut = int(np.argmax(last))
            if cut:
                yield from _compared(table.slice(0, cut), radius)
            held = table.slice(cut).combine_chunks().to_batches()
            size = table.num_rows - cut
        if size:
            yield from _compared(pa.Table.from_batches(held), radius)

    return run


def _check_blocks(radius: int, similarity: float):
    """The pairs between two blocks (or within one) of a candidate class that are within the radius and alike; those already joined need no comparison."""

    def run(key, table):
        t, hashes = _columns(table), table.column("hashes")
        sets = lambda side: [np.frombuffer(hashes[int(i)].as_buffer(), np.uint64) for i in side.at]
        left, right = _sides(t, np.arange(table.num_rows))
        own = sets(left)
        others = own if left is right else sets(right)
        parts = Parts(table.num_rows)
        for x, y, far in _near_pairs(left, right, radius):
            order = np.argsort(far, kind="stable")
            x, y = x[order], y[order]
            while len(x):  # a few pairs at a time, as joined ones settle others
                apart = parts.apart(left.at[x], right.at[y])
                x, y = x[apart], y[apart]
                found = np.array([alike(own[i], others[j], similarity) for i, j in zip(x[:256].tolist(), y[:256].tolist(), strict=True)], bool)
                parts.join(left.at[x[:256][found]], right.at[y[:256][found]])
                x, y = x[256:], y[256:]
        return pa.Table.from_batches([parts.edges(t["id"])])

    return run


def _paired(dealt: DataFrame, groups: Column) -> DataFrame:
    """Every row once for each block that its own block ``g`` meets, as (low, high)."""
    return dealt.withColumn("o", F.explode(F.sequence(F.lit(0), groups.cast("int") - 1))).withColumn("low", F.least("g", "o")).withColumn("high", F.greatest("g", "o")).drop("o")


def _dealt(groups: Column) -> Column:
    return F.pmod(F.xxhash64("id", F.lit(7)), groups).cast("int")


def band_links(nodes: DataFrame, radius: int = WIDE_RADIUS) -> DataFrame:
    """Edges (u, v) between sets (id, a, b, keys) that agree in a band and whose fingerprints are within the radius: a forest of each comparison's links.

    A band key in a single set goes before anything is compared; one in very many sets is dealt to blocks.
    """
    spots = nodes.select("id", "a", "b", F.posexplode("keys").alias("band", "key")).select("id", "a", "b", F.xxhash64("band", "key").alias("key"))
    shared = spots.groupBy("key").count().where("count > 1").select("key", F.ceil(F.col("count") / BAND_BLOCK).alias("blocks"))
    met = spots.join(shared, "key").withColumn("g", _dealt(F.col("blocks")))
    dealt = _paired(met, F.col("blocks")).drop("blocks").repartition(shuffle_parts(nodes.sparkSession), "key", "low", "high").sortWithinPartitions("key", "low", "high")
    return dealt.mapInArrow(_compare_bands(radius), "u long, v long")


def wide_classes(docs: DataFrame, shingle: int = WIDE_SHINGLE, radius: int = WIDE_RADIUS, similarity: float = SIMILARITY) -> DataFrame:
    """(doc_id, row, component_id, keep) for every row: classes of texts linked by fingerprints within the radius and a Jaccard similarity of their shingles.

    ``row`` is the hash of doc_id and text, and ``keep`` marks the class's row of least doc_id (then hash). Distinct
    shingle sets meet in the tiles of their band keys, where fingerprints are compared; that gives candidate classes.
    Only there the sets travel, and pairs are linked that are alike.
    """
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string").alias("text")).withColumn("row", F.xxhash64("doc_id", "text"))
    marks = written(rows.select("doc_id", "row", "text").mapInArrow(_wide(shingle), "doc_id long, row long, a long, b long, id long, n long, keys array<long>"), "wide-fingerprints")
    best = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row"))
    nodes = marks.groupBy("id", "a", "b", "n").agg(best.alias("best"), F.min("row").alias("row"), F.first("keys").alias("keys"))
    roots = stars(band_links(nodes, radius))
    members = roots.select("node", "root").unionByName(roots.select(F.col("root").alias("node"), "root").distinct())
    candidates = written(nodes.join(members, F.col("id") == F.col("node")).select("id", "a", "b", "n", "row", "root"), "candidates")
    sizes = candidates.groupBy("root").agg(F.ceil(F.greatest(F.count("*") / CHECKED, F.sum("n") / CHECKED_SHINGLES, F.lit(1.0))).alias("blocks"))
    texts = rows.select("row", "text").join(candidates.select("row"), "row", "left_semi")
    sets = texts.mapInArrow(_sets(shingle), "row long, hashes binary").dropDuplicates(["row"])
    blocked = candidates.join(sizes, "root").withColumn("g", _dealt(F.col("blocks"))).join(sets, "row").select("root", "id", "a", "b", "g", "blocks", "hashes")
    checked = _paired(blocked, F.col("blocks")).drop("blocks")
    roots = stars(checked.groupBy("root", "low", "high").applyInArrow(_check_blocks(radius, similarity), "u long, v long"))
    rooted = nodes.select("id", "best").join(roots, F.col("id") == F.col("node"), "left").select("id", "best", F.coalesce("root", "id").alias("root"))
    named = rooted.groupBy("root").agg(F.min("best").alias("first"))
    classed = marks.select("doc_id", "row", "id").join(rooted.select("id", "root").join(named, "root").drop("root"), "id")
    return classed.select("doc_id", "row", F.col("first.doc_id").alias("component_id"), (F.col("row") == F.col("first.row")).alias("keep"))


def hex_digits(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))
