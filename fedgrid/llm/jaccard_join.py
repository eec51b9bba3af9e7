"""N-gram Jaccard join by universe partition and pigeonhole, verified exactly.

A document's set holds the distinct hashed shingles of its words. Set sizes fall into bands such that two
similar sets lie in the same or in neighbouring bands. For the pairs whose smaller set is in band k at most
H shingles differ, so the hash universe is cut into H + 1 segments: similar sets agree in one segment at
least. Each document indexes its own band's segments and probes with these and the segments of the band
below. Allocation by cost: empty segments and single shingles match too many documents, so a probe skips
them, and pays for each skip with a designated segment that it searches one deletion wide (its own shingles
minus one, and the index's minus one); then still H + 1 units of difference would be needed to escape. A
skip without such a segment left isn't made, so no pair is lost.

From segments to links, without listing the pairs of a group:

1. Documents of one set become a class under its smallest doc_id; classes go on alone.
2. Equal segments meet by hash; groups of the same members (a family of copies shares most segments) melt
   into one. Keys that a large family shares are told beforehand from one document in SAMPLE: their rows are
   summed up before anything moves and meet the sums by broadcast, so no task gets such a key's rows. Which
   keys are handled so changes where rows go, not what is found.
3. Every member is compared with its group's smallest one, linear in the group; links make components.
4. Only where a group still has several components, members outside the smallest one's component are
   compared with the members of other components. All pairs that share a segment are then linked, or
   compared, or already in one component, so the components are exact.

Comparison intersects whole shingle arrays, of the pairs whose parity maps (1024 bits) differ by no more than similar
sets can (a bound that loses no pair, and is tested inside the join of step 4). Components come from alternating large-star and small-star
rounds over edges, cut by checkpoints. Nothing but counts reaches the driver; ids are broadcast only when
counted within BROADCAST_IDS, beyond it these joins shuffle.

Defined results: a null text is empty; a text without words has an empty set and no links; rows with one
doc_id count as one document (what links to either links to it); a null doc_id is linked with nothing and
has a null component; an empty table gives no rows; further columns are kept by the stage.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from fedgrid.llm.common import checkpointed, hash_share, kept, shielded, table, trim

BROADCAST_IDS = 1_000_000
#: Rows of a key (estimated from one document in SAMPLE) from which it is summed up first, and the most such keys.
HOT_ROWS, SAMPLE, HOT_KEYS = 4096, 64, 1_000_000
#: Bytes of text that are hashed at a time.
_BLOCK = 1 << 18

_U = np.uint64
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_LETTER = np.random.default_rng(20).integers(1, 1 << 63, 256, dtype=np.uint64)
_BASE = 0x9E3779B97F4A7C15
_WEIGHT = np.random.default_rng(21).integers(1, 1 << 63, 64, dtype=np.uint64) | _U(1)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


@lru_cache(maxsize=1)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    with np.errstate(over="ignore"):
        up = np.cumprod(np.concatenate([[_U(1)], np.full(n - 1, _U(_BASE))]), dtype=np.uint64)
        inverse = _U(pow(_BASE, -1, 1 << 64))
        down = np.cumprod(np.concatenate([[_U(1)], np.full(n - 1, inverse)]), dtype=np.uint64)
    return up, down


def _word_hashes(block: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Hash and start of each word of a block of at most 2 * _BLOCK bytes."""
    raw = _LOWER[np.frombuffer(block, np.uint8)]
    space = _SPACE[raw]
    edge = np.flatnonzero(np.diff(space, prepend=True, append=True))
    start, stop = edge[::2], edge[1::2]
    up, down = _powers(2 * _BLOCK + 2)
    sums = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum(_LETTER[raw] * up[: len(raw)], out=sums[1:])
    return _mix((sums[stop] - sums[start]) * down[start] + (stop - start).astype(np.uint64)), start


def _long_word_hashes(data: bytes) -> np.ndarray:
    """Of a text above the block size: its words in blocks; a word that is no block itself is folded."""
    import xxhash

    hashes, block, size = [], [], 0

    def flush() -> None:
        if block:
            hashes.append(_word_hashes(b" ".join(block))[0])
            block.clear()

    for word in data.split():
        if len(word) > _BLOCK:
            flush()
            size = 0
            hashes.append(np.array([xxhash.xxh3_64_intdigest(word.lower())], np.uint64))
            continue
        if size + len(word) + 1 > _BLOCK:
            flush()
            size = 0
        block.append(word)
        size += len(word) + 1
    flush()
    return np.concatenate(hashes) if hashes else np.zeros(0, np.uint64)


def _shingles(words: np.ndarray, width: int) -> np.ndarray:
    """Sorted distinct shingle hashes of one document's word hashes."""
    n = len(words)
    if n == 0:
        return words
    if n < width:
        return _mix(np.array([(words * _WEIGHT[n : 2 * n]).sum() + _U(n)], np.uint64))
    total = np.zeros(n - width + 1, np.uint64)
    for k in range(width):
        total += words[k : n - width + 1 + k] * _WEIGHT[k]
    return np.unique(_mix(total))


def shingle_sets(texts: list[str | None], width: int) -> Iterator[np.ndarray]:
    """The set of each whole text, in order."""
    blocks, size = [], 0
    for text in texts:
        data = (text or "").encode("utf-8", "surrogatepass")
        if size + len(data) + 1 > _BLOCK and blocks:
            yield from _block_sets(blocks, width)
            blocks, size = [], 0
        if len(data) > _BLOCK:
            yield _shingles(_long_word_hashes(data), width)
            continue
        blocks.append(data)
        size += len(data) + 1
    if blocks:
        yield from _block_sets(blocks, width)


def _block_sets(blocks: list[bytes], width: int) -> Iterator[np.ndarray]:
    hashes, start = _word_hashes(b"\n".join(blocks))
    ends = np.cumsum([len(b) + 1 for b in blocks])
    cuts = np.concatenate([[0], np.searchsorted(start, ends)])
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        yield _shingles(hashes[a:b], width)


class Bands:
    """Size bands and segment counts for a threshold of ``percent`` hundredths."""

    def __init__(self, percent: int):
        self.percent, self.tops = percent, [1]

    def of(self, n: int) -> int:
        while self.tops[-1] < n:
            top = self.tops[-1]
            self.tops.append(max(top + 1, top * 100 // self.percent))
        return int(np.searchsorted(self.tops, n))

    def differing(self, band: int) -> int:
        """The most shingles that differ in a pair whose smaller set is in ``band``."""
        top = self.tops[band]
        return (top + top * 100 // self.percent) * (100 - self.percent) // (100 + self.percent)


def designated(segments: int, percent: int) -> int:
    """Of a band's segments the first so many can be searched one deletion wide.

    As many as there are segments under two shingles, by the mean number a segment holds, and a margin.
    """
    mean = 0.9 * (100 + percent) / (2 * (100 - percent))
    poor = math.exp(-mean) * (1 + mean)
    return min(segments, 2 + math.ceil(1.25 * poor * segments))


def signatures(shingles: np.ndarray, bands: Bands) -> tuple[np.ndarray, np.ndarray]:
    """Keys of a set and whether each is probed with; keys that are not are there to be found only.

    Keys live in two spaces. In the first a segment as it is meets segments as they are, and the deletions of a
    wide probe; in the second the deletions of the index meet the segments of wide probes. So two deletions of
    one segment don't meet, but for those of two wide probes.
    """
    band = bands.of(len(shingles))
    keys, probes = [], []
    mixed = _mix(shingles ^ _U(0x5851F42D4C957F2D))
    sums = np.concatenate([[_U(0)], np.cumsum(mixed)])
    for scheme in (band, band - 1):
        differing = bands.differing(scheme) if scheme >= 0 else 0
        if differing == 0:  # then only equal sets are similar, and these are one class
            continue
        m = differing + 1
        place = ((shingles >> _U(32)) * _U(m)) >> _U(32)  # rises with the hash, so segments are slices
        cuts = np.searchsorted(place, np.arange(m + 1, dtype=np.uint64))
        count = np.diff(cuts)
        own = sums[cuts[1:]] - sums[cuts[:-1]]
        salt = _mix(np.arange(m, dtype=np.uint64) + _U(scheme * 1_000_003 + 1))
        wide = np.arange(designated(m, bands.percent))
        able = wide[count[wide] >= 3]
        skipped = np.argsort(count, kind="stable")[: int((count < 2).sum())][: len(able)]
        paying = able[np.argsort(-count[able], kind="stable")][: len(skipped)]
        probe = np.ones(m, bool)
        probe[skipped] = False
        index = scheme == band
        shown = np.ones(m, bool) if index else probe
        keys += [_mix(own + salt)[shown], _mix(own[paying] + ~salt[paying])]
        probes += [probe[shown], np.ones(len(paying), bool)]
        for j in paying:
            keys.append(_mix(own[j] - mixed[cuts[j] : cuts[j + 1]] + salt[j]))
            probes.append(np.ones(count[j], bool))
        for j in wide[count[wide] >= 4] if index else ():  # a wide probe holds three shingles at least
            keys.append(_mix(own[j] - mixed[cuts[j] : cuts[j + 1]] + ~salt[j]))
            probes.append(np.zeros(count[j], bool))
    if not keys:
        return np.zeros(0, np.uint64), np.zeros(0, bool)
    return np.concatenate(keys), np.concatenate(probes)


def _parts(batch: pa.RecordBatch, rows: int, size: int = _BLOCK) -> Iterator[pa.RecordBatch]:
    """Slices of a batch of so many rows and bytes of text at most (a longer text alone)."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(1)), 0).to_numpy(zero_copy_only=False))
    at = 0
    while at < batch.num_rows:
        before = ends[at - 1] if at else 0
        to = min(max(int(np.searchsorted(ends, before + size, "right")), at + 1), at + rows)
        yield batch.slice(at, to - at)
        at = to


def _mapped(docs: DataFrame, schema: str, width: int, make: Callable, chunk: int = 512) -> DataFrame:
    """``make`` gets lists of ids and sets, of some rows at a time, and gives a list of arrays.

    Rows are taken by number and by bytes, so that a run of very long texts makes many small results.
    """
    names = [part.split()[0] for part in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept("jaccard_join")
        np.seterr(over="ignore")
        for batch in batches:
            for part in _parts(batch, chunk):
                sets = list(shingle_sets(part.column(1).to_pylist(), width))
                yield pa.RecordBatch.from_arrays(make(part.column(0), sets), names=names)
        trim()

    return docs.select("doc_id", "text").mapInArrow(run, schema)


#: 64-bit words of a set's parity map: one bit for each of 1024 buckets of the hash universe, set where the
#: set has an odd number of shingles in the bucket.
PARITY_WORDS = 16


def set_prints(docs: DataFrame, width: int) -> DataFrame:
    """(doc_id, n, a, b, parity): size, 128-bit hash and parity map of each row's set."""

    def make(ids: pa.Array, sets: list[np.ndarray]) -> list[pa.Array]:
        a = np.array([s.sum(dtype=np.uint64) for s in sets], np.uint64)
        b = np.array([_mix(s ^ _U(0x2545F4914F6CDD1D)).sum(dtype=np.uint64) for s in sets], np.uint64)
        odd = [np.bincount((s >> _U(54)).astype(np.int64), minlength=64 * PARITY_WORDS).astype(np.uint8) & 1 for s in sets]
        flat = pa.array(np.packbits(np.concatenate(odd)).view(np.int64))
        offsets = pa.array(np.arange(0, PARITY_WORDS * len(sets) + 1, PARITY_WORDS, dtype=np.int32))
        sizes = pa.array([len(s) for s in sets], pa.int64())
        parts = [ids, sizes, pa.array(a.view(np.int64)), pa.array(b.view(np.int64))]
        return [*parts, pa.ListArray.from_arrays(offsets, flat)]

    return _mapped(docs, "doc_id bigint, n bigint, a bigint, b bigint, parity array<bigint>", width, make)


def _signature_rows(docs: DataFrame, width: int, percent: int) -> DataFrame:
    def make(ids: pa.Array, sets: list[np.ndarray]) -> list[pa.Array]:
        bands = Bands(percent)
        made = [signatures(s, bands) if len(s) else (np.zeros(0, np.uint64), np.zeros(0, bool)) for s in sets]
        sizes = np.array([len(k) for k, _ in made], np.int64)
        keys = np.concatenate([k for k, _ in made])
        rows = np.repeat(np.arange(len(made)), sizes)
        n = np.array([len(s) for s in sets], np.int32)
        probe = np.concatenate([p for _, p in made])
        return [pa.array(keys.view(np.int64)), ids.take(pa.array(rows)), pa.array(np.where(probe, n[rows], -n[rows]))]

    # n is negative for keys that aren't probed with
    return _mapped(docs, "key bigint, doc bigint, n int", width, make, chunk=256)


def _arrays(docs: DataFrame, width: int) -> DataFrame:
    def make(ids: pa.Array, sets: list[np.ndarray]) -> list[pa.Array]:
        offsets = np.concatenate([[0], np.cumsum([len(s) for s in sets])]).astype(np.int32)
        values = np.concatenate([s.view(np.int64) for s in sets]) if sets else np.zeros(0, np.int64)
        return [ids, pa.ListArray.from_arrays(pa.array(offsets), pa.array(values))]

    return _mapped(docs, "doc bigint, shingles array<bigint>", width, make, chunk=256)


def _only(docs: DataFrame, ids: DataFrame, how: str) -> DataFrame:
    """left_semi or left_anti of the documents with ids (a checkpointed table), broadcast where small."""
    named = ids.toDF("__id")
    named = F.broadcast(named) if ids.count() <= BROADCAST_IDS else named
    return docs.join(named, F.col("doc_id") == F.col("__id"), how)


def _alike(percent: int, i: Column, x: Column, y: Column) -> Column:
    return 100 * i >= percent * (x + y - i)


def _within(percent: int, x: str, y: str, px: str, py: str) -> Column:
    """A bound that no similar pair breaks: parity maps differ in no more bits than the sets do in shingles."""
    words = [F.bit_count(F.get(px, F.lit(i)).bitwiseXOR(F.get(py, F.lit(i)))) for i in range(PARITY_WORDS)]
    return sum(words[1:], words[0]) * (100 + percent) <= (F.col(x) + F.col(y)) * (100 - percent)


def verified(docs: DataFrame, pairs: DataFrame, maps: DataFrame, width: int, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets are similar; intersects the whole sets of those within the bound."""
    ma, mb = maps.toDF("a", "na", "ma"), maps.toDF("b", "nb", "mb")
    pairs = pairs.join(ma, "a").join(mb, "b").where(_within(percent, "na", "nb", "ma", "mb"))
    pairs = checkpointed(pairs.select("a", "b").distinct())
    ids = checkpointed(pairs.select(F.explode(F.array("a", "b")).alias("doc")).distinct())
    arrays = _arrays(_only(docs, ids, "left_semi"), width)
    left = arrays.select(F.col("doc").alias("a"), F.col("shingles").alias("x"))
    right = arrays.select(F.col("doc").alias("b"), F.col("shingles").alias("y"))
    both = pairs.join(left, "a").join(right, "b")
    shared = F.size(F.array_intersect("x", "y")).cast("bigint")
    return both.where(_alike(percent, shared, F.size("x"), F.size("y"))).select("a", "b").distinct()


#: Edges from which hubs are told apart, and the most hubs there can be then.
HUB_EDGES, HUBS = 100_000, 100_000


def components(edges: DataFrame) -> DataFrame:
    """(node, component): the smallest node that the edges (a, b) reach, for each node of an edge.

    A node of very many edges is a hub: the edges of hubs stay where they are and meet the hubs' least neighbours,
    of which there are HUBS at most, by broadcast.
    """
    edges = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct()

    def star(edges: DataFrame, large: bool, total: int) -> DataFrame:
        if large:
            near = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        else:
            near = edges
        least = near.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n"))
        least = least.select("u", F.least("u", "m").alias("m"), "n")
        if total > HUB_EDGES:
            many = F.col("n") >= max(HOT_ROWS, 2 * total // HUBS)
            hubs = least.where(many).drop("n")
            joined = near.join(F.broadcast(hubs.select("u")), "u", "left_anti").join(least.where(~many).drop("n"), "u")
            joined = joined.unionByName(near.join(F.broadcast(hubs), "u"))
        else:
            joined = near.join(least.drop("n"), "u")
        if large:
            out = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        else:
            out = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(
                least.select("u", F.col("m").alias("v"))
            )
        return out.where("u <> v").distinct()

    before, edges = None, checkpointed(edges)
    total = edges.count()
    while True:
        edges = checkpointed(star(star(edges, True, total), False, total))
        now = edges.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v"))).first()
        if now == before:
            break
        before, total = now, now[0]
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(
        edges.select("v", "v").distinct().toDF("node", "component")
    )


def _groups(docs: DataFrame, width: int, percent: int) -> DataFrame:
    """(name, size, p, pn, doc, n): members of each key's group beside its smallest one; groups of two or more."""
    rows = _signature_rows(docs, width, percent)
    share = _signature_rows(docs.where(hash_share("doc_id", 1.0 / SAMPLE)), width, percent)
    hot = share.groupBy("key").count().where(F.col("count") >= HOT_ROWS // SAMPLE)
    hot = checkpointed(hot.orderBy(F.col("count").desc()).limit(HOT_KEYS).select("key"))

    n = F.abs("n").alias("n")
    sums = {
        "pivot": F.min(F.struct("doc", n)),
        "top": F.max("doc"),
        "probed": F.max("n"),
        "name": F.bit_xor(F.xxhash64("doc")),
        "size": F.count(F.lit(1)),
    }
    same = Window.partitionBy("key")

    def cold(rows: DataFrame) -> DataFrame:
        return rows.select("doc", n, *[f.over(same).alias(c) for c, f in sums.items()])

    if hot.isEmpty():
        grouped = cold(rows)
    else:
        grouped = cold(rows.join(F.broadcast(hot), "key", "left_anti"))
        own = checkpointed(rows.join(F.broadcast(hot), "key", "left_semi"))
        heads = own.groupBy("key").agg(*[f.alias(c) for c, f in sums.items()])  # HOT_KEYS rows at most
        grouped = grouped.unionByName(own.join(F.broadcast(heads), "key").select("doc", n, *sums))
    grouped = grouped.where((F.col("probed") > 0) & (F.col("top") > F.col("pivot.doc")))
    return checkpointed(
        grouped.select("name", "size", F.col("pivot.doc").alias("p"), F.col("pivot.n").alias("pn"), "doc", "n").distinct()
    )


def links(docs: DataFrame, width: int, percent: int, prints: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(classes, components): each doc_id's class, and the component of each class that has links."""
    known = prints.where(F.col("doc_id").isNotNull() & (F.col("n") > 0))
    maps = known.select(F.col("doc_id").alias("doc"), F.col("n").cast("int").alias("n"), "parity")
    known = known.drop("parity")
    classes = known.groupBy("a", "b").agg(F.min("doc_id").alias("class"))
    classes = checkpointed(known.join(classes, ["a", "b"]).select("doc_id", "class").distinct())
    alone = docs.where(F.col("doc_id").isNotNull())
    # documents that stand for no class of their own: all their sets are copies of others'
    ids = classes.groupBy("doc_id").agg(F.min("class").alias("a"), F.max(F.col("class") == F.col("doc_id")).alias("own"), F.count(F.lit(1)).alias("sets"))
    copies = checkpointed(ids.where(~F.col("own")).select("doc_id"))
    groups = _groups(_only(alone, copies, "left_anti"), width, percent)

    def near(x: str, y: str) -> Column:
        return 100 * F.least(x, y) >= percent * F.greatest(x, y)

    star = groups.where((F.col("doc") > F.col("p")) & near("n", "pn"))
    star = checkpointed(star.select(F.col("p").alias("a"), F.col("doc").alias("b")).distinct())
    # one document of several classes (rows that share a doc_id) joins them
    joined = ids.where("sets > 1").select("doc_id", "a").join(classes, "doc_id").where("a <> class")
    joined = joined.select("a", F.col("class").alias("b"))
    first = checkpointed(verified(alone, star, maps, width, percent).unionByName(joined))

    found = components(first).withColumnRenamed("node", "doc")
    placed = groups.join(found, "doc", "left").withColumn("c", F.coalesce("component", "doc"))
    key = ["name", "size", "p"]
    open_ = placed.groupBy(*key).agg(F.min("c").alias("low"), F.max("c").alias("high")).where("low <> high")
    open_ = placed.join(open_.select(*key), key).select(*key, "doc", "c")
    open_ = checkpointed(open_.join(maps, "doc"))
    main = open_.where("doc = p").select(*key, F.col("c").alias("main")).distinct()
    minor = open_.join(main, key).where("c <> main")
    minor = minor.toDF(*key, *[f"{c}1" for c in ("doc", "c", "n", "parity")], "main")
    other = (F.col("c") == F.col("main")) | (F.col("doc1") < F.col("doc"))
    cross = minor.join(open_, key).where((F.col("c") != F.col("c1")) & near("n", "n1") & other)
    cross = cross.where(_within(percent, "n", "n1", "parity", "parity1"))
    cross = cross.select(F.least("doc1", "doc").alias("a"), F.greatest("doc1", "doc").alias("b")).distinct()
    cross = checkpointed(cross.join(star, ["a", "b"], "left_anti"))
    if cross.isEmpty():
        return classes, found.withColumnRenamed("doc", "node")
    second = verified(alone, cross, maps, width, percent)
    return classes, components(first.unionByName(second))


def similar_documents(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id), a row for each row of ``docs``."""
    docs = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    prints = checkpointed(set_prints(docs, width))
    classes, found = links(docs, width, percent, prints)
    classes = classes.groupBy("doc_id").agg(F.min("class").alias("class"))
    placed = classes.join(found.withColumnRenamed("node", "class"), "class", "left").select(
        "doc_id", F.coalesce("component", "class").alias("component")
    )
    return prints.join(placed, "doc_id", "left").select(
        "doc_id", F.col("n").alias("n_shingles"), F.coalesce("component", "doc_id").alias("component_id")
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_documents(table(spark, sf_dir, "documents"), width=4, percent=85)


@shielded
def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of the smallest doc_id of each group; of rows that share a doc_id one stays."""
    found = checkpointed(similar_documents(docs))
    dropped = found.where("doc_id <> component_id").select("doc_id").distinct()
    repeated = found.where("doc_id is not null").groupBy("doc_id").count().where("count > 1")
    out = _only(docs, checkpointed(dropped), "left_anti")
    if repeated.isEmpty():
        return out
    again = out.join(repeated.select(F.col("doc_id").alias("__again")), F.col("doc_id") == F.col("__again"), "left")
    once = again.where(F.col("__again").isNotNull()).dropDuplicates(["doc_id"])
    return again.where(F.col("__again").isNull()).unionByName(once).drop("__again")


SQL = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(string_split_regex(
           translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'),
           lambda x: x <> '') AS w FROM documents
), sets AS (
  SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')]
           ELSE list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' ')) END) AS s FROM words
), shingles AS (SELECT doc_id, len(s) AS n, unnest(s) AS h FROM sets
), links AS (
  SELECT x.doc_id AS a, y.doc_id AS b FROM shingles x JOIN shingles y ON x.h = y.h AND x.doc_id <> y.doc_id
  GROUP BY x.doc_id, y.doc_id, x.n, y.n HAVING 100 * count(*) >= 85 * (x.n + y.n - count(*))
), reach(id, c) AS (
  SELECT doc_id, doc_id FROM documents UNION SELECT links.b, reach.c FROM reach JOIN links ON links.a = reach.id
)
SELECT doc_id, CAST(len(s) AS BIGINT) AS n_shingles, (SELECT min(c) FROM reach WHERE id = doc_id) AS component_id FROM sets
"""
