"""N-gram Jaccard self-join by parity sketches, and the classes of linked documents.

A document is its set of distinct word shingles, as 64-bit hashes. Each shingle flips one bit of a
bit sketch, so the Hamming distance of two sketches never exceeds the sets' symmetric difference, and
folding a sketch in half keeps that. Two documents of a and b shingles link only if their sets differ
in at most (a + b) / 9 places (at 80 of 100), and then their sizes are within the threshold's ratio.

Candidates, size band by size band: the sketch is cut into more segments than a linked pair can differ
in. A segment enters the join as one 64-bit word: the XOR of a word per flipped bit. If sets differ in
at most D places, at most D segments differ, so among the first D + 2 occupied segments of either
document (in one common order: most shingles first) at least two are shared. Documents meet in the
buckets of equal segment words. Each document is in its own band and, if near its lower edge, in the
band below.

No bucket is expanded into all pairs of rows. First every member is paired with the bucket's least only; pairs
that pass the sketch bound are verified on the whole sets, and verified links are joined to components.
A bucket whose members are one component is settled. A pair left open shares two unsettled buckets,
so only members of two of them stay. Inside an unsettled bucket these are compared by
sketches; what leaves it is which components may link, at most one row per component and block, and which sets
have a possible partner. Components that may link form a group, to which each such set goes,
whole; there pairs are compared by finer sketches and then exactly, unless their components have met
already. So no link between components is lost.

A bucket's least comes from a combining aggregation, and its members find it by a join that adaptive execution splits
where a bucket is hot; so are the pairs of a hub split, which meet the leaf's set first and the hub's last. A bucket or group over
the size of a block is dealt into blocks, and each pair of blocks is a task's work of its own: m members in blocks of b
are sent to m / b places, so of a bucket that stays unsettled the work grows with the square of its members, while no task holds more than two blocks.

Equal sets are one class from the start: a task emits the segments of a set once.

Defined results: null, empty and blank texts have no shingle and link with nothing; a text of fewer words
than a shingle is one shingle; equal sets link; repeated rows are documents like others (with one id they
share it); a null id takes no part in the smallest id; an empty table gives an empty result; other columns
are ignored. Hashes of 64 bits stand for shingles, and digests of 128 bits for equal sets.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import components
from .shared import STEP, keep_nothing, materialize, mixed, raw_texts, settled

FOLD = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
#: Sizes below this use one segment per shingle, so that enough segments are occupied for certain.
FINE_BELOW = 64
MEMO_ENTRIES = 1 << 17
#: Members of a bucket that are compared by sketches at a time, against as many.
BLOCK = 2048
#: Shingles of a group's sets that are compared at a time, against as many.
BLOCK_SHINGLES = 1 << 20
#: Rows of ids that are broadcast at most; beyond it they are joined by shuffle.
BROADCAST_ROWS = 100_000


class _WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        value = xxhash.xxh3_64_intdigest(word)
        if len(self) < MEMO_ENTRIES:
            self[word] = value
        return value


def shingles(raw: bytes, width: int, memo: dict) -> np.ndarray:
    """Sorted distinct hashes of the text's shingles of ``width`` words."""
    words = raw.translate(FOLD).split()
    if not words:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(memo.__getitem__, words), np.uint64, len(words))
    n = max(1, len(h) - width + 1)
    acc = np.full(n, len(h) if len(h) < width else width, np.uint64)
    for k in range(min(width, len(h))):
        acc = acc * STEP + h[k : k + n]
    return np.unique(mixed(acc))


class Bands:
    """Size bands [least * 2^i, least * 2^(i+1)) and the segments of a set in them, for a threshold of ``num`` / ``den``."""

    def __init__(self, num: int = 80, den: int = 100):
        self.num, self.den = num, den
        self.least = den // (den - num) - 1 if den > num else 1 << 62  # smaller sets link only if equal

    def differ(self, a: int, b: int) -> int:
        """The largest symmetric difference of linked sets of these sizes."""
        return (a + b) * (self.den - self.num) // (self.den + self.num)

    def _schemes(self, n: int) -> Iterator[tuple[int, int, int]]:
        """(band, D, largest size of the band) in which a set of n shingles meets others."""
        band = (n // self.least).bit_length() - 1
        yield band, self.differ(n, n * self.den // self.num), self.least * 2 ** (band + 1) - 1
        below = self.least * 2**band - 1
        if band and below * self.den >= n * self.num:
            yield band - 1, self.differ(n, below), below

    def words(self, s: np.ndarray) -> np.ndarray:
        """Join words of a set's leading segments, in each of its bands."""
        n = len(s)
        if n < self.least:
            return np.zeros(0, np.uint64)
        out = []
        base = mixed(s ^ STEP)
        for band, differ, largest in self._schemes(n):
            salt = np.uint64((band + 1) * 0x632BE59BD9B4E019 & (2**64 - 1))
            if largest < FINE_BELOW:
                out.append(np.sort(mixed(base ^ salt))[: differ + 2])
                continue
            segments = int(1.1 * (self.differ(largest, largest * self.den // self.num) + 1)) + 10
            at = ((s >> np.uint64(24)) % np.uint64(segments)).astype(np.uint16 if segments < 65536 else np.int64)
            order = np.argsort(at, kind="stable")
            at = at[order]
            starts = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
            held = np.diff(np.append(starts, n))
            lead = np.lexsort((at[starts], -held))[: differ + 2]
            xor = np.bitwise_xor.reduceat(base[order], starts)[lead]
            out.append(mixed(xor ^ mixed(at[starts][lead].astype(np.uint64) + salt)))
        return np.concatenate(out)


def parity_sketch(s: np.ndarray) -> bytes:
    """Bits that an odd number of shingles hash to; as many bits as shingles, rounded up to a power of two, 64 at least."""
    bits = max(64, 1 << (len(s) - 1).bit_length()) if len(s) else 64
    odd = np.bincount((s & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def folded(sketch: np.ndarray, words: int) -> np.ndarray:
    """A sketch folded to ``words`` 64-bit words; parities add up, so distances only shrink."""
    return np.bitwise_xor.reduce(sketch.reshape(-1, words), axis=0)


def document_sets(docs: DataFrame, id_col: str, text_col: str, width: int, bands: Bands) -> DataFrame:
    """One row per document: ``_id``, ``n``, digest ``d1`` ``d2``, ``sketch`` and ``words`` (where a task meets a set first)."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_nothing()
        memo, seen = _WordHashes(), set()
        for batch in batches:
            size, first, second, sketches, words = [], [], [], [], []
            for raw in raw_texts(batch.column(1)):
                s = shingles(raw, width, memo)
                digest = xxhash.xxh3_128_intdigest(s.tobytes())
                size.append(len(s))
                first.append(digest >> 64)
                second.append(digest & (2**64 - 1))
                new = len(s) >= bands.least and digest not in seen
                seen.add(digest)
                sketches.append(parity_sketch(s) if new else None)
                words.append(bands.words(s) if new else None)
            offsets = np.cumsum([0] + [0 if w is None else len(w) for w in words])
            flat = np.concatenate([w for w in words if w is not None] or [np.zeros(0, np.uint64)])
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(size, pa.int64()), pa.array(np.array(first, np.uint64).view(np.int64)), pa.array(np.array(second, np.uint64).view(np.int64)), pa.array(sketches, pa.binary()),
                 pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(flat.view(np.int64)))],
                names=["_id", "n", "d1", "d2", "sketch", "words"],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("_id"), text_col).mapInArrow(read, f"_id {kind}, n bigint, d1 bigint, d2 bigint, sketch binary, words array<bigint>")


def buckets(sets: DataFrame) -> DataFrame:
    """Members of buckets that hold two sets or more: ``word``, ``d1``, ``least`` (the bucket's), each once."""
    rows = sets.select(F.explode("words").alias("word"), "d1")
    # Most words occur once: a count, which packs well, tells which; the members of the others are few.
    often = rows.groupBy("word").agg(F.count(F.lit(1)).alias("_n")).where("_n > 1").select("word")
    found = materialize(rows.join(often, "word"), "join-members")
    least = found.groupBy("word").agg(F.min("d1").alias("least"), F.max("d1").alias("_most")).where("least < _most").select("word", "least")
    return found.groupBy("d1", "word").agg(F.lit(0).alias("_")).select("word", "d1").join(least, "word")


def _near(pairs: DataFrame, sketches: DataFrame, bands: Bands) -> DataFrame:
    """Pairs (``a``, ``b``) of digests whose sizes and sketches allow a link."""
    one = sketches.select(F.col("d1").alias("a"), F.col("n").alias("na"), F.col("sketch").alias("sa"))
    two = sketches.select(F.col("d1").alias("b"), F.col("n").alias("nb"), F.col("sketch").alias("sb"))
    sized = pairs.join(one, "a").join(two, "b").where(f"least(na, nb) * {bands.den} >= greatest(na, nb) * {bands.num}")

    def test(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_nothing()
        for batch in batches:
            a, b, na, sa, nb, sb = (batch.column(k).to_pylist() for k in range(6))
            keep = []
            for x, p, y, q in zip(na, sa, nb, sb, strict=True):
                p, q = np.frombuffer(p, np.uint64), np.frombuffer(q, np.uint64)
                w = min(len(p), len(q))
                keep.append(int(np.bitwise_count(folded(p, w) ^ folded(q, w)).sum()) <= bands.differ(x, y))
            yield batch.filter(pa.array(keep, pa.bool_())).select(["a", "b"])

    return sized.select("a", "b", "na", "sa", "nb", "sb").mapInArrow(test, "a bigint, b bigint")


def _whole_sets(wanted: DataFrame, sets: DataFrame, docs: DataFrame, id_col: str, text_col: str, width: int) -> DataFrame:
    """``d1``, ``s``: the whole shingle set of each wanted digest, read again from one document that has it."""
    reps = sets.where("words is not null").join(wanted, "d1", "left_semi").groupBy("d1").agg(F.min("_id").alias("_rep"))
    reps = materialize(reps, "join-wanted")
    side = reps.select("_rep").distinct()
    small = reps.count() <= BROADCAST_ROWS
    texts = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text"))
    texts = texts.join(F.broadcast(side) if small else side, F.col("_id").eqNullSafe(F.col("_rep")), "left_semi")

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_nothing()
        memo = _WordHashes()
        for batch in batches:
            own = [shingles(raw, width, memo) for raw in raw_texts(batch.column(0))]
            digest = [xxhash.xxh3_128_intdigest(s.tobytes()) >> 64 for s in own]
            offsets = np.cumsum([0] + [len(s) for s in own])
            flat = np.concatenate(own or [np.zeros(0, np.uint64)])
            yield pa.RecordBatch.from_arrays([pa.array(np.array(digest, np.uint64).view(np.int64)), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(flat.view(np.int64)))], names=["d1", "s"])

    whole = texts.select("_text").mapInArrow(read, "d1 bigint, s array<bigint>").join(reps.select("d1"), "d1", "left_semi").dropDuplicates(["d1"])
    return materialize(whole, "join-whole-sets")


def _verified(pairs: DataFrame, sets: DataFrame, docs: DataFrame, id_col: str, text_col: str, width: int, bands: Bands) -> DataFrame:
    """The pairs of digests whose whole sets link."""
    pairs = materialize(pairs, "join-candidates")
    whole = _whole_sets(pairs.select(F.col("a").alias("d1")).union(pairs.select("b")).distinct(), sets, docs, id_col, text_col, width)
    both = pairs.join(whole.select(F.col("d1").alias("a"), "s"), "a").join(whole.select(F.col("d1").alias("b"), F.col("s").alias("t")), "b")
    common = F.size(F.array_intersect("s", "t"))
    return both.where(common * bands.den >= (F.size("s") + F.size("t") - common) * bands.num).select("a", "b")


class _Forest:
    """Union-find over the components that meet in a bucket."""

    def __init__(self) -> None:
        self.up: dict[int, int] = {}

    def root(self, x: int) -> int:
        while (y := self.up.get(x, x)) != x:
            self.up[x] = self.up.get(y, y)
            x = y
        return x

    def join(self, x: int, y: int) -> None:
        self.up[self.root(x)] = self.root(y)


def bucket_links(digests: list[int], roots: list[int], own: list[int], sets: list[np.ndarray], i: int, j: int, bands: Bands) -> list[tuple[int, int]]:
    """Links that join different components in a group (or between its blocks i and j): no more than components less one.

    Sketches of eight bits a shingle leave few pairs to compare whole, and a pair whose components
    have met already needs no comparison. Sets of like size are sketched at a time, so one long set doesn't widen the sketches of short ones.
    """
    order = sorted(range(len(sets)), key=lambda k: len(sets[k]))
    n = np.array([len(sets[k]) for k in order])
    label, block = np.array([roots[k] for k in order]), np.array([own[k] for k in order])
    # A set is compared with those of its size or more, up to the threshold's ratio; of blocks i and j, one must be in each.
    ends = np.searchsorted(n, n * bands.den // bands.num, "right")
    forest, found, at = _Forest(), [], 0
    while at < len(n):
        bits = max(64, 1 << (int(n[at]) * 8 - 1).bit_length())
        stop = int(np.searchsorted(n, bits // 8, "right"))
        sketch = np.stack([_wide_sketch(sets[k], bits) for k in order[at : int(ends[stop - 1])]])
        for k in range(at, stop):
            fits = label[k + 1 : ends[k]] != label[k]
            if i != j:
                fits &= block[k + 1 : ends[k]] != block[k]
            near = k + 1 + np.flatnonzero(fits)
            if not len(near):
                continue
            apart = np.bitwise_count(sketch[near - at] ^ sketch[k - at]).sum(1)
            for m in near[apart <= (n[near] + n[k]) * (bands.den - bands.num) // (bands.den + bands.num)].tolist():
                if forest.root(int(label[k])) != forest.root(int(label[m])):
                    one, two = order[k], order[m]
                    common = len(np.intersect1d(sets[one], sets[two], assume_unique=True))
                    if common * bands.den >= (n[k] + n[m] - common) * bands.num:
                        forest.join(int(label[k]), int(label[m]))
                        found.append((max(digests[one], digests[two]), min(digests[one], digests[two])))
        at = stop
    return found


def _wide_sketch(s: np.ndarray, bits: int) -> np.ndarray:
    """A set's parity sketch of ``bits`` bits, as 64-bit words."""
    odd = np.bincount((s & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.uint64)


def bucket_meetings(digests: list[int], roots: list[int], own: list[int], sizes: list[int], sketches: list[bytes], i: int, j: int, bands: Bands) -> set[tuple[int, int, int]]:
    """What a bucket's sketches leave possible between its components (or between its blocks i and j).

    Rows (0, root, root) join components that may link, one less than there are at most; rows (1, digest, root) name
    the sets that have a possible partner in another component.
    """
    n, label, block = np.array(sizes), np.array(roots), np.array(own)
    width = min(len(s) for s in sketches) // 8
    bits = np.stack([folded(np.frombuffer(s, np.uint64), width) for s in sketches])
    forest, found = _Forest(), set()
    for k in range(len(sizes)):
        if i != j and block[k] != i:
            continue
        fits = (label != label[k]) & (np.minimum(n, n[k]) * bands.den >= np.maximum(n, n[k]) * bands.num)
        fits &= (block == j) if i != j else (np.arange(len(sizes)) > k)
        at = np.flatnonzero(fits)
        if len(at):
            apart = np.bitwise_count(bits[at] ^ bits[k]).sum(1)
            near = at[apart <= (n[at] + n[k]) * (bands.den - bands.num) // (bands.den + bands.num)].tolist()
            for m in near:
                found.add((1, digests[m], roots[m]))
                if forest.root(roots[k]) != forest.root(roots[m]):
                    forest.join(roots[k], roots[m])
                    found.add((0, max(roots[k], roots[m]), min(roots[k], roots[m])))
            if near:
                found.add((1, digests[k], roots[k]))
    return found


def _by_group(rows: DataFrame, group: str, size: str, most: int, payload: list[str], work, schema: str) -> DataFrame:
    """Run ``work(payload columns as lists, i, j)`` on every group, large groups block against block.

    A group of ``size`` over ``most`` is dealt into blocks by hash, and every pair of blocks (i, j) is a group of
    its own, for any task to take: no task ever holds more than two blocks.
    """
    dealt = rows.withColumn("_blocks", F.expr(f"({size} + {most - 1}) div {most}")).withColumn("_own", F.pmod(F.xxhash64("d1"), F.col("_blocks")))
    dealt = dealt.withColumn("_other", F.explode(F.expr("sequence(0L, _blocks - 1)")))
    dealt = dealt.select(F.col(group).alias("_g"), F.least("_own", "_other").alias("_i"), F.greatest("_own", "_other").alias("_j"), "_own", *payload)
    names = [f.split(" ")[0] for f in schema.split(", ")]

    def out(found) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([r[k] for r in found], pa.int32() if name == "kind" else pa.int64()) for k, name in enumerate(names)], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_nothing()
        key, held = None, []
        for batch in batches:
            found: list[tuple] = []
            columns = [c.to_pylist() if not pa.types.is_list(c.type) else _arrays(c) for c in batch.columns]
            for row in zip(*columns, strict=True):
                if row[:3] != key:
                    if len(held) > 1:
                        found += work(*(list(c) for c in zip(*held, strict=True)), key[1], key[2])
                    key, held = row[:3], []
                held.append(row[3:])
            yield out(found)
        yield out(work(*(list(c) for c in zip(*held, strict=True)), key[1], key[2]) if len(held) > 1 else [])

    return dealt.repartition("_g", "_i", "_j").sortWithinPartitions("_g", "_i", "_j").mapInArrow(run, schema)


def _arrays(column: pa.ListArray) -> list[np.ndarray]:
    """Copies, so that a held group doesn't hold whole batches."""
    flat = column.flatten().to_numpy().view(np.uint64)
    cuts = np.concatenate([[0], np.cumsum(column.value_lengths().to_numpy())])
    return [flat[a:b].copy() for a, b in zip(cuts, cuts[1:], strict=False)]


def _components_of_sets(sets: DataFrame, docs: DataFrame, id_col: str, text_col: str, width: int, bands: Bands) -> DataFrame:
    """``node``, ``root``: the component, by its least digest, of every set that links with another."""
    met = settled(docs.sparkSession, lambda: buckets(sets), "join-buckets")
    involved = met.select("d1").distinct()
    sketches = sets.where("sketch is not null").join(involved, "d1", "left_semi").groupBy("d1").agg(F.min("n").alias("n"), F.min("sketch").alias("sketch"))
    sketches = materialize(sketches, "join-sketches")

    stars = materialize(met.where("d1 > least").select(F.col("d1").alias("a"), F.col("least").alias("b")).distinct(), "join-stars")
    links = settled(docs.sparkSession, lambda: _verified(_near(stars, sketches, bands), sets, docs, id_col, text_col, width, bands), "join-links")
    roots = components(links, "join-rounds")

    labelled = met.join(roots.withColumnRenamed("node", "d1"), "d1", "left").withColumn("root", F.coalesce("root", "d1"))
    unsettled = labelled.groupBy("word").agg(F.count(F.lit(1)).alias("members"), F.min("root").alias("_lo"), F.max("root").alias("_hi")).where("members > 2 and _lo < _hi")
    still = materialize(labelled.join(unsettled.select("word"), "word", "left_semi").select("word", "d1", "root"), "join-unsettled")
    twice = still.groupBy("d1").agg(F.count(F.lit(1)).alias("_k")).where("_k > 1").select("d1")
    still = still.join(twice, "d1", "left_semi")
    counts = still.groupBy("word").agg(F.count(F.lit(1)).alias("members"), F.min("root").alias("_lo"), F.max("root").alias("_hi")).where("_lo < _hi").select("word", "members")
    still = still.join(counts, "word").join(sketches, "d1")
    meet = lambda own, d, root, n, sketch, i, j: bucket_meetings(d, root, own, n, sketch, i, j, bands)
    met_again = materialize(_by_group(still, "word", "members", BLOCK, ["d1", "root", "n", "sketch"], meet, "kind int, a bigint, b bigint").distinct(), "join-meetings")

    # Components that may link are one group; each set of it that has a possible partner goes there once, whole.
    grouped = components(met_again.where("kind = 0").select("a", "b"), "join-rounds").select(F.col("node").alias("root"), F.col("root").alias("group"))
    possible = met_again.where("kind = 1").select(F.col("a").alias("d1"), F.col("b").alias("root"))
    possible = materialize(possible.join(grouped, "root", "left").withColumn("group", F.coalesce("group", "root")), "join-possible")
    whole = _whole_sets(possible.select("d1"), sets, docs, id_col, text_col, width)
    possible = possible.join(whole, "d1")
    sizes = possible.groupBy("group").agg(F.sum(F.size("s").cast("long")).alias("shingles"))
    link = lambda own, d, root, s, i, j: bucket_links(d, root, own, s, i, j, bands)
    more = materialize(_by_group(possible.join(sizes, "group"), "group", "shingles", BLOCK_SHINGLES, ["d1", "root", "s"], link, "a bigint, b bigint").distinct(), "join-more-links")
    roots = components(links.unionByName(more), "join-rounds")
    return roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct())


def linked_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """One row per document: id, ``n_shingles``, ``component_id`` (the smallest id reachable by links)."""
    spark, bands = docs.sparkSession, Bands(num, den)
    sets = materialize(document_sets(docs, id_col, text_col, width, bands), "join-sets-by-document")
    roots = settled(spark, lambda: _components_of_sets(sets, docs, id_col, text_col, width, bands), "join-roots")

    rows = sets.where("n > 0").select("_id", "n", "d1", "d2").join(roots.withColumnRenamed("node", "d1"), "d1", "left")
    # A set without links is a class by its whole digest.
    rows = rows.select("_id", "n", F.coalesce("root", "d1").alias("_r1"), F.when(F.col("root").isNull(), F.col("d2")).otherwise(F.lit(0)).alias("_r2"))
    ids = rows.groupBy("_r1", "_r2").agg(F.min("_id").alias("_least"))
    found = rows.join(ids, ["_r1", "_r2"]).select("_id", "n", "_least")
    alone = sets.where("n = 0").select("_id", "n", F.col("_id").alias("_least"))
    return found.unionByName(alone).select(F.col("_id").alias(id_col), F.col("n").alias("n_shingles"), F.col("_least").alias("component_id"))


def one_per_class(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of ``docs`` whose id is the smallest of their class, with all their columns.

    The ids that go are few, as a rule, and then they are broadcast and no text is moved. A repeated id stays if one of its rows does.
    """
    classes = materialize(linked_classes(docs, id_col, text_col, **options), "join-classes")
    least = F.col(id_col).eqNullSafe(F.col("component_id"))
    stay = classes.where(least).select(F.col(id_col).alias("_stay")).distinct()
    go = classes.where(~least).select(F.col(id_col).alias("_go")).distinct()
    go = materialize(go.join(stay, F.col("_go").eqNullSafe(F.col("_stay")), "left_anti"), "join-dropped")
    side = F.broadcast(go) if go.count() <= BROADCAST_ROWS else go
    rows = docs.select(F.struct("*").alias("_doc"), F.col(id_col).alias("_id"))
    return rows.join(side, F.col("_id").eqNullSafe(F.col("_go")), "left_anti").select("_doc.*")
