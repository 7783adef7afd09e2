"""I-Match fingerprints with randomised lexicons.

The lexicon is the terms within a chosen band of inverse document frequency, counted over all
documents. Randomised subsets of it are drawn by keyed hash, some with many terms and some with few.
A text's fingerprint has one hash per subset: of its distinct, sorted terms in that subset. A text with hardly a term of the
lexicon has as well the hashes of subsets of all its terms. The
likeness of two fingerprints is the share of equal hashes among the subsets where either has terms,
in the group of subsets that is fine enough to tell and still has enough of them occupied.

Which terms are frequent enough is found without shuffling all terms: a term with a share of all
documents has that share in some slice of them, so slices propose their frequent terms and a second
pass counts the proposed ones exactly. If the proposals outgrow ``broadcast_terms``, all terms are
counted by one aggregation instead. The lexicon itself holds at most (terms per document / least
share) terms, whatever the number of documents.

Documents follow each other by descending id without a sort in one place: ids, with hashes of the texts, are dealt to ranges
of even size, of which only the largest entries reach the driver; texts are then moved once, to the task of their range.

Defined results: a null text counts as empty; texts without a lexicon term are hashed by all their
terms; equal texts have equal fingerprints; rows with the same id follow each other in the order of their texts' hashes; a null
id comes last; a single document is its own next; an empty table gives an empty result; other columns
are ignored.
"""

from __future__ import annotations

import hashlib
import uuid
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .shared import STEP, kept, mixed, raw_texts

#: ASCII letters in lower case, other ASCII that isn't a letter or digit as a space.
FOLD = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or chr(b).isalnum() else 32 for b in range(256))
#: Groups of randomised subsets: a term is in a subset of the group with this probability.
SHARES = (1 / 2, 1 / 8, 1 / 32, 1 / 128, 1 / 512)
PER_GROUP = 32
HEX = 4
EMPTY = "-" * HEX
#: Texts with fewer terms of the lexicon are hashed by all their terms as well, in the first groups of subsets.
FEW, GROUPS_OF_ALL = 4, 2


def terms(raw: bytes) -> set[bytes]:
    return set(raw.translate(FOLD).split())


def _proposals(docs: DataFrame, text_col: str, least: float) -> DataFrame:
    def propose(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seen: Counter[bytes] = Counter()
            for raw in raw_texts(batch.column(0)):
                seen.update(terms(raw))
            frequent = [t for t, n in seen.items() if n >= least * batch.num_rows]
            yield pa.RecordBatch.from_arrays([pa.array(frequent, pa.binary())], names=["term"])

    return docs.select(text_col).mapInArrow(propose, "term binary").distinct()


def _counts(docs: DataFrame, text_col: str, wanted) -> DataFrame:
    """Document frequency of the terms in the broadcast ``wanted``, or of all terms if that is None."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only = None if wanted is None else wanted.value
        seen: Counter[bytes] = Counter()

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(list(seen.keys()), pa.binary()), pa.array(list(seen.values()), pa.int64())], names=["term", "n"])

        for batch in batches:
            for raw in raw_texts(batch.column(0)):
                seen.update(terms(raw) if only is None else terms(raw) & only)
            if len(seen) > 500_000:
                yield out()
                seen.clear()
        yield out()

    return docs.select(text_col).mapInArrow(count, "term binary, n bigint").groupBy("term").agg(F.sum("n").alias("n"))


def lexicon(docs: DataFrame, text_col: str = "text", least: float = 0.001, most: float = 0.1, broadcast_terms: int = 2_000_000) -> list[bytes]:
    """Terms in at least ``least`` (and 2 documents) and at most ``most`` of all documents, sorted."""
    n_docs = docs.count()
    proposed = _proposals(docs, text_col, least)
    proposed = [r[0] for r in proposed.limit(broadcast_terms + 1).collect()]
    wanted = docs.sparkSession.sparkContext.broadcast(frozenset(map(bytes, proposed))) if len(proposed) <= broadcast_terms else None
    found = _counts(docs, text_col, wanted).where((F.col("n") >= max(2, least * n_docs)) & (F.col("n") <= most * n_docs))
    return sorted(bytes(r[0]) for r in found.select("term").collect())


def _subsets(hashes: np.ndarray, seed: int, groups: int) -> np.ndarray:
    """Whether each term, given by its hash, is in each subset of the first ``groups`` groups."""
    number = np.arange(groups * PER_GROUP, dtype=np.uint64) + np.uint64(1 + seed * 1_000_003)
    least = np.repeat(np.array([int(share * 2**64) for share in SHARES[:groups]], np.uint64), PER_GROUP)
    out = np.empty((len(hashes), len(number)), bool)
    for at in range(0, len(hashes), 1 << 16):
        out[at : at + (1 << 16)] = mixed(hashes[at : at + (1 << 16), None] ^ mixed(number * STEP)[None, :]) < least
    return out


def _set_hashes(terms_in_order: np.ndarray, member: np.ndarray) -> str:
    """One hash per subset of the terms in it, as text."""
    subset, at = np.nonzero(member.T)
    flat, ends = memoryview(terms_in_order[at].tobytes()), np.searchsorted(subset, np.arange(member.shape[1]), "right").tolist()
    width, start, out = terms_in_order.itemsize, 0, []
    for end in ends:
        out.append(xxhash.xxh64_hexdigest(flat[start * width : end * width])[:HEX] if end > start else EMPTY)
        start = end
    return "".join(out)


class Fingerprinter:
    """Fingerprints under a sorted lexicon; subset membership follows from a keyed hash of the term."""

    def __init__(self, words: list[bytes], seed: int = 0):
        self.seed = seed
        self.number = {word: k for k, word in enumerate(words)}
        self.words = frozenset(words)
        self.hashes = np.array([xxhash.xxh64_intdigest(w) for w in words], np.uint64)
        self.member = _subsets(self.hashes, seed, len(SHARES))

    def fingerprint(self, raw: bytes) -> str:
        own = terms(raw)
        known = np.array(sorted(map(self.number.__getitem__, own & self.words)), np.int64)
        # The terms' hashes in the order of the terms, so that a lexicon's numbering doesn't enter.
        out = _set_hashes(self.hashes[known], self.member[known])
        if len(known) < FEW:
            every = np.array([xxhash.xxh64_intdigest(t) for t in sorted(own)], np.uint64)
            out += "+" + _set_hashes(every, _subsets(every, self.seed, GROUPS_OF_ALL))
        return out


def likeness(a: str, b: str) -> float:
    """0 to 1; 1 for equal fingerprints."""
    if a == b:
        return 1.0
    best = 0.0
    for own, other in zip(a.split("+"), b.split("+"), strict=False):
        for start in range(0, len(own), PER_GROUP * HEX):
            pairs = [(own[k : k + HEX], other[k : k + HEX]) for k in range(start, start + PER_GROUP * HEX, HEX)]
            occupied = [x == y for x, y in pairs if x != EMPTY or y != EMPTY]
            if len(occupied) >= PER_GROUP // 2:
                best = max(best, sum(occupied) / len(occupied))
    return best


def _fingerprinter(token: str, words: list[bytes], seed: int) -> Fingerprinter:
    """One per worker process and lexicon."""
    return kept(("imatch", token), lambda: Fingerprinter(words, seed))


class _Ranges:
    """Ranges of (key, hash) pairs, given by the largest pair of each; range 0 holds the largest pairs."""

    def __init__(self, tops: list[tuple[int, int]]):
        tops = sorted(tops)
        self.k, self.h = (np.array([t[c] for t in tops], np.int64) for c in (0, 1))

    def _among(self, k: np.ndarray, h: np.ndarray) -> np.ndarray:
        """The number of tops below each pair."""
        low, high = np.searchsorted(self.k, k, "left"), np.searchsorted(self.k, k, "right")
        for i in np.flatnonzero(low < high):
            low[i] += np.searchsorted(self.h[low[i] : high[i]], h[i], "left")
        return low

    def places(self, k: np.ndarray, h: np.ndarray) -> list[list[int]]:
        """For each pair 2 * its range, and if it is the top of one, 2 * the range before that + 1: there its row closes."""
        n, at = len(self.k), self._among(k, h)
        top = (self.k[at] == k) & (self.h[at] == h)
        return [[2 * (n - 1 - a), 2 * ((n - 2 - a) % n) + 1] if t else [2 * (n - 1 - a)] for a, t in zip(at.tolist(), top.tolist(), strict=True)]


def _with_successors(docs: DataFrame, id_col: str, text_col: str, partition_bytes: int) -> DataFrame:
    """Rows dealt by descending id: ``_part``, ``_extra``, ``doc_id``, ``_text``.

    Each part ends with the row (``_extra`` 1) that follows its last one: the first of the next part,
    and after the last part the first of all.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).alias("doc_id"), text.alias("_text"), F.coalesce(F.col(id_col).cast("long"), F.lit(-(1 << 63))).alias("_k"), F.xxhash64(text).alias("_h"))
    total = docs.agg(F.sum(F.octet_length(text_col))).first()[0] or 0
    n = int(max(min(docs.sparkSession.sparkContext.defaultParallelism * 4, 4096), -(-total // partition_bytes)))
    dealt = rows.select("_k", "_h").repartitionByRange(n, "_k", "_h").groupBy(F.spark_partition_id()).agg(F.max(F.struct("_k", "_h")).alias("top"))
    tops = [(r.top._k, r.top._h) for r in dealt.collect()]
    ranges = _Ranges(tops)

    @F.pandas_udf(T.ArrayType(T.IntegerType()))
    def places(k: pd.Series, h: pd.Series) -> pd.Series:
        return pd.Series(ranges.places(k.to_numpy(), h.to_numpy()), dtype=object)

    rows = rows.withColumn("_place", F.explode(places("_k", "_h")))
    rows = rows.select(F.expr("_place div 2").cast("int").alias("_part"), (F.col("_place") % 2).alias("_extra"), "_k", "_h", "doc_id", "_text")
    return rows.repartitionById(max(1, len(tops)), F.col("_part")).sortWithinPartitions("_part", "_extra", F.col("_k").desc(), F.col("_h").desc())


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: float = 0.001, most: float = 0.1, seed: int = 0, partition_bytes: int = 64 << 20) -> DataFrame:
    """One row per document: doc_id, ``n_chars``, ``edited_sha256``, ``fingerprint``, ``edited_fingerprint``, ``near_edited``, ``near_next``.

    The edited text has its last half of characters replaced by the first as many of the next document.
    """
    words, token = docs.sparkSession.sparkContext.broadcast(lexicon(docs, text_col, least, most)), uuid.uuid4().hex
    kind = docs.schema[id_col].dataType
    fields = T.StructType().add("doc_id", kind).add("n_chars", "long").add("edited_sha256", "string").add("fingerprint", "string").add("edited_fingerprint", "string").add("near_edited", "double").add("near_next", "double")
    names, arrow = fields.fieldNames(), [f.type for f in to_arrow_schema(fields)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make = _fingerprinter(token, words.value, seed).fingerprint
        last = None  # (part, id, text, fingerprint) of the row that waits for its next
        done = -1  # the part whose closing row has come
        for batch in batches:
            out = []
            for part, extra, doc, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(4).to_pylist(), raw_texts(batch.column(5)), strict=True):
                if extra and done == part:
                    continue
                text = raw.decode("utf-8", "replace")
                own = make(raw)
                if last is not None and last[0] == part:
                    n = len(last[2])
                    edited = (last[2][: n - n // 2] + text[: n // 2]).encode("utf-8")
                    changed = make(edited)
                    out.append((last[1], n, hashlib.sha256(edited).hexdigest(), last[3], changed, likeness(last[3], changed), likeness(last[3], own)))
                last, done = (None, part) if extra else ((part, doc, text, own), done)
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), arrow, strict=True)], names=names)

    return _with_successors(docs, id_col, text_col, partition_bytes).mapInArrow(run, fields)

