"""Best-fit packing with swap-based local search.

Documents become pieces of at most ``capacity`` tokens; only longer ones are cut, the short piece
first. Pieces are dealt by hash, with their row's number, into blocks of bounded size, whatever their source and however often
they repeat. In a block a best-fit pass fills bins, then local search moves one document, exchanges one for one, or two for
one, always from an emptier to a fuller bin, so the sum of squared fills grows until bins empty and no change is left.
Bins that stay clearly underfull are released, and their pieces are packed together in a second
round of fewer blocks. No block, and no task, depends on the number of documents.

Defined results: a null or empty text is one piece, the end token alone; repeated rows are packed
row by row; a null id is allowed; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import kept, materialize, raw_texts
from .token_counts import FOREIGN, SPLIT, UNSURE, _Memo, byte_symbols

#: A bin filled to less than this share is released to the second round.
RELEASE_BELOW = 0.98


class IdEncoder:
    """Ids of a text as little-endian 32-bit bytes, as the tokenizers library gives them.

    A single space before a visible character always begins a piece of the byte-level split, so
    the ids of a text are those of its space-led chunks, which repeat and are remembered. New chunks
    are encoded under the same vocabulary by the faster tiktoken; texts where the two could split
    differently, or with special strings, go to the tokenizers library whole.
    """

    def __init__(self, path: str):
        import tiktoken
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.specials = [t.content for t in self.library.get_added_tokens_decoder().values()]
        byte_of = {s: b for b, s in enumerate(byte_symbols())}
        ranks = {bytes(map(byte_of.__getitem__, t)): i for t, i in self.library.get_vocab(with_added_tokens=False).items() if all(c in byte_of for c in t) and t not in self.specials}
        self.chunk_ids = tiktoken.Encoding("vocabulary", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
        self.memo = _Memo(lambda chunk: np.array(self.chunk_ids(chunk), "<u4").tobytes())

    def encode(self, raw: bytes) -> bytes:
        text = raw.decode("utf-8", "replace")
        if FOREIGN.search(raw) or any(s in text for s in self.specials):
            return np.array(self.library.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        if text.endswith(" ") or any(p in text for p in UNSURE):
            return np.array(self.chunk_ids(text), "<u4").tobytes()
        head, *rest = text.split(" ")
        return self.memo[head] + b"".join(map(self.memo.__getitem__, [f" {x}" for x in rest]))


def encoder(path: str) -> IdEncoder:
    return kept(("packing", path), lambda: IdEncoder(path))


def pieces(docs: DataFrame, vocabulary: str, capacity: int = 1024, end_id: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: id, ``piece``, ``start``, ``length``, ``ids_crc32``."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(vocabulary).encode
        end = np.array([end_id], "<u4").tobytes()
        for batch in batches:
            row, piece, start, length, crc = [], [], [], [], []
            for i, raw in enumerate(raw_texts(batch.column(1))):
                ids = encode(raw) + end
                n = len(ids) // 4
                cuts = [0, *range(n % capacity or capacity, n + 1, capacity)]
                for k, (a, b) in enumerate(zip(cuts, cuts[1:])):
                    row.append(i)
                    piece.append(k)
                    start.append(a)
                    length.append(b - a)
                    crc.append(zlib.crc32(memoryview(ids)[4 * a : 4 * b]))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())],
                names=["doc_id", "piece", "start", "length", "ids_crc32"],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), text_col).mapInArrow(cut, f"doc_id {kind}, piece int, start bigint, length bigint, ids_crc32 bigint")


def best_fit(sizes: np.ndarray, capacity: int) -> list[list[int]]:
    """Bins of item numbers; longest items first, each into the fullest bin that takes it. Free rooms are a bit set."""
    bins: list[list[int]] = []
    by_room: list[list[int]] = [[] for _ in range(capacity + 1)]
    rooms = 0
    for i in np.argsort(-sizes, kind="stable").tolist():
        size = int(sizes[i])
        fitting = rooms >> size
        if fitting:
            room = size + (fitting & -fitting).bit_length() - 1
            b = by_room[room].pop()
            if not by_room[room]:
                rooms &= ~(1 << room)
            bins[b].append(i)
        else:
            room, b = capacity, len(bins)
            bins.append([i])
        room -= size
        if room:
            by_room[room].append(b)
            rooms |= 1 << room
    return bins


class LocalSearch:
    """Improves a packing by moves and exchanges that raise the sum of squared fills, until none does.

    Each change raises the sum, a whole number with a bound, so the search ends. What a bin can give away is looked up for all
    its documents and pairs at once: an item of a fuller bin can make way for as much as its own size and that bin's room,
    and of the items that can make way for some size the smallest gives the largest gain.
    """

    def __init__(self, sizes: np.ndarray, bins: list[list[int]], capacity: int):
        self.capacity = capacity
        fills = [int(sizes[b].sum()) for b in bins]
        self.full = [b for b, fill in zip(bins, fills, strict=True) if fill == capacity]
        self.open = [list(b) for b, fill in zip(bins, fills, strict=True) if fill < capacity]
        self.fill = np.array([fill for fill in fills if fill < capacity], np.int64)
        items = [(i, k) for k, b in enumerate(self.open) for i in b]
        # The items of open bins, largest first, with their bins.
        self.item = np.array([i for i, _ in sorted(items, key=lambda x: (-sizes[x[0]], x[0]))], np.int64)
        self.place = {int(i): at for at, i in enumerate(self.item)}
        self.size = sizes[self.item].astype(np.int64)
        bin_of = dict(items)
        self.bin = np.array([bin_of[int(i)] for i in self.item], np.int64)

    def run(self) -> list[list[int]]:
        improved = True
        while improved:
            improved = False
            for a in np.argsort(self.fill, kind="stable").tolist():
                while self.open[a] and self._improve(a):
                    improved = True
        return self.full + [b for b in self.open if b]

    def _swap(self, a: int, give: list[int], b: int, take: list[int]) -> None:
        """Places ``give`` of bin a and ``take`` of bin b change sides."""
        for places, source, target in ((give, a, b), (take, b, a)):
            for at in places:
                self.open[source].remove(int(self.item[at]))
                self.open[target].append(int(self.item[at]))
                self.bin[at] = target
                self.fill[source] -= self.size[at]
                self.fill[target] += self.size[at]

    def _improve(self, a: int) -> bool:
        """One change that takes tokens out of bin ``a`` into a bin at least as full."""
        fits = (self.fill >= self.fill[a]) & (self.fill < self.capacity)
        fits[a] = False
        room = np.where(fits, self.capacity - self.fill, 0)
        most = int(room.max(initial=0))
        if not most:
            return False
        own = sorted((self.place[i] for i in self.open[a]), key=lambda at: (-self.size[at], at))
        sizes = self.size[own]
        movable = np.flatnonzero(sizes <= most)
        if len(movable):  # the largest that has room elsewhere goes to the bin it fills best
            at = own[movable[0]]
            self._swap(a, [at], int(np.where(room >= self.size[at], room, self.capacity + 1).argmin()), [])
            return True
        # The smallest item that can make way for a size, for every size.
        among = np.flatnonzero(room[self.bin])
        limit = np.minimum(self.size[among] + room[self.bin[among]], 2 * self.capacity)
        smallest = np.full(2 * self.capacity + 2, 2 * self.capacity + 1)
        smallest[limit] = self.size[among]  # the last one written is the smallest
        smallest = np.minimum.accumulate(smallest[::-1])[::-1]
        gain = sizes - smallest[sizes]
        if gain.max() > 0:  # one for one
            give = [own[int(gain.argmax())]]
        else:  # two for one
            distinct, first = np.unique(sizes, return_index=True)
            twice = np.flatnonzero(sizes[:-1] == sizes[1:])
            i, k = np.triu_indices(len(distinct), 1)
            left, right = np.concatenate([first[i], twice]), np.concatenate([first[k], twice + 1])
            both = sizes[left] + sizes[right]
            gain = both - smallest[both]
            if not len(both) or gain.max() <= 0:
                return False
            best = int(gain.argmax())
            give = [own[left[best]], own[right[best]]]
        total = int(self.size[give].sum())
        take = among[np.flatnonzero((limit >= total) & (self.size[among] == smallest[total]))[0]]
        self._swap(a, give, int(self.bin[take]), [int(take)])
        return True


def pack_block(sizes: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bin number, offset and bin fill of each item."""
    whole = np.flatnonzero(sizes >= capacity)
    part = np.flatnonzero(sizes < capacity)
    packed = LocalSearch(sizes[part], best_fit(sizes[part], capacity), capacity).run() if len(part) else []
    number, offset, fill = (np.zeros(len(sizes), np.int64) for _ in range(3))
    number[whole], fill[whole] = np.arange(len(whole)), capacity
    for k, items in enumerate(packed, len(whole)):
        at = part[items]
        number[at], offset[at], fill[at] = k, np.cumsum(sizes[at]) - sizes[at], sizes[at].sum()
    return number, offset, fill


def _packed(rows: DataFrame, capacity: int, block_rows: int, first_block: int) -> tuple[DataFrame, int]:
    count = rows.count()
    blocks = max(1, -(-count // block_rows))
    # The row's number in its files deals repeated rows to all blocks.
    dealt = rows.withColumn("_block", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32", F.monotonically_increasing_id()), F.lit(blocks)) + first_block)

    def pack(block: pa.Table) -> pa.Table:
        block = block.sort_by([("length", "descending"), ("doc_id", "ascending"), ("piece", "ascending"), ("ids_crc32", "ascending")])
        number, offset, fill = pack_block(block["length"].to_numpy(), capacity)
        sequence = (block["_block"].to_numpy() << 32) + number
        kept = block.drop_columns(["_block"])
        for name, values in (("sequence_id", sequence), ("offset", offset), ("_fill", fill)):
            kept = kept.append_column(name, pa.array(values, pa.int64()))
        return kept

    fields = dealt.drop("_block").schema.add("sequence_id", "long").add("offset", "long").add("_fill", "long")
    return dealt.groupBy("_block").applyInArrow(pack, fields), first_block + blocks


def pack(cut: DataFrame, capacity: int = 1024, block_rows: int = 8192) -> DataFrame:
    """``cut`` (as ``pieces`` gives it) with ``sequence_id`` and ``offset``."""
    cut = materialize(cut, "packing-pieces")
    first, used = _packed(cut, capacity, block_rows, 0)
    first = materialize(first, "packing-first")
    kept = first.where(F.col("_fill") >= RELEASE_BELOW * capacity)
    again, _ = _packed(first.where(F.col("_fill") < RELEASE_BELOW * capacity).select(cut.columns), capacity, block_rows, used)
    return kept.unionByName(again).drop("_fill")


def pack_documents(docs: DataFrame, vocabulary: str, capacity: int = 1024) -> DataFrame:
    return pack(pieces(docs, vocabulary, capacity), capacity)
