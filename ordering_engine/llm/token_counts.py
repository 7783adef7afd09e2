"""Token counts by heap-and-linked-list byte-pair merging.

A piece of text is a list of byte symbols, linked both ways. A heap holds the rank and place of
every adjacent pair that may merge; the lowest rank is popped, the pair becomes one symbol and its
new neighbours enter the heap. The count is the initial number of symbols less the merges: symbols
are strings and no identifier is ever made. Counts of pieces are remembered, up to a bound.

Defined results: a null or empty text has 0 bytes and 0 tokens; special strings inside a text count
as one token each, as the library does; repeated rows and ids are counted row by row; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import heapq
import json
import re
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .shared import kept, raw_texts

#: The byte-level split of the public vocabulary.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Pieces of text whose counts a worker remembers.
MEMO_ENTRIES = 600_000
MEMO_CHARS = 40
#: From this lead byte on (U+0540), the regex module's character tables and the library's differ in places.
FOREIGN = re.compile(rb"[\xd5-\xff]")
#: A space before white space or the end, or white space beyond ASCII: there a space isn't a sure piece boundary.
UNSURE = tuple(f" {c}" for c in " \t\n\r\x0b\x0c\x1c\x1d\x1e\x1f") + ("\x85", "\xa0")


def byte_symbols() -> list[str]:
    """The printable stand-in of each byte in byte-level vocabularies: printable ones stand for themselves, others follow from 256 on."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = iter(range(256, 512))
    return [chr(b) if b in set(own) else chr(next(rest)) for b in range(256)]


class MergeCounter:
    """Counts the tokens of texts under the merge ranks of a byte-level ``.json`` vocabulary."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        pairs = (m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"])
        self.ranks = {(a, b): rank for rank, (a, b) in enumerate(pairs)}
        self.symbols = byte_symbols()
        self.split = regex.compile(SPLIT)
        self.specials = [t["content"] for t in spec.get("added_tokens", []) if t["content"]]
        self.special = regex.compile("|".join(map(regex.escape, sorted(self.specials, key=len, reverse=True)))) if self.specials else None
        self.path, self.library = path, None
        self.pieces, self.chunks = _Memo(self.merged), _Memo(self._chunk)

    def merged(self, piece: str) -> int:
        """Symbols left of one piece once no adjacent pair has a rank."""
        symbol = list(map(self.symbols.__getitem__, piece.encode("utf-8")))
        n = len(symbol)
        place = 1 << n.bit_length()  # a heap entry is rank * place + left symbol: one comparison, lowest rank and then leftmost first
        ranks = self.ranks.get
        heap = [r * place + i for i, r in enumerate(map(ranks, zip(symbol, symbol[1:]))) if r is not None]
        heapq.heapify(heap)
        pop, push = heapq.heappop, heapq.heappush
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        merges = 0
        while heap:
            rank, i = divmod(pop(heap), place)
            left, j = symbol[i], after[i]
            if left is None or j >= n or ranks((left, right := symbol[j])) != rank:
                continue  # one of the two has merged meanwhile
            symbol[i] = both = left + right
            symbol[j] = None
            merges += 1
            after[i] = k = after[j]
            if k < n:
                before[k] = i
                if (r := ranks((both, symbol[k]))) is not None:
                    push(heap, r * place + i)
            h = before[i]
            if h >= 0 and (r := ranks((symbol[h], both))) is not None:
                push(heap, r * place + h)
        return n - merges

    def _chunk(self, chunk: str) -> int:
        return sum(map(self.pieces.__getitem__, self.split.findall(chunk)))

    def _plain(self, text: str, foreign: bool) -> int:
        if foreign:
            return sum(map(self.pieces.__getitem__, self._library_pieces(text)))
        if text.endswith(" ") or any(p in text for p in UNSURE):
            return self._chunk(text)
        head, *rest = text.split(" ")
        return self.chunks[head] + sum(map(self.chunks.__getitem__, [f" {x}" for x in rest]))

    def _library_pieces(self, text: str) -> list[str]:
        if self.library is None:
            from tokenizers import Tokenizer

            self.library = Tokenizer.from_file(self.path).pre_tokenizer
        return [text[a:b] for _, (a, b) in self.library.pre_tokenize_str(text)]

    def count(self, raw: bytes) -> int:
        text, foreign = raw.decode("utf-8", "replace"), FOREIGN.search(raw) is not None
        if self.special is None or not any(s in text for s in self.specials):
            return self._plain(text, foreign) if text else 0
        parts = self.special.split(text)
        return len(parts) - 1 + sum(self._plain(p, foreign) for p in parts if p)


class _Memo(dict):
    """Remembers a function of short strings, and starts afresh when full."""

    def __init__(self, f):
        self.f = f

    def __missing__(self, key: str) -> int:
        value = self.f(key)
        if len(key) <= MEMO_CHARS:
            if len(self) >= MEMO_ENTRIES:
                self.clear()
            self[key] = value
        return value


def counter(path: str) -> MergeCounter:
    return kept(("token_counts", path), lambda: MergeCounter(path))


def token_counts(docs: DataFrame, vocabulary: str, limit: int = 512, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, ``n_bytes``, ``n_tokens``, ``over_limit``. ``vocabulary``: path of the ``.json`` file on every executor."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = counter(vocabulary)
        for batch in batches:
            texts = list(raw_texts(batch.column(1)))
            n = [tokens.count(t) for t in texts]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([len(t) for t in texts], pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())],
                names=[id_col, "n_bytes", "n_tokens", "over_limit"],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(count, f"`{id_col}` {kind}, n_bytes bigint, n_tokens bigint, over_limit boolean")
