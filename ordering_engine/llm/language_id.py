"""Language identification by prediction by partial matching over bytes.

Each language has a context tree of bytes up to ``order`` deep, with frozen counts. A byte seen in
its context costs -log2(count / (n + d)), with n the context's count and d its distinct successors;
any other byte costs the escape, -log2(d / (n + d)), and its cost in the next shorter context,
renormalised over the bytes the longer context has not seen. Below order 0 bytes are equally likely.
So every context holds an exact probability distribution over all 256 bytes, and a text's score in a
language is its exact code length in bits. The language with the shortest code wins; ``score`` is its
posterior probability with equal priors.

The trees are sparse: for each length there is one hash table of the grams that any language has seen, with their
costs in every language, and one of the contexts, with their escapes. A byte is looked up with its longest context; where that
gram is unknown, its context's escape is added and the next shorter gram is looked up. The tables grow with the grams
of the sample, never with the alphabet or the corpus. Whole texts are scored in bounded slices.

The counts come from a bounded sample of labelled rows: at most ``sample_rows`` whole texts per language, those of smallest hash
of the id. The bound is on rows alone, so a language of long texts is learned as well as one of short ones.

Defined results: a null text, or one without a letter, is ``und`` with score 0; with no labelled row
every text is ``und``; rows with a null label teach nothing; ties go to the first language in
alphabetical order; repeated rows are judged row by row; other columns are ignored.
"""

from __future__ import annotations

import re
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import keep_nothing, kept, raw_texts

UNDETERMINED = "und"
LETTER = re.compile(r"[^\W\d_]")
#: Bytes of text that a worker scores at a time.
SLICE_BYTES = 1 << 19


def prepared(raw: bytes) -> bytes:
    """Lower-cased text, so that capitals and headlines read as the same language."""
    return raw.lower() if raw.isascii() else raw.decode("utf-8", "replace").lower().encode("utf-8")


def grams(raw: bytes, order: int) -> np.ndarray:
    """Every byte with the ``order`` bytes before it, as one number; before the text stand zeros."""
    return _after(b"\0" * order + prepared(raw), order)


def _after(raw: bytes, order: int) -> np.ndarray:
    b = np.frombuffer(raw, np.uint8).astype(np.uint64)
    n = len(b) - order
    key = np.zeros(n, np.uint64)
    for k in range(order + 1):
        key = (key << np.uint64(8)) | b[k : k + n]
    return key


@dataclass(frozen=True)
class Model:
    """Frozen counts: gram ``keys[i]`` occurred ``counts[i]`` times in language ``languages[lang[i]]``."""

    languages: tuple[str, ...]
    order: int
    lang: np.ndarray
    keys: np.ndarray
    counts: np.ndarray


class _Places:
    """The place of each of some distinct keys, by open addressing in a table that is at most a quarter full."""

    def __init__(self, keys: np.ndarray):
        self.keys = keys
        bits = max(6, (4 * len(keys)).bit_length())
        self.shift, self.mask = np.uint64(64 - bits), (1 << bits) - 1
        self.place = np.full(1 << bits, -1, np.int32)
        at, left = self._start(keys), np.arange(len(keys))
        while len(left):
            free = left[self.place[at[left]] < 0]
            self.place[at[free]] = free  # of several on one slot the last stays, the others go on
            left = left[self.place[at[left]] != left]
            at[left] = (at[left] + 1) & self.mask

    def _start(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Place of each key, -1 where there is none."""
        at = self._start(keys)
        place = self.place[at]
        if not len(self.keys):
            return place
        on = np.flatnonzero((place >= 0) & (self.keys[place] != keys))
        while len(on):
            at[on] = (at[on] + 1) & self.mask
            place[on] = self.place[at[on]]
            on = on[(place[on] >= 0) & (self.keys[place[on]] != keys[on])]
        return place


def _tail(keys: np.ndarray, length: int) -> np.ndarray:
    """The last ``length`` bytes of each gram."""
    return keys & np.uint64((1 << 8 * length) - 1)


class Scorer:
    """The context trees of a model, all languages side by side."""

    def __init__(self, model: Model):
        self.order, self.languages = model.order, model.languages
        self.symbol = np.arange(256, dtype=np.int64)
        count = len(model.languages)
        self.single = np.full((256, max(count, 1)), 8.0, np.float32)
        self.grams: list[_Places] = []
        self.costs: list[np.ndarray] = []
        self.contexts: list[_Places] = []
        self.escapes: list[np.ndarray] = []
        if count:
            self._grow(model, count)

    def _grow(self, model: Model, count: int) -> None:
        for length in range(self.order + 1):
            keys, at = np.unique(_tail(model.keys, length + 1), return_inverse=True)
            seen = np.stack([np.bincount(at[own], model.counts[own], len(keys)) for own in (model.lang == k for k in range(count))], 1)
            before, of = np.unique(keys >> np.uint64(8), return_inverse=True)
            added = lambda values, of=of, size=len(before): np.stack([np.bincount(of, v, size) for v in values.T], 1)
            n, d = added(seen), added((seen > 0).astype(float))
            with np.errstate(divide="ignore", invalid="ignore"):
                own = -np.log2(seen / (n + d)[of])
                if length:
                    shorter = self._cost(_tail(keys, length), length - 1).astype(np.float64)
                    left = 1.0 - added(np.where(seen > 0, np.exp2(-shorter), 0.0))
                    escape = np.where(n > 0, np.log2(np.maximum(left, 1e-12)) - np.log2(d / (n + d)), 0.0)
                    self.costs.append(np.where(seen > 0, own, escape[of] + shorter).astype(np.float32))
                    self.contexts.append(_Places(before))
                    self.escapes.append(np.append(escape, np.zeros((1, count)), 0).astype(np.float32))  # the last row is that of unknown contexts
                    self.grams.append(_Places(keys))
                else:
                    unseen = np.where(n > 0, np.log2((n + d) / np.maximum(d, 1)), 0.0) + np.log2(np.maximum(256 - d, 1))
                    self.single = np.broadcast_to(unseen, (256, count)).astype(np.float32)
                    self.single[keys.astype(np.int64)] = np.where(seen > 0, own, unseen)

    def _cost(self, keys: np.ndarray, length: int) -> np.ndarray:
        """Cost of the last byte of each gram after the ``length`` bytes before it, in every language."""
        if not length or not self.grams:
            return self.single[_tail(keys, 1).astype(np.int64)]
        place = self.grams[length - 1].find(keys)
        out = self.costs[length - 1][place]
        new = np.flatnonzero(place < 0)
        if len(new):
            out[new] = self.escapes[length - 1][self.contexts[length - 1].find(keys[new] >> np.uint64(8))] + self._cost(_tail(keys[new], length), length - 1)
        return out

    def _bits(self, symbols: np.ndarray) -> np.ndarray:
        """Cost of each byte after the first ``order`` ones."""
        n = len(symbols) - self.order
        keys, b = np.zeros(n, np.uint64), symbols.astype(np.uint64)
        for k in range(self.order + 1):
            keys = (keys << np.uint64(8)) | b[k : k + n]
        return self._cost(keys, self.order)

    def code_lengths(self, texts: list[bytes]) -> np.ndarray:
        """Bits of each text in each language."""
        total = np.zeros((len(texts), len(self.languages)))
        symbol, most = self.symbol.astype(np.uint8), max(256, SLICE_BYTES * 4 // max(4, len(self.languages)))
        pad = b"\0" * self.order
        batch: list[int] = []
        held = 0
        for i, raw in enumerate(texts):
            if len(raw) > most:
                whole = pad + raw
                for at in range(0, len(raw), most):
                    part = np.frombuffer(whole[at : at + most + self.order], np.uint8)
                    total[i] += self._bits(symbol[part]).sum(0, dtype=np.float64)
                continue
            batch.append(i)
            held += len(raw)
            if held > most:
                self._score(texts, batch, pad, symbol, total)
                batch, held = [], 0
        self._score(texts, batch, pad, symbol, total)
        return total

    def _score(self, texts, batch, pad, symbol, total) -> None:
        batch = [i for i in batch if texts[i]]
        if not batch:
            return
        joined = np.frombuffer(b"".join(pad + texts[i] for i in batch), np.uint8)
        bits = self._bits(symbol[joined])
        sizes = np.array([len(texts[i]) for i in batch])
        starts = np.concatenate([[0], np.cumsum(sizes + self.order)[:-1]])
        cuts = np.stack([starts, np.minimum(starts + sizes, len(bits))], 1).ravel()
        cuts = cuts[:-1] if cuts[-1] == len(bits) else cuts  # every other sum is of the zeros between two texts
        total[batch] = np.add.reduceat(bits, cuts, axis=0, dtype=np.float64)[::2]


def sample(labelled: DataFrame, id_col: str, text_col: str, lang_col: str, sample_rows: int, spread: int) -> DataFrame:
    """``_lang``, ``_text`` of at most ``sample_rows`` rows per language, those of smallest hash of the id.

    First only labels and hashes are ranked, in ``spread`` parts a language, which gives each language's largest hash of the
    sample; then the texts up to it are read. Where many rows share that hash, the last step keeps the bound.
    """
    rows = labelled.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(lang_col).alias("_lang"), F.col(text_col).alias("_text"), F.xxhash64(F.col(id_col)).alias("_h"))
    part = Window.partitionBy("_lang", F.pmod("_h", F.lit(spread))).orderBy("_h")
    few = rows.select("_lang", "_h").withColumn("_r", F.row_number().over(part)).where(F.col("_r") <= sample_rows)
    own = Window.partitionBy("_lang").orderBy("_h")
    # One row per language that is learned, as the model itself has.
    last = few.withColumn("_r", F.row_number().over(own)).where(F.col("_r") <= sample_rows).groupBy("_lang").agg(F.max("_h").alias("_last"))
    near = rows.join(F.broadcast(last), "_lang").where("_h <= _last").withColumn("_r", F.row_number().over(Window.partitionBy("_lang").orderBy("_h", F.xxhash64("_text"))))
    return near.where(F.col("_r") <= sample_rows).select("_lang", "_text")


def train(labelled: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", order: int = 3, sample_rows: int = 512, spread: int = 16) -> Model:
    """Frozen counts from at most ``sample_rows`` whole texts per language."""
    rows = sample(labelled, id_col, text_col, lang_col, sample_rows, spread).repartition(spread)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_nothing()
        for batch in batches:
            for lang, raw in zip(batch.column(0).to_pylist(), raw_texts(batch.column(1)), strict=True):
                whole = b"\0" * order + prepared(raw)
                for at in range(0, len(whole) - order, SLICE_BYTES):
                    keys, n = np.unique(_after(whole[at : at + SLICE_BYTES + order], order), return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array([lang] * len(keys), pa.string()), pa.array(keys.view(np.int64)), pa.array(n, pa.int64())], names=["lang", "gram", "n"])

    found = rows.mapInArrow(count, "lang string, gram bigint, n bigint").groupBy("lang", "gram").agg(F.sum("n").alias("n")).toPandas()
    found = found.sort_values(["lang", "gram"])
    languages = tuple(sorted(found["lang"].unique()))
    place = {name: i for i, name in enumerate(languages)}
    return Model(languages, order, found["lang"].map(place).to_numpy(np.int16), found["gram"].to_numpy(np.int64).view(np.uint64), found["n"].to_numpy(np.int64))


def predict(docs: DataFrame, model: Model, text_col: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The columns ``keep`` of every row, with ``lang_pred``, ``score`` and ``bits_per_byte`` of the winner."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # its size is bounded by the sample
    names, token = list(model.languages), uuid.uuid4().hex

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = kept(("language_id", token), lambda: Scorer(shared.value)) if names else None
        for batch in batches:
            raw = list(raw_texts(batch.column(batch.num_columns - 1)))
            texts = [prepared(t) if LETTER.search(t.decode("utf-8", "replace")) else b"" for t in raw]
            lang, value, rate = [UNDETERMINED] * len(raw), np.zeros(len(raw)), np.zeros(len(raw))
            if names and raw:
                bits = scorer.code_lengths(texts)
                best = bits.argmin(1)
                value = 1.0 / np.exp2(np.maximum(bits.min(1, keepdims=True) - bits, -1000.0)).sum(1)
                size = np.array([len(t) for t in texts])
                lang = [names[b] if n else UNDETERMINED for b, n in zip(best, size, strict=True)]
                value = np.where(size > 0, value, 0.0)
                rate = np.where(size > 0, bits.min(1) / np.maximum(size, 1), 0.0)
            own = batch.columns[:-1]
            yield pa.RecordBatch.from_arrays([*own, pa.array(lang, pa.string()), pa.array(value, pa.float64()), pa.array(rate, pa.float64())], names=[*keep, "lang_pred", "score", "bits_per_byte"])

    fields = T.StructType([docs.schema[c] for c in keep]).add("lang_pred", "string").add("score", "double").add("bits_per_byte", "double")
    return docs.select(*keep, F.col(text_col).alias("_text")).mapInArrow(score, fields)


def held_out(doc_id: Column) -> Column:
    return F.pmod(F.crc32(doc_id.cast("string")), F.lit(3)) == 1


def identify(docs: DataFrame) -> DataFrame:
    """Learn from the rows that are not held out, predict all: doc_id, ``held_out``, ``lang_pred``, ``score``, ``bits_per_byte``."""
    model = train(docs.where(F.coalesce(~held_out(F.col("doc_id")), F.lit(True))))
    return predict(docs, model).withColumn("held_out", F.coalesce(held_out(F.col("doc_id")), F.lit(False))).select("doc_id", "held_out", "lang_pred", "score", "bits_per_byte")


def known_language(docs: DataFrame, least_score: float = 0.5) -> DataFrame:
    """The rows of ``docs`` in a learned language: those that are ``und`` or whose posterior is under ``least_score`` go."""
    model = train(docs.where(F.coalesce(~held_out(F.col("doc_id")), F.lit(True))))
    rows = docs.select(F.struct("*").alias("_row"), F.col("text"))
    judged = predict(rows, model, keep=("_row",))
    return judged.where((F.col("lang_pred") != UNDETERMINED) & (F.col("score") >= least_score)).select("_row.*")
