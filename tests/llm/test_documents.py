"""Operators on documents, against plain Python on the same rows."""

import hashlib
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import public_tokenizers
import pytest
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from ordering_engine.llm import components, exact_dedup, imatch, language_id, packing, parity_join, shared, source_mix, token_counts

PATH = public_tokenizers.path("byte_bpe_50k.json")
LIBRARY = Tokenizer.from_file(PATH)
FOLD = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))


def fold(text):
    return (text or "").encode().translate(FOLD)


def rows(df):
    return [tuple(r) for r in df.collect()]


# Exact deduplication


@pytest.mark.parametrize("keep", ["min", "max"])
def test_exact_groups(odd, documents, keep):
    for docs in (odd, documents):
        given = [(r.doc_id, fold(r.text)) for r in docs.collect()]
        groups = defaultdict(list)
        for i, t in given:
            groups[t].append(i)
        best = {t: (min if keep == "min" else max)((i for i in ids if i is not None), default=None) for t, ids in groups.items()}
        want = Counter((i, best[t], len(groups[t]), i == best[t], hashlib.sha256(t).hexdigest()) for i, t in given)
        assert Counter(rows(exact_dedup.exact_groups(docs, keep=keep))) == want


def test_exact_groups_compare_bytes_behind_colliding_hashes(odd):
    from pyspark.sql import functions as F

    one = exact_dedup.exact_groups(odd, keep="max", content_hash=lambda text: F.lit("same").cast("binary"))
    assert Counter(rows(one)) == Counter(rows(exact_dedup.exact_groups(odd, keep="max")))


def test_drop_copies(odd, none, documents):
    kept = exact_dedup.drop_copies(odd, keep="max")
    assert kept.columns == odd.columns
    assert sorted((r.doc_id is None, r.doc_id or 0) for r in kept.collect()) == [(False, i) for i in (2, 4, 5, 7, 8, 10, 11)] + [(True, 0)]
    assert exact_dedup.drop_copies(none).count() == 0 and exact_dedup.exact_groups(none).count() == 0
    assert exact_dedup.drop_copies(documents, keep="max").count() == len({fold(r.text) for r in documents.collect()})


# Token counts and packing


def test_token_counts_match_the_library(odd, none, documents):
    for docs in (odd, documents):
        want = Counter()
        for r in docs.collect():
            n = len(LIBRARY.encode(r.text or "", add_special_tokens=False).ids)
            want[(r.doc_id, len((r.text or "").encode()), n, n > 512)] += 1
        assert Counter(rows(token_counts.token_counts(docs, PATH))) == want
    assert token_counts.token_counts(none, PATH).count() == 0


def test_token_counts_of_awkward_strings():
    rng = np.random.default_rng(1)
    alphabet = [*"ab 1!'\n\t\r  é\x85ж中🎉\x1c՘𐥀", "<|endoftext|>", "'re", " the", "ing"]
    count = token_counts.MergeCounter(PATH).count
    for _ in range(3000):
        text = "".join(rng.choice(alphabet) for _ in range(rng.integers(0, 30)))
        assert count(text.encode()) == len(LIBRARY.encode(text, add_special_tokens=False).ids), repr(text)


def test_packing(odd, none, documents):
    for docs in (odd, documents):
        packed = packing.pack_documents(docs, PATH).toPandas()
        want = Counter()
        for r in docs.collect():
            ids = np.array([*LIBRARY.encode(r.text or "", add_special_tokens=False).ids, 2], "<u4")
            first = len(ids) % 1024 or 1024
            cuts = [0, *range(first, len(ids) + 1, 1024)]
            for k, (a, b) in enumerate(zip(cuts, cuts[1:])):
                want[(r.doc_id, k, a, b - a, zlib.crc32(ids[a:b].tobytes()))] += 1
        ids = [None if i != i else int(i) for i in packed.doc_id]
        assert Counter(zip(ids, packed.piece, packed.start, packed.length, packed.ids_crc32)) == want
        for _, s in packed.sort_values("offset").groupby("sequence_id"):
            assert s.length.sum() <= 1024 and (s.offset.to_numpy() == np.concatenate([[0], s.length.cumsum()[:-1]])).all()
        assert packed.sequence_id.nunique() <= -(-packed.length.sum() // 1024) + 2
    assert packing.pack_documents(none, PATH).count() == 0


def test_local_search_never_loses_and_improves_squares():
    rng = np.random.default_rng(5)
    for low, high in ((200, 400), (300, 700), (1, 1024)):
        sizes = rng.integers(low, high, 400)
        before = [[i] for i in range(len(sizes))]
        after = packing.LocalSearch(sizes, [list(b) for b in before], 1024).run()
        assert sorted(i for b in after for i in b) == list(range(len(sizes)))
        assert all(sizes[b].sum() <= 1024 for b in after) and len(after) < len(before)
        assert sum(sizes[b].sum() ** 2 for b in after) > (sizes**2).sum()


def test_local_search_frees_bins_that_best_fit_leaves():
    rng = np.random.default_rng(3)
    triples = []
    for _ in range(400):
        a = int(rng.integers(257, 450))
        b = int(rng.integers(257, 768 - a))
        triples += [a, b, 1024 - a - b]
    for sizes, least in ((np.array(triples), 20), (rng.integers(200, 401, 4000), 20), (rng.integers(340, 521, 2000), 0)):
        first = packing.best_fit(sizes, 1024)
        after = packing.LocalSearch(sizes, [list(b) for b in first], 1024).run()
        assert sorted(i for b in after for i in b) == list(range(len(sizes))) and all(sizes[b].sum() <= 1024 for b in after)
        assert len(after) <= len(first) - least
        # Nothing is left to move or to exchange, by trying everything.
        open_bins = sorted((b for b in after if sizes[b].sum() < 1024), key=lambda b: sizes[b].sum())
        for a in open_bins[:: max(1, len(open_bins) // 10)]:
            for b in open_bins:
                fill = sizes[b].sum()
                if b is not a and fill >= sizes[a].sum():
                    gives = {int(sizes[i]) for i in a} | {int(sizes[i] + sizes[k]) for i in a for k in a if i < k}
                    assert not any(0 < give - take <= 1024 - fill for give in gives for take in sizes[b]) and min(sizes[a]) > 1024 - fill


def test_repeated_rows_are_dealt_to_all_blocks(spark):
    rows = spark.range(6000).selectExpr("1L AS doc_id", "0 AS piece", "0L AS start", "300L AS length", "7L AS ids_crc32")
    packed = packing.pack(rows, block_rows=500).toPandas()
    assert len(packed) == 6000 and packed.sequence_id.nunique() <= 2000 + 24
    assert (packed.sequence_id // 2**32).value_counts().max() <= 750


# Source mix


def test_targets_and_taken(documents, odd, none):
    for docs in (documents, odd):
        got = source_mix.mix(docs).toPandas()
        size = Counter()
        for r in docs.collect():
            size[r.source] += len((r.text or "").encode().split())
        order = sorted((s for s in size if s is not None), key=lambda s: s.encode()) + ([None] if None in size else [])
        weight = {s: k % 3 + 1 for k, s in enumerate(order)}
        total, target, free = sum(size.values()), {}, set(order)
        while free:
            level = (total - sum(target.values())) / sum(weight[s] for s in free)
            over = {s for s in free if 3 * size[s] < level * weight[s]}
            if not over:
                target |= {s: level * weight[s] for s in free}
                break
            target |= {s: 3 * size[s] for s in over}
            free -= over
        assert len(got) == docs.count() and (got.taken <= 3 * got["size"]).all()
        assert sorted(set(zip(got.source_size, got.target.round(3)))) == sorted({(size[s], round(target[s], 3)) for s in order})
        if docs is documents:
            for (_, t), part in got.groupby(["source_size", "target"]):
                assert abs(part.taken.sum() - t) <= 0.01 * t + 40
    again = source_mix.mix(documents).toPandas().sort_values("doc_id").taken.tolist()
    assert again == source_mix.mix(documents.repartition(3)).toPandas().sort_values("doc_id").taken.tolist()
    assert source_mix.mix(none).count() == 0 and source_mix.mixed_documents(none).count() == 0


def test_every_source_gets_its_target(spark, documents, odd):
    """To the word, however small the source is beside the corpus."""
    big = spark.range(2000).selectExpr("id AS doc_id", "repeat('w ', 5000) AS text", "'z' AS source")
    few = spark.createDataFrame([(-1, "w " * 3, "a"), (-2, "w " * 100, "b"), (-3, "w " * 20, "b"), (-4, "w", "c")], big.schema)
    for docs in (documents, odd, big.unionByName(few)):
        for (source_size, target), part in source_mix.mix(docs).toPandas().groupby(["source_size", "target"]):
            sources = max(1, round(part["size"].sum() / source_size)) if source_size else 1
            assert part.taken.sum() == sources * int(target + 0.5)
            assert (part.taken >= target // source_size * part["size"]).all() if source_size else not part.taken.any()
    mixed = {r.doc_id: r["count"] for r in source_mix.mixed_documents(big.unionByName(few)).where("doc_id < 0").groupBy("doc_id").count().collect()}
    assert mixed == dict.fromkeys((-1, -2, -3, -4), 3)


def test_repeated_rows_are_spread_and_many_sources_found(spark):
    from pyspark.sql import functions as F

    same = spark.range(50_000).selectExpr("1L AS doc_id", "'a b c' AS text", "if(id % 2 = 0, 'x', 'y') AS source")
    sized = same.select(F.lit(3).alias("_key"), F.col("source"))
    numbers = source_mix._numbered(sized.repartition(5)).groupBy("_number").count()
    assert numbers.count() == 50_000 and numbers.agg(F.max("_number")).first()[0] == 49_999
    got = source_mix.mix(same, bucket_rows=1000).groupBy("source_size").agg(F.sum("taken").alias("taken"), F.max("taken").alias("most"))
    assert [(r.source_size, r.most) for r in got.collect()] == [(75_000, 6)] and got.first().taken == 150_000
    many = spark.range(3000).selectExpr("id AS doc_id", "repeat('w ', cast(1 + id % 40 AS int)) AS text", "concat('s', id % 500) AS source")
    per = source_mix.mix(many, block_words=16).join(many.select("doc_id", "source"), "doc_id").groupBy("source").agg(F.sum("taken").alias("taken"), F.first("target").alias("target"))
    assert all(r.taken == int(r.target + 0.5) for r in per.collect())
    points = [(i * source_mix.GOLDEN_32) % source_mix.RANGE_32 for i in range(400)]
    targets = spark.createDataFrame([(k, float(k % 7)) for k in range(300)], "_place int, target double")
    ends = np.cumsum([k % 7 for k in range(300)]) / sum(k % 7 for k in range(300)) * source_mix.RANGE_32
    got = {r.slot: (r._place, r.rank) for r in source_mix.schedule(targets, 2).collect()}
    place = [int(np.searchsorted(ends, x, "right")) for x in points]
    assert all(got[i] == (place[i], place[:i].count(place[i])) for i in range(400))


def test_mixed_documents(documents):
    mixed = source_mix.mixed_documents(documents)
    assert mixed.columns == documents.columns
    taken = {r.doc_id: r.taken / r["size"] for r in source_mix.mix(documents).collect()}
    times = Counter(r.doc_id for r in mixed.select("doc_id").collect())
    assert all(abs(times[i] - t) <= 0.5 for i, t in taken.items())


# Similarity join


def brute_classes(docs):
    sets = {}
    for r in docs:
        w = fold(r.text).split()
        sets.setdefault(r.doc_id, frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else frozenset())
    up = {i: i for i in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(sets)
    for k, i in enumerate(ids):
        for j in ids[k + 1 :]:
            a, b = sets[i], sets[j]
            if a and b and 0.8 * max(len(a), len(b)) <= min(len(a), len(b)) and 100 * len(a & b) >= 80 * len(a | b):
                x, y = root(i), root(j)
                up[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), root(i)) for i in ids}


def near_copies(spark, n=160):
    """A family around one text, edited so that some pairs link and many just don't, chains, and sets of four and five shingles."""
    rng = np.random.default_rng(7)
    base = [f"w{k}" for k in range(90)]
    texts = []
    for _ in range(n):
        own = list(base)
        for k in rng.choice(len(base), rng.integers(0, 4), replace=False):
            own[k] = f"e{rng.integers(1 << 30)}"
        texts.append(" ".join(own))
    texts += [" ".join(f"c{k}" for k in range(s, s + 60)) for s in range(0, 60, 3)]
    texts += ["a b c d e f g h", "a b c d e f g h i", "a b c", "A B C", "x", "", " ".join(f"p{k}" for k in range(40)) + " " + " ".join(base[:30])]
    return spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")


def test_join_against_brute_force(spark, documents):
    for docs in (near_copies(spark), documents):
        want = brute_classes(docs.collect())
        got = {r.doc_id: (r.n_shingles, r.component_id) for r in parity_join.linked_classes(docs).collect()}
        assert got == want
    family = near_copies(spark)
    kept = {r.doc_id for r in parity_join.one_per_class(family).collect()}
    assert kept == {i for i, (_, c) in brute_classes(family.collect()).items() if i == c}


def test_join_in_small_blocks(spark, monkeypatch):
    """Groups dealt into many blocks give the same classes."""
    monkeypatch.setattr(parity_join, "BLOCK", 7)
    monkeypatch.setattr(parity_join, "BLOCK_SHINGLES", 900)
    monkeypatch.setattr(parity_join, "BROADCAST_ROWS", 0)
    docs = near_copies(spark, 60)
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in parity_join.linked_classes(docs).collect()} == brute_classes(docs.collect())


def test_join_of_short_sets_whose_sketches_are_equal(spark):
    """Sets of four shingles in one group, the smallest that meet: they share three, and the fourth has the same bit."""
    memo, like = parity_join._WordHashes(), defaultdict(list)
    for k in range(1000):
        text = f"a b c d e f g x{k}"
        like[parity_join.parity_sketch(parity_join.shingles(text.encode(), 5, memo))].append(text)
    texts = max(like.values(), key=len)[:6]
    got = rows(parity_join.linked_classes(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")))
    assert sorted(got) == [(k, 4, k) for k in range(6)]


def test_a_long_set_leaves_the_sketches_of_short_ones_short():
    import tracemalloc

    rng = np.random.default_rng(1)
    sets = [np.unique(rng.integers(0, 1 << 63, n).astype(np.uint64)) for n in [20_000] + [5] * 2_000]
    sets.append(sets[1][:4])  # links with the five that it is of
    name = list(range(len(sets)))
    tracemalloc.start()
    found = parity_join.bucket_links(name, name, [0] * len(sets), sets, 0, 0, parity_join.Bands())
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert (len(sets) - 1, 1) in found and most < 10 << 20


def test_staged_tables_take_small_batches(spark):
    names = ("spark.sql.execution.arrow.maxRecordsPerBatch", "spark.sql.execution.arrow.maxBytesPerBatch")
    before = [spark.conf.get(n) for n in names]

    def size(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows]), pa.array([b.nbytes])], names=["n", "size"])

    wide = spark.range(5000, numPartitions=1).select(F.expr("repeat('x', 10000)").alias("t"))
    assert max(r.size for r in shared.materialize(wide.mapInArrow(size, "n long, size long")).collect()) < 6 << 20
    flat = shared.materialize(spark.range(5000, numPartitions=1).mapInArrow(size, "n long, size long")).collect()
    assert sum(r.n for r in flat) == 5000 and max(r.n for r in flat) <= 2000
    assert [spark.conf.get(n) for n in names] == before


def test_workers_keep_one_operators_things_at_most():
    for key in (("a", 1), ("b", 1), ("b", 2)):
        assert shared.kept(key, lambda key=key: [key]) is shared.kept(key, lambda: None) and list(shared._kept) == [key]
    shared.keep_nothing()
    assert not shared._kept


def test_near_copies_drop_the_model_that_their_worker_kept(odd, monkeypatch):
    ran = []
    monkeypatch.setattr(type(odd), "mapInArrow", lambda self, function, schema: ran.append(function))
    parity_join.document_sets(odd, "doc_id", "text", 5, parity_join.Bands())
    shared.kept(("language_id", "earlier"), lambda: "models")
    batch = pa.RecordBatch.from_arrays([pa.array([1]), pa.array(["a b c d e f"])], names=["_id", "text"])
    assert next(ran[0]([batch])).num_rows == 1 and not shared._kept


def test_join_of_awkward_rows(odd, none):
    got = Counter(rows(parity_join.linked_classes(odd)))
    assert got[(1, 5, 1)] == 1 and got[(2, 5, 1)] == 2 and got[(3, 0, 3)] == 1 and got[(4, 0, 4)] == 1 and got[(5, 0, 5)] == 1
    assert got[(9, 1, 9)] == 1 and got[(10, 1, 9)] == 1 and got[(None, 1, None)] == 1 and sum(got.values()) == 12
    assert parity_join.linked_classes(none).count() == 0 and parity_join.one_per_class(none).count() == 0
    assert parity_join.one_per_class(odd).columns == odd.columns


def test_parity_sketches_bound_the_difference_and_prefixes_share_words():
    rng = np.random.default_rng(3)
    bands = parity_join.Bands()
    for n in (4, 5, 9, 40, 63, 64, 80, 127, 128, 300, 2000):
        for _ in range(30):
            a = np.unique(parity_join.mixed(rng.integers(0, 1 << 62, n).astype(np.uint64)))
            most = bands.differ(len(a), len(a))
            drop = int(rng.integers(0, most // 2 + 1))
            b = np.unique(np.concatenate([a[drop:], parity_join.mixed(rng.integers(0, 1 << 62, most - drop).astype(np.uint64))]))
            if 100 * len(np.intersect1d(a, b)) < 80 * len(np.union1d(a, b)):
                continue
            p, q = (np.frombuffer(parity_join.parity_sketch(s), np.uint64) for s in (a, b))
            w = min(len(p), len(q))
            assert np.bitwise_count(parity_join.folded(p, w) ^ parity_join.folded(q, w)).sum() <= len(np.setxor1d(a, b))
            assert len(np.intersect1d(bands.words(a), bands.words(b))) >= 2 or len(np.setxor1d(a, b)) == 0


def test_components_of_long_chains(spark):
    """Rounds go on until nothing changes."""
    from pyspark.sql import functions as F

    n = 3000
    place = F.expr(f"(id * 1009) % {n}")  # neighbours on the chain aren't neighbours as numbers
    chain = spark.range(n - 1).select(place.alias("a"), F.expr(f"((id + 1) * 1009) % {n}").alias("b"))
    ring = spark.range(5).select((F.col("id") + n).alias("a"), (F.lit(n) + (F.col("id") + 1) % 5).alias("b"))
    got = {r.node: r.root for r in components.components(chain.unionByName(ring)).collect()}
    assert got == dict.fromkeys(range(1, n), 0) | dict.fromkeys(range(n + 1, n + 5), n)


# Fingerprints


def test_fingerprints(odd, none, documents):
    for docs in (documents, odd):
        got = {r.doc_id: r for r in imatch.fingerprints(docs).collect()}
        given = sorted(docs.select("doc_id", "text").collect(), key=lambda r: (-(r.doc_id if r.doc_id is not None else -(1 << 63)), (r.text or "").encode()))
        for r, after in zip(given, given[1:] + given[:1]):
            if sum(x.doc_id == r.doc_id for x in given) > 1:
                continue
            text, other = r.text or "", after.text or ""
            edited = text[: len(text) - len(text) // 2] + other[: len(text) // 2]
            assert got[r.doc_id].n_chars == len(text) and got[r.doc_id].edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        by_text = defaultdict(set)
        for r in given:
            by_text[r.text or ""].add(got[r.doc_id].fingerprint)
        assert all(len(v) == 1 for v in by_text.values())
    frame = imatch.fingerprints(documents).toPandas()
    assert frame.near_edited.mean() > 0.1 and frame.near_next.mean() < 0.05 and (frame[["near_edited", "near_next"]].max() <= 1).all()
    assert imatch.fingerprints(none).count() == 0


def plain_fingerprint(raw, words, seed=0):
    """The fingerprint term by term and subset by subset, in whole numbers."""
    mask = (1 << 64) - 1

    def mix(x):
        x = ((x ^ x >> 30) * int(shared.MIX_1)) & mask
        x = ((x ^ x >> 27) * int(shared.MIX_2)) & mask
        return x ^ x >> 31

    def section(chosen, groups):
        out = ""
        for k in range(groups * imatch.PER_GROUP):
            salt, least = mix((k + 1 + seed * 1_000_003) * int(shared.STEP) & mask), int(imatch.SHARES[k // imatch.PER_GROUP] * 2**64)
            inside = [xxhash.xxh64_intdigest(t) for t in sorted(chosen)]
            inside = [h for h in inside if mix(h ^ salt) < least]
            out += xxhash.xxh64_hexdigest(b"".join(h.to_bytes(8, "little") for h in inside))[:4] if inside else "----"
        return out

    own = imatch.terms(raw)
    known = own & set(words)
    return section(known, 5) + ("+" + section(own, 2) if len(known) < 4 else "")


def plain_likeness(a, b):
    if a == b:
        return 1.0
    found = [0.0]
    for x, y in zip(a.split("+"), b.split("+")):
        for g in range(0, len(x), 128):
            cells = [(x[k : k + 4], y[k : k + 4]) for k in range(g, g + 128, 4)]
            cells = [c for c in cells if c != ("----", "----")]
            if len(cells) >= 16:
                found.append(sum(p == q for p, q in cells) / len(cells))
    return max(found)


def test_fingerprints_against_plain_python(documents, odd):
    for docs in (documents.where("doc_id % 4 = 0"), odd.where("doc_id is null or doc_id <> 2")):
        given = sorted(docs.select("doc_id", "text").collect(), key=lambda r: -(r.doc_id if r.doc_id is not None else -(1 << 63)))
        texts = [(r.text or "").encode() for r in given]
        df = Counter(t for raw in texts for t in imatch.terms(raw))
        words = sorted(t for t, n in df.items() if max(2, 0.001 * len(texts)) <= n <= 0.1 * len(texts))
        got = {r.doc_id: r for r in imatch.fingerprints(docs).collect()}
        for r, raw, after in zip(given, texts, texts[1:] + texts[:1]):
            text, row = raw.decode(), got[r.doc_id]
            edited = (text[: len(text) - len(text) // 2] + after.decode()[: len(text) // 2]).encode()
            own, changed, other = (plain_fingerprint(x, words) for x in (raw, edited, after))
            assert (row.fingerprint, row.edited_fingerprint) == (own, changed)
            assert row.near_edited == plain_likeness(own, changed) and row.near_next == plain_likeness(own, other)


def test_ranges_of_repeated_ids():
    rng = np.random.default_rng(4)
    pairs = [(int(rng.integers(0, 6)), int(rng.integers(-3, 3))) for _ in range(200)]
    pairs += [(2, k) for k in range(50)]
    tops = sorted(set(pairs[::17]) | {max(pairs)})
    places = imatch._Ranges(tops).places(*(np.array([p[c] for p in pairs]) for c in (0, 1)))
    for pair, got in zip(pairs, places):
        own = len(tops) - 1 - next(k for k, t in enumerate(tops) if t >= pair)
        assert got == [2 * own] + ([2 * ((own - 1) % len(tops)) + 1] if pair in tops else [])


def test_lexicon_counts_all_documents(documents):
    texts = [r.text.encode() for r in documents.collect()]
    df = Counter(t for raw in texts for t in imatch.terms(raw))
    want = sorted(t for t, n in df.items() if max(2, 0.01 * len(texts)) <= n <= 0.1 * len(texts))
    assert imatch.lexicon(documents, least=0.01) == want
    assert imatch.lexicon(documents, least=0.01, broadcast_terms=3) == want


# Language


def test_language_accuracy_on_held_out_rows(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    judged = language_id.identify(docs).toPandas().merge(docs.select("doc_id", "lang").toPandas())
    assert all(judged.held_out == judged.doc_id.map(lambda i: zlib.crc32(str(i).encode()) % 3 == 1))
    assert (judged.lang == judged.lang_pred)[judged.held_out].mean() > 0.97
    assert judged.score.between(0, 1).all()
    assert language_id.known_language(docs).count() >= 0.98 * docs.count()


def test_language_of_awkward_rows(odd, none, documents):
    model = language_id.train(documents)
    got = {r.doc_id: r for r in language_id.predict(odd, model).collect()}
    assert [got[i].lang_pred for i in (3, 4, 5, 11)] == ["und"] * 4 and got[3].score == 0
    assert language_id.predict(none, model).count() == 0 and language_id.identify(none).count() == 0
    assert {r.lang_pred for r in language_id.identify(none.sparkSession.createDataFrame([(1, "text without label", None)], "doc_id bigint, text string, lang string")).collect()} == {"und"}
    assert language_id.known_language(odd).columns == odd.columns


def test_languages_of_long_texts_only_are_learned(spark):
    rows = [(i, "habari ya asubuhi na jioni " * 4000, "sw") for i in range(10)] + [(100 + i, "good morning to all the people", "en") for i in range(30)] + [(7, "good morning to all the people", "en")] * 600
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string")
    assert all(r.lang_pred == ("sw" if r.doc_id < 10 and r.doc_id != 7 else r.lang_pred) for r in language_id.identify(docs).collect())
    assert {r.doc_id: r.lang_pred for r in language_id.identify(docs.where("doc_id <> 7")).collect()} == {i: t for i, _, t in rows if i != 7}
    assert language_id.sample(docs, "doc_id", "text", "lang", 20, 4).groupBy("_lang").count().where("count > 20").isEmpty()


def plain_code_length(texts, order, raw):
    """The same model byte by byte, in plain Python: probabilities, exclusion and escapes from nested counts."""
    counts = defaultdict(Counter)
    for t in texts:
        b = b"\0" * order + language_id.prepared(t)
        for i in range(order, len(b)):
            for k in range(order + 1):
                counts[b[i - k : i]][b[i]] += 1

    def p(context, symbol):
        own = counts.get(context, {})
        n, d = sum(own.values()), len(own)
        if not context:
            return own[symbol] / (n + d) if symbol in own else (d / (n + d) if n else 1) / (256 - d)
        if not n:
            return p(context[1:], symbol)
        if symbol in own:
            return own[symbol] / (n + d)
        return d / (n + d) * p(context[1:], symbol) / max(1 - sum(p(context[1:], s) for s in own), 1e-12)

    b = b"\0" * order + raw
    return -sum(np.log2(p(b[i - order : i], b[i])) for i in range(order, len(b)))


def test_code_lengths_match_plain_python(spark):
    lessons = {"de": ["der Weg ist das Ziel und das Ziel ist weit", "die Katze auf dem Dach"], "en": ["the way is the goal", "a cat on the roof of the house"]}
    docs = spark.createDataFrame([(i, t, lang) for i, (lang, t) in enumerate((lang, t) for lang, ts in lessons.items() for t in ts)], "doc_id bigint, text string, lang string")
    scorer = language_id.Scorer(language_id.train(docs))
    texts = [b"the cat is das ziel", "größe".encode(), b"x", b"qqqq \xff"]
    want = [[plain_code_length([t.encode() for t in lessons[lang]], 3, raw) for lang in ("de", "en")] for raw in texts]
    assert np.allclose(scorer.code_lengths(texts), want, rtol=1e-4)


def test_code_lengths_are_those_of_a_distribution():
    """In any context the costs of all 256 bytes are a code: their probabilities add up to one."""
    keys, counts = np.unique(language_id.grams(b"the theory of the thing is thin " * 3, 3), return_counts=True)
    scorer = language_id.Scorer(language_id.Model(("x",), 3, np.zeros(len(keys), np.int16), keys, counts))
    for context in (b"the", b"qqq", b"\0\0\0", b"zth", b" of"):
        before = scorer.symbol[np.frombuffer(context, np.uint8)].astype(np.int32)
        bits = [scorer._bits(np.append(before, scorer.symbol[b]).astype(np.int32))[0, 0] for b in range(256)]
        assert abs(np.exp2(-np.array(bits)).sum() - 1) < 1e-3
    whole = scorer.code_lengths([b"the thing", b"", b"the " * 700_000])
    assert whole[1, 0] == 0 and whole[2, 0] > whole[0, 0] > 0
    language_id.SLICE_BYTES, kept = 1000, language_id.SLICE_BYTES
    try:
        assert abs(scorer.code_lengths([b"the " * 700_000])[0, 0] - whole[2, 0]) < 1e-3 * whole[2, 0]
    finally:
        language_id.SLICE_BYTES = kept
