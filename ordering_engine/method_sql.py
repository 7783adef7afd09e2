"""DuckDB SQL of the methods themselves, round by round, so that a query is held to where its method puts every element."""

from __future__ import annotations

from .functions.hashing import DUCK


def positions(source: str, dims: int) -> str:
    return f"SELECT pe, key, uid, row_number() OVER (PARTITION BY pe ORDER BY key, uid) AS pos, count(*) OVER (PARTITION BY pe) AS m, pe >> {dims} AS sub FROM {source}"


def pivot(how: str, at: str, dims: int, k: int, seed: int, levels: int = 12, tag: str = "") -> list[tuple[str, str]]:
    """Steps (name, query) to the pivots (sub, s) of subcubes of ``dims`` dimensions, from positions ``at``; the last one has them.

    Windows of PEs with fewer than k elements, which need sentinels, aren't covered; ``levels`` threefold levels are.
    """
    own = f"SELECT * FROM {at} WHERE pos = (m + 1) // 2"
    middle = f"SELECT sub, key AS s FROM (SELECT sub, key, row_number() OVER (PARTITION BY sub ORDER BY {{}}) AS r, count(*) OVER (PARTITION BY sub) AS n FROM {{}}) WHERE r = (n + 1) // 2"
    if how == "first_pe":
        return [(f"piv{tag}", f"SELECT sub, min_by(key, pe) AS s FROM ({own}) GROUP BY sub")]
    if how == "random_pe":
        return [(f"piv{tag}", f"SELECT sub, min_by(key, {DUCK.hash('pe', seed)}) AS s FROM ({own}) GROUP BY sub")]
    if how == "median_of_medians":
        return [(f"piv{tag}", middle.format("key, pe", f"({own})"))]
    if how == "exact":
        return [(f"piv{tag}", middle.format("key, uid", at))]
    if how == "ternary_tree":
        steps = [(f"t0{tag}", f"SELECT sub, row_number() OVER (PARTITION BY sub ORDER BY {DUCK.hash('uid', seed)}, uid) - 1 AS leaf, key FROM {at}")]
        for level in range(1, levels + 1):
            steps.append((f"t{level}{tag}", f"SELECT sub, leaf // 3 AS leaf, list_sort(list(key))[(count(*) + 1) // 2] AS key FROM t{level - 1}{tag} GROUP BY ALL"))
        return [*steps, (f"piv{tag}", f"SELECT sub, key AS s FROM t{levels}{tag}")]
    steps = [(f"w0{tag}", f"SELECT pe, list_sort(list(key)) AS w FROM (SELECT *, m // 2 + (m % 2) * ({DUCK.hash('pe', seed)} % 2) AS mid FROM {at}) WHERE pos > mid - {k // 2} AND pos <= mid + {k // 2} GROUP BY pe")]
    for level in range(1, dims + 1):
        steps.append((f"w{level}{tag}", f"SELECT pe // 2 AS pe, list_sort(flatten(list(w)))[{k // 2 + 1}:{k // 2 + k}] AS w FROM w{level - 1}{tag} GROUP BY ALL"))
    return [*steps, (f"piv{tag}", f"SELECT pe AS sub, w[{k // 2} + ({DUCK.hash('pe', seed + 1)} % 2)] AS s FROM w{dims}{tag}")]


def quicksort(held: str, p: int, how: str = "first_pe", shuffle: bool = False, local_ties: bool = False, k: int = 2, seed: int = 1) -> tuple[str, list[tuple[int, str]]]:
    """The WITH part that leaves the sorted elements in ``done`` (pe, key, uid), and (step, table of src and pe) of every exchange."""
    d = p.bit_length() - 1
    steps, moves = [("start", f"SELECT pe, pe AS src, key, uid FROM {held}")], []
    now = "start"
    if shuffle:
        steps.append(("shuffled", f"SELECT cast({DUCK.hash('uid', seed)} % {p} AS int) AS pe, pe AS src, key, uid FROM start"))
        now, moves = "shuffled", [(0, "shuffled")]
    for number, j in enumerate(range(d - 1, -1, -1)):
        steps.append((f"at{j}", positions(now, j + 1)))
        steps += pivot(how, f"at{j}", j + 1, k, seed + 101 * (j + 1), tag=f"_{j}")
        left = "pos <= lt + least(greatest((m + 1) // 2 - lt, 0), eq)" if local_ties else "key <= s"
        counts = ", count(*) FILTER (WHERE key < s) OVER (PARTITION BY pe) AS lt, count(*) FILTER (WHERE key = s) OVER (PARTITION BY pe) AS eq" if local_ties else ""
        steps.append((f"moved{j}", f"SELECT cast(CASE WHEN {left} THEN pe & {(p - 1) ^ (1 << j)} ELSE pe | {1 << j} END AS int) AS pe, pe AS src, key, uid FROM (SELECT a.*, s{counts} FROM at{j} a JOIN piv_{j} USING (sub))"))
        now = f"moved{j}"
        moves.append((int(shuffle) + 2 * number + 1, now))
    steps.append(("done", f"SELECT pe, key, uid FROM {now}"))
    return "WITH " + ", ".join(f"{name} AS MATERIALIZED ({sql})" for name, sql in steps), moves


def ranked(sorted_elements: str) -> str:
    return f"SELECT pe, row_number() OVER (ORDER BY pe, key, uid) - 1 AS rank, key FROM {sorted_elements}"


def trace(moves: list[tuple[int, str]]) -> str:
    """Per exchange: the largest number of partners, of words and of elements of a PE."""
    parts = []
    for step, name in moves:
        pairs = f"(SELECT src, pe, count(*) AS c FROM {name} GROUP BY ALL)"
        ends = f"SELECT src AS x, cast(src <> pe AS int) AS n, CASE WHEN src <> pe THEN c ELSE 0 END AS wo, 0 AS wi, 0 AS h FROM {pairs} UNION ALL SELECT pe, cast(src <> pe AS int), 0, CASE WHEN src <> pe THEN c ELSE 0 END, c FROM {pairs}"
        parts.append(f"SELECT {step} AS step, max(n) AS startups, max(greatest(wo, wi)) AS words, max(h) AS held FROM (SELECT x, sum(n) AS n, sum(wo) AS wo, sum(wi) AS wi, sum(h) AS h FROM ({ends}) GROUP BY x)")
    return "SELECT cast(step AS int) AS step, cast(startups AS bigint) AS startups, cast(words AS bigint) AS words, cast(held AS bigint) AS held FROM (" + " UNION ALL ".join(parts) + ")"


def direct(held: str, p: int, oversample: int = 16, seed: int = 1) -> str:
    """One exchange by splitters from the elements of smallest hash."""
    return f"""WITH h AS MATERIALIZED (SELECT * FROM {held}), drawn AS (SELECT * FROM h ORDER BY {DUCK.hash('uid', seed)}, uid LIMIT {oversample * p}),
        placed AS (SELECT key, row_number() OVER (ORDER BY key, pe, uid) AS i, count(*) OVER () AS n FROM drawn),
        cuts AS (SELECT key AS s FROM placed WHERE i * {p} // n > (i - 1) * {p} // n AND i * {p} // n < {p}),
        done AS (SELECT cast((SELECT count(*) FROM cuts WHERE s < key) AS int) AS pe, key, uid FROM h) {ranked('done')}"""


def study(sizes: list[int], k: int, tree: str, held: str) -> str:
    """Ranks (n, seed, m, rank, error) of tree medians over blocks of held elements, as ``medians.study_of`` makes them."""
    widest, arity = max(sizes), 2 if tree == "binary" else 3
    depth = next(d for d in range(64) if arity**d >= widest)
    steps = [("cells", f"SELECT cast(n AS int) AS n, cast(uid * ((total + n - 1) // n) // total AS int) AS seed, key, uid FROM (SELECT key, uid, count(*) OVER () AS total FROM {held}), (SELECT unnest({sizes}) AS n)"),
             ("leaves", f"SELECT n, seed, row_number() OVER (PARTITION BY n, seed ORDER BY key, uid) AS v, row_number() OVER (PARTITION BY n, seed ORDER BY {DUCK.hash('uid', 5)}, uid) - 1 AS leaf FROM cells")]
    if tree == "binary":
        low, high = ("[" + ", ".join([value] * times) + "]" if times else "[]" for value, times in (("-1", k // 2), (str(1 << 30), k // 2)))
        low1, high1 = ("[" + ", ".join([value] * (k // 2 - 1)) + "]" for value in ("-1", str(1 << 30)))
        empty = "[]::BIGINT[]"
        fix = lambda x: empty if x == "[]" else f"{x}::BIGINT[]"
        coin = f"({DUCK.hash('leaf + 31 * seed + 7 * n', 3)} % 2)"
        steps.append(("l0", f"SELECT n, seed, leaf, CASE WHEN {coin} = 1 THEN list_concat(list_concat({fix(low1)}, [v]::BIGINT[]), {fix(high)}) ELSE list_concat(list_concat({fix(low)}, [v]::BIGINT[]), {fix(high1)}) END AS w FROM leaves"))
        for level in range(1, depth + 1):
            steps.append((f"l{level}", f"SELECT n, seed, leaf, w[1 + (len(w) - least({k}, len(w))) // 2 : (len(w) - least({k}, len(w))) // 2 + {k}] AS w FROM (SELECT n, seed, leaf // 2 AS leaf, list_sort(flatten(list(w))) AS w FROM l{level - 1} GROUP BY n, seed, leaf // 2)"))
        chosen = f"w[{k // 2} + ({DUCK.hash('seed + 7 * n', 9)} % 2)]"
        real = f"list_filter(w, lambda x: x > 0 AND x < {1 << 30})"
        steps.append(("found", f"SELECT n, seed, CASE WHEN {chosen} < 0 THEN ({real})[1] WHEN {chosen} >= {1 << 30} THEN ({real})[-1] ELSE {chosen} END AS rank FROM l{depth}"))
    else:
        steps.append(("l0", "SELECT n, seed, leaf, v FROM leaves"))
        for level in range(1, depth + 1):
            steps.append((f"l{level}", f"SELECT n, seed, leaf // 3 AS leaf, list_sort(list(v))[count(*) // 2 + 1] AS v FROM l{level - 1} GROUP BY n, seed, leaf // 3"))
        steps.append(("found", f"SELECT n, seed, v AS rank FROM l{depth}"))
    steps.append(("study", "SELECT n, seed, m, rank, abs(rank / (m / 2.0) - 1) AS error FROM found JOIN (SELECT n, seed, count(*) AS m FROM cells GROUP BY ALL) USING (n, seed)"))
    return "WITH " + ", ".join(f"{name} AS MATERIALIZED ({sql})" for name, sql in steps)


def study_fit(sizes: list[int], k: int, tree: str, held: str) -> str:
    label = k if tree == "binary" else 3
    return f"""SELECT '{tree}' AS tree, {label} AS k, c, gamma, bias FROM ({study(sizes, k, tree, held)}, e AS (SELECT n, avg(error) AS error FROM study GROUP BY n),
        b AS (SELECT n, avg(rank / (m / 2.0)) AS half FROM study GROUP BY n)
        SELECT round(exp(regr_intercept(ln(error), ln(n))), 3) AS c, round(-regr_slope(ln(error), ln(n)), 3) AS gamma, (SELECT round(avg(half), 6) FROM b) AS bias FROM e WHERE error > 0)"""
