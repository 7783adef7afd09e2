"""Surrogates: consistent, distinct, of the same type, and nothing of the originals left."""

import re

from pyspark.sql import functions as F

from ordering_engine.llm import surrogates

TEXTS = [
    (1, "Write to anna.b@mail1.example.com or ANNA.B@mail1.example.com, call +1 (017) 555-7713."),
    (2, "anna.b@mail1.example.com again; IP 10.2.3.4. Card 4111 1111 1111 1111, 4111111111111111 and 1234567890123456."),
    (3, 'token = "24be64439e3e49cf46b2d7c90f3602a3d0b907ff" and version 3.0.'),
    (4, "Mrs. Smith met Herr Müller; Maria Schmidt and Peter Jones were there. Mrs. Smith left."),
    (5, None), (6, ""), (6, "nothing here 2.0."), (7, "Mr Иванов wrote"), (7, "Mr Иванов wrote"), (None, "123-45-6789"),
]


def luhn(s):
    d = [int(c) for c in re.sub(r"\D", "", s)][::-1]
    return sum(d[::2] + [sum(divmod(2 * x, 10)) for x in d[1::2]]) % 10 == 0


def test_replacements(spark):
    docs = spark.createDataFrame(TEXTS, "doc_id bigint, text string").withColumn("kind", F.lit("x")).withColumn("surrogate", F.lit(1))
    got = [tuple(r) for r in surrogates.replace_entities(docs, key="k1", whole_names=False).collect()]
    assert len(got) == len(TEXTS)
    text = {i: t for i, t, n in got if i not in (6, 7)}
    assert text[5] is None and (6, "", 0) in got and (6, "nothing here 2.0.", 0) in got
    first = re.fullmatch(r"Write to (\w+\.\w@\w+\.example\.com) or (\w+\.\w@\w+\.example\.com), call \+1 \((\d{3})\) 555-(\d{4})\.", text[1])
    assert first and first[1].lower() == first[2].lower() and first[1] != "anna.b@mail1.example.com" and first[2].split("@")[0].isupper()
    assert text[2].startswith(first[1] + " again; IP ")
    cards = re.findall(r"\d{4} \d{4} \d{4} \d{4}|\d{16}", text[2])
    assert [luhn(c) for c in cards] == [True, True, False] and all(c[0] == o for c, o in zip(cards, "441")) and "1111 1111" not in text[2]
    assert re.fullmatch(r'token = "[0-9a-f]{40}" and version 3\.0\.', text[3]) and "24be64439e" not in text[3]
    names = re.fullmatch(r"Mrs\. (\p{Lu}\p{Ll}+) met Herr (\p{Lu}\p{Ll}+); (\w+) Schmidt and (\w+) Jones were there\. Mrs\. (\w+) left\.".replace(r"\p{Lu}\p{Ll}+", r"[^\W\d_]+"), text[4])
    assert names and names[1] == names[5] != "Smith" and names[3] in surrogates.FEMALE and names[4] in surrogates.MALE
    russian = {t for i, t, n in got if i == 7}
    assert len(russian) == 1 and re.fullmatch(r"Mr [А-Я][а-я]+ wrote", russian.pop()) and re.fullmatch(r"\d{3}-\d{2}-\d{4}", text[None])
    other = {r.doc_id: r.text for r in surrogates.replace_entities(docs, key="k2", whole_names=False).collect()}
    assert other[3] != text[3]
    assert surrogates.replace_entities(docs.where("doc_id < 0")).count() == 0


def test_collisions_draw_again(spark):
    """Numbers of one short format: many values, so first draws collide, and some draws are values of the corpus."""
    values = spark.range(3000).select(F.format_string("+1 (%03d) 555-%04d", (F.col("id") % 7).cast("int"), (F.col("id") * 3).cast("int")).alias("value"), F.lit("phone").alias("kind"))
    table = surrogates.surrogate_table(values, "k").toPandas()
    assert table.surrogate.nunique() == len(table) == 3000 and not set(table.surrogate) & set(table.value)


def test_given_names_stay_distinct(spark):
    """Every name that can be found gets one of its gender for itself, and never a name that can be found."""
    found = [(n, "female") for n in surrogates.FOUND_FEMALE] + [(n, "male") for n in surrogates.FOUND_MALE]
    values = spark.createDataFrame(found, "value string, kind string")
    drawn = []
    for key in ("k1", "k2"):
        got = {r.value: (r.kind, r.surrogate) for r in surrogates.surrogate_table(values, key).collect()}
        assert len(got) == len({s for _, s in got.values()}) == len(found) and not {s for _, s in got.values()} & set(got)
        assert all(s in (surrogates.FEMALE if kind == "female" else surrogates.MALE) for kind, s in got.values())
        drawn.append(got)
    assert drawn[0] != drawn[1]


def test_whole_names_and_more_formats(spark):
    docs = spark.createDataFrame([
        (1, "Maria Schmidt met Mr Peter J. Smith and Frau von Braun. Peter Smith left; Mrs Smith-Jones stayed."),
        (2, "0171 2345678, (030) 123-4567, 555-123-4567, +49301234567 and 0049 30 1234567"),
        (3, "DE89 3704 0044 0532 0130 00 or GB29NWBK60161331926819"), (4, "2001:db8:85a3::8a2e:370:7334 at 12:30:45"),
        (5, "3782 822463 10005 and 378282246310005"), (6, "ghp_abcdefghijklmnopqrstuvwxyz0123456789 password: hunter2x9y"),
    ], "doc_id bigint, text string")
    got = {r.doc_id: (r.text, r.n_entities) for r in surrogates.replace_entities(docs, whole_names=True).collect()}
    word = r"([A-Z][a-z]+)"
    names = re.fullmatch(rf"{word} {word} met Mr {word} ([A-Z])\. {word} and Frau von {word}\. {word} {word} left; Mrs ([A-Z][a-z]+-[A-Z][a-z]+) stayed\.", got[1][0])
    assert names and got[1][1] == 5 and names[1] in surrogates.FEMALE and names[3] == names[7] in surrogates.MALE and names[5] == names[8] and names[4] != "J"
    assert not {"Maria", "Schmidt", "Peter", "Smith", "Braun", "Smith-Jones"} & set(names.groups())
    assert [got[k][1] for k in (2, 3, 4, 5, 6)] == [5, 2, 1, 2, 2]
    assert re.fullmatch(r"0\d{3} \d{7}, \(0\d\d\) \d{3}-\d{4}, \d{3}-\d{3}-\d{4}, \+4\d{10} and 0049 \d\d \d{7}", got[2][0]) and not any(x in got[2][0] for x in ("2345678", "1234567", "123-4567"))
    spaced, plain = re.fullmatch(r"(DE\d\d(?: \d{4}){4} \d\d) or (GB\d\d[A-Z]{4}\d{14})", got[3][0]).groups()
    for account in (spaced.replace(" ", ""), plain):
        assert int("".join(str(int(c, 36)) for c in account[4:] + account[:4])) % 97 == 1 and "0532" not in account and "NWBK" not in account
    assert re.fullmatch(r"2001:db8(:[0-9a-f]{4}){6} at 12:30:45", got[4][0])
    cards = got[5][0].split(" and ")
    assert all(luhn(c) and c.startswith("37") for c in cards) and "822463" not in got[5][0]
    assert re.fullmatch(r"ghp_[a-z]{26}\d{10} password: [a-z]{6}\d[a-z]\d[a-z]", got[6][0]) and "abcdef" not in got[6][0] and "hunter" not in got[6][0]


def test_persons_stay_one_and_their_names_go(spark):
    """Against the names the texts were made from: one surrogate a part, none for two, nothing left."""
    import itertools
    import random

    rng = random.Random(5)
    families = [a + b for a, b in itertools.product(("Kra", "Ober", "Sand", "Wil", "Hart"), ("mann", "berg", "son", "feld", "lin", "stein"))]
    given = surrogates.FOUND_FEMALE + surrogates.FOUND_MALE
    rows, parts = [], []
    for k in range(60):
        first, last, other = rng.choice(given), *rng.sample(families, 2)
        rows.append((k, f"{first} {last} wrote to {rng.choice(('Mr', 'Frau', 'Ms'))} {other}. Then {last} and {other} agreed; Ms {last} said \"{last}'s\" house, not {last}ville, was {first}'s. The end, {other}!"))
        parts.append((first, last, other))
    got = {r.doc_id: r for r in surrogates.replace_entities(spark.createDataFrame(rows, "doc_id bigint, text string"), key="k").collect()}
    word, new = r"([A-Z][a-z]+)", {}
    for (k, text), (first, last, other) in zip(rows, parts):
        pattern = re.escape(text)
        for name in (first, last, other):
            pattern = re.sub(rf"\b{name}\b", lambda m: word, pattern)
        order = re.findall(rf"\b(?:{first}|{last}|{other})\b", text)
        match = re.fullmatch(pattern, got[k].text)
        assert match and got[k].n_entities == 8, got[k]
        for old, surrogate in zip(order, match.groups()):
            assert new.setdefault(old, surrogate) == surrogate != old
    assert len(set(new.values())) == len(new) and not set(new) & set(new.values())


def test_without_a_key_each_call_draws_one(spark):
    docs = spark.createDataFrame([(1, "call +1 (017) 555-7713 or write to ann@mail.com")], "doc_id bigint, text string")
    assert surrogates.replace_entities(docs).first().text != surrogates.replace_entities(docs).first().text
    assert surrogates.replace_entities(docs, key="it's").first() == surrogates.replace_entities(docs, key="it's").first()


def test_corpus_keeps_distinctness_and_coreference(spark, documents):
    rows = {r.doc_id: r.text for r in documents.collect()}
    got = surrogates.replace_entities(documents)
    assert "Python" not in got._jdf.queryExecution().executedPlan().toString()
    pattern, pairs = re.compile(r"[\w.+-]+@[\w.-]+\.\w+|\b\d{16}\b|(?<![\d.])\d{1,3}(?:\.\d{1,3}){3}(?!\.?\d)|\+\d \(\d{3}\) \d{3}-\d{4}|\b[0-9a-fA-F]{40}\b"), set()
    for r in got.collect():
        old, new = pattern.findall(rows[r.doc_id]), pattern.findall(r.text)
        assert len(old) == len(new) and not set(old) & set(new)
        assert pattern.split(rows[r.doc_id]) == pattern.split(r.text)
        pairs |= set(zip(old, new))
    assert len(pairs) > 10 and len({a for a, _ in pairs}) == len({b for _, b in pairs}) == len(pairs)
