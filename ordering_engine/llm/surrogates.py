"""Surrogates for personal data, in DataFrame functions only.

Entities are found by patterns: mail and network addresses, phone, account, card and social security numbers,
secrets, and names after a title or from lists of given names, with the capitalised words, initials and
particles that follow. Each part of a name is a value with a surrogate of its own; particles stay. Each distinct value gets a replacement that
is a keyed function of it: of the same type, length class, letter case, script and punctuation; a given name
one of the same gender; a card number one that passes or fails the check digit as the original did; a
mail address one under a reserved domain. So one value has one surrogate wherever it occurs.

Collision checks go over all distinct values: two values with one surrogate, or a surrogate that is itself
a value of the corpus, draw again with the next attempt number, the smallest value staying, until none is left. Values that
differ in letter case only are one value, and their surrogates differ in letter case only.
Texts are cut at their entities, the entities' surrogates are looked up by a join on the value, and the
pieces are put together; only texts with entities take part. Where a text names a person in full or with a title, the parts of that name
are replaced wherever else the text has them as words of their own, so that who is meant stays clear and the name is gone.

The key is secret: without one each call draws its own, and with one replacements agree between calls.

Defined results: a null text stays null and has no entities; texts without entities stay as they are;
repeated rows are treated alike; an empty table gives an empty result; other columns are kept or ignored by
the caller, whatever their names.
"""

from __future__ import annotations

import hashlib
import secrets

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import LOWER, UPPER, materialize

#: Given names by gender that are found in texts.
FOUND_FEMALE = "Anna Maria Laura Julia Sofia Emma Clara Helena Marta Paula Elena Louise Camille Alice Carmen Lucia Ingrid Katharina Margaret Susan".split()
FOUND_MALE = "Peter Thomas Michael Daniel Martin Paul Robert Andreas Stefan Pierre Louis Antoine Carlos Miguel Javier Diego Klaus Jürgen William George".split()
#: Those from which surrogates are drawn: more of them, and none that is found.
FEMALE = """Agnes Amelie Beatrice Birgit Blanca Brigitte Cecilia Charlotte Claudia Colette Daniela Diana Dorothea Edith Eleanor Esther Eva Florence Frances Gabriela
    Greta Hanna Harriet Ida Irene Isabel Jana Johanna Josefina Karin Lena Lydia Magdalena Miriam Monika Nora Olivia Petra Rosa Sabine""".split()
MALE = """Adam Albert Alfonso Arthur Benjamin Bernard Bruno Christian Conrad David Edgar Emil Ernst Felipe Felix Francis Frank Gabriel Gustav Harold
    Henri Hugo Ignacio Jakob Jonas Julian Karl Leon Lorenz Marcel Matthias Niklas Oliver Oscar Philip Ralph Samuel Simon Theodor Victor""".split()
TITLES = "Mr|Mrs|Ms|Miss|Herr|Frau|Mme|Sra|Sr"
GIVEN = "|".join(FOUND_FEMALE + FOUND_MALE)
#: A part of a name: a capitalised word (also O'Neil, McDonald, Weber-Braun) or an initial; words between parts that tell nobody.
WORD = r"\p{Lu}(?:['’]\p{Lu})?\p{Ll}+(?:\p{Lu}\p{Ll}+)*(?:-\p{Lu}\p{Ll}+)*"
WORD_SQL = WORD.replace("'", "\\u0027")
INITIAL = r"\b[A-Z]\."
PARTICLE = r"(?:(?:von|van|vom|zu|zur|der|den|de|del|della|di|da|dos|du|la|le) ){1,3}"
NAME = rf"(?:{INITIAL} )*(?:{PARTICLE})?{WORD}(?: (?:{PARTICLE})?{WORD}| {INITIAL})*"
MORE = rf"(?: (?:{PARTICLE})?{WORD}| {INITIAL})"
#: Type and pattern, the first that fits decides. Spaces, dots and hyphens group digits.
PATTERNS = (
    ("email", r"[\p{L}\p{N}._%+-]+@[\p{L}\p{N}-]+(?:\.[\p{L}\p{N}-]+)*\.\p{L}{2,}"),
    ("ip", r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?!\.?\d)"),
    ("ip6", r"(?<![0-9A-Za-z:.])(?=[A-Fa-f:]*\d)(?:(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}|(?:[0-9A-Fa-f]{1,4}:){1,6}(?::[0-9A-Fa-f]{1,4}){1,6}|::(?:[0-9A-Fa-f]{1,4}:){1,6}[0-9A-Fa-f]{1,4}|(?:[0-9A-Fa-f]{1,4}:){2,7}:)(?![0-9A-Za-z:])"),
    ("iban", r"(?<![0-9A-Za-z])[A-Z]{2}\d{2}(?=(?: ?[A-Z]{0,4} ?\d){8})(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![0-9A-Za-z])"),
    ("phone", r"(?<!\d)\+\d{1,3}[ .-]?\(?\d{2,4}\)?[ .-]?\d{3}[ .-]?\d{3,4}(?!\d)"),
    ("phone", r"(?<!\d)(?:\+|00)(?=[1-9](?:[ .()/-]{0,2}\d){7,14}(?!\d))\d{1,3}(?:[ ./-]?\(?\d{1,5}\)?){1,6}(?!\d)"),
    ("card", r"(?<!\d)\d{4}(?:[ -]?\d{4}){3}(?!\d)"),
    ("card", r"(?<!\d)(?:3[47]\d{2}[ -]?\d{6}[ -]?\d{5}|3[068]\d{2}[ -]?\d{6}[ -]?\d{4}|\d{4}(?:[ -]\d{4}){3}[ -]\d{1,3}|4\d{12}|[4-6]\d{16,18})(?!\d)"),
    ("ssn", r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])"),
    ("phone", r"(?<![\d+])(?:\(\d{2,5}\)[ -]?\d{3,4}[ .-]?\d{3,5}|\d{3}([-.])\d{3}\1\d{4}|0\d(?:[ .]\d{2}){4}|0\d{1,4}[ /-]\d{5,8}|0\d{2,4}[ /-]\d{3,4}[ -]\d{3,5})(?![\d-])"),
    ("secret", r"(?<![0-9a-zA-Z])[0-9a-fA-F]{32,64}(?![0-9a-zA-Z])"),
    ("token", r"(?<![0-9A-Za-z_-])(?:gh[pousr]_[0-9A-Za-z]{20,}|github_pat_\w{20,}|glpat-[\w-]{16,}|(?:AKIA|ASIA)[0-9A-Z]{16}|AIza[\w-]{35}|xox[abeprs]-[0-9A-Za-z-]{10,}|[spr]k[-_][\w-]{16,}|eyJ[\w-]{8,}\.[\w-]{8,}\.[\w-]{8,})(?![0-9A-Za-z_-])"),
    ("token", r"(?<![0-9A-Za-z+/=_-])(?=[A-Za-z+_-]{0,40}\d)(?=[0-9a-z+_-]{0,40}[A-Z])(?=[0-9A-Z+_-]{0,40}[a-z])[0-9A-Za-z+_-]{32,}={0,2}(?![0-9A-Za-z+/=_-])"),
    ("named token", r"(?<=(?i:token|secret|password|passwd|pwd|api[_-]?key)['\"]?\s{0,2}[:=]\s{0,2}['\"]?)(?<![0-9A-Za-z+/_.-])(?=[A-Za-z+/_.-]*\d)[0-9A-Za-z+/_.-]*[0-9A-Za-z+/_-]{7,}={0,2}"),
    ("titled", rf"(?<=\b(?:{TITLES})\.? )(?:{INITIAL} )*(?:{PARTICLE})?{WORD}{MORE}{{0,3}}"),
)
#: After a given name its surname may be left: then only given names with a capitalised word behind them are found.
AFTER_GIVEN = {True: rf"\b(?:{GIVEN})(?:-\p{{Lu}}\p{{Ll}}+)*{MORE}{{1,4}}", False: rf"\b(?:{GIVEN})(?= \p{{Lu}}\p{{Ll}})"}


def any_pattern(whole_names: bool) -> str:
    # In one pattern, the group that a repeated separator refers to is counted over all of it.
    patterns = [p.replace(r"([-.])", r"(?<sep>[-.])").replace(r"\1", r"\k<sep>") for _, p in PATTERNS]
    return "|".join(f"(?:{p})" for p in [*patterns, AFTER_GIVEN[whole_names]])


#: Words without which no name is found.
LEADS = rf"\b(?:{TITLES}|{GIVEN})\b"


def kind_of(value: Column) -> Column:
    """The type of a value that was found, or of a part of a name; what only its surroundings tell is a token if it has digits."""
    found = F.when(value.rlike(r"\d"), F.lit("token")).otherwise(F.lit("surname"))
    found = F.when(value.rlike(r"^[A-Z]\.$"), F.lit("initial")).when(value.isin(FOUND_MALE), F.lit("male")).when(value.isin(FOUND_FEMALE), F.lit("female")).otherwise(found)
    for kind, pattern in reversed(PATTERNS):
        if kind not in ("titled", "named token"):
            found = F.when(value.rlike(f"^(?:{pattern})$"), F.lit(kind)).otherwise(found)
    return found


def parts_of(entity: Column) -> Column:
    """What has a surrogate of its own, and the text before it: the parts of a name, or the whole of anything else."""
    part = F.lit(f"{WORD}|{INITIAL}")
    parts = F.zip_with(F.split(entity, part, -1), F.regexp_extract_all(entity, part, F.lit(0)), lambda lead, value: F.struct(lead.alias("lead"), value.alias("value")))
    whole = F.array(F.struct(F.lit("").alias("lead"), entity.alias("value")))
    return F.when(entity.rlike(f"^(?:{NAME})$"), F.filter(parts, lambda x: x["value"].isNotNull())).otherwise(whole)


#: Letters that stand for one another, by script and case.
CLASSES = ("aeiou", "bcdfghklmnprstvwz", "AEIOU", "BCDFGHKLMNPRSTVWZ", "аеиоуя", "бвгдзклмнпрст", "АЕИОУЯ", "БВГДЗКЛМНПРСТ", "αεηιουω", "βγδθκλμνπρστ", "ΑΕΗΙΟΥΩ", "ΒΓΔΘΚΛΜΝΠΡΣΤ", "0123456789")
DIGITS = CLASSES[-1]


def _redrawn(text: str, digest: str, alphabets: tuple[str, ...] = CLASSES) -> str:
    """SQL: each character of ``text`` replaced by one of its class, chosen by a byte of the hex ``digest``; others stay."""
    byte = f"cast(conv(substr({digest}, (i % 60) * 2 + 1, 4), 16, 10) AS int)"
    cases = " ".join(f"WHEN contains('{a}', c) THEN substr('{a}', 1 + {byte} % {len(a)}, 1)" for a in alphabets)
    # Letters outside the classes (accented, or j, q, x, y) take those of the same case.
    rest = f"WHEN c rlike '\\\\p{{IsLatin}}' AND c = lower(c) THEN substr('aeioulnrst', 1 + {byte} % 10, 1) WHEN c rlike '\\\\p{{IsLatin}}' THEN substr('AEIOULNRST', 1 + {byte} % 10, 1)"
    return f"array_join(transform(split({text}, ''), (c, i) -> CASE WHEN c = '' THEN '' {cases} {rest} ELSE c END), '')"


def surrogate(value: str = "value", kind: str = "kind", attempt: str = "attempt", key: str = "key") -> Column:
    """The surrogate of a value at an attempt, under a secret key."""
    digest = f"sha2(concat_ws('|', '{key}', {kind}, lower({value}), cast({attempt} AS string)), 512)"
    number = lambda k: f"cast(conv(substr(_h, {4 * k + 1}, 4), 16, 10) AS int)"
    hexed = f"array_join(transform(split({value}, ''), (c, i) -> CASE WHEN c = '' THEN '' WHEN c rlike '[A-F]' OR (c rlike '[0-9]' AND {value} = upper({value}) AND {value} rlike '[A-F]') THEN upper(substr(_h, i + 1, 1)) ELSE substr(_h, i + 1, 1) END), '')"
    tld = f"if(substring_index({value}, '.', -1) IN ('com', 'org', 'net'), substring_index({value}, '.', -1), 'com')"
    mail = f"concat({_redrawn(f'substring_index({value}, chr(64), 1)', '_h')}, '@', {_redrawn(f'substring_index(substring_index({value}, chr(64), -1), chr(46), 1)', 'reverse(_h)')}, '.example.', {tld})"
    address = "concat_ws('.', " + ", ".join(f"cast(1 + {number(k)} % 254 AS string)" for k in range(4)) + ")"
    digits = _redrawn(value, "_h", ("0123456789",))
    # The country code or trunk prefix stays, and a fictional exchange stays fictional.
    prefix = f"regexp_extract({value}, '^(\\\\+|00)[0-9]{{1,3}}(?=[^0-9])|^\\\\+[0-9]|^00[0-9]|^\\\\(?0', 0)"
    phone = f"concat({prefix}, regexp_replace(substr({digits}, length({prefix}) + 1), '[0-9]{{3}}([ .-]?[0-9]{{4}})$', if({value} rlike '555[ .-]?[0-9]{{4}}$', '555$1', '$0')))"
    # An address of the range for documentation; an account of the same country with the check digits that fit.
    address6 = "concat('2001:db8:', array_join(transform(sequence(0, 5), g -> substr(_h, g * 4 + 1, 4)), ':'))"
    body = f"substr({_redrawn(value, '_h', (UPPER, DIGITS))}, 5)"
    rest = f"aggregate(split(regexp_replace(concat({body}, substr({value}, 1, 2), '00'), ' ', ''), ''), 0, (a, c) -> CASE WHEN c = '' THEN a WHEN c rlike '[A-Z]' THEN (a * 100 + ascii(c) - 55) % 97 ELSE (a * 10 + ascii(c) - 48) % 97 END)"
    account = f"concat(substr({value}, 1, 2), lpad(cast(98 - {rest} AS string), 2, '0'), {body})"
    known = f"regexp_extract({value}, '^(gh[pousr]_|github_pat_|glpat-|AKIA|ASIA|AIza|xox[abeprs]-|[spr]k[-_](live_|test_|proj-)?|eyJ)', 0)"
    token = f"concat({known}, substr({_redrawn(value, '_h', (LOWER, UPPER, DIGITS))}, length({known}) + 1))"
    # Initials are shifted alike, by 1 to 25 letters: no two share one and none stays.
    shift = f"cast(conv(substr(sha2('{key}|initial', 256), 1, 4), 16, 10) AS int) % 25 + 1"
    initial = f"concat(chr(65 + (ascii({value}) - 65 + {shift}) % 26), '.')"
    # Where short names are crowded, later draws are longer.
    longer = f"substr(concat(substr('aeiou', 1 + {number(7)} % 5, 1), substr('lnrst', 1 + {number(8)} % 5, 1), substr('aeiou', 1 + {number(9)} % 5, 1), substr('lnrst', 1 + {number(10)} % 5, 1)), 1, {attempt} div 10)"
    plain = "regexp_replace({}, '[^0-9]', '')"
    first = f"if({value} rlike '^3' AND length({plain.format(value)}) < 16, 2, 1)"  # of 14 and 15 digits two tell the issuer
    head = f"concat(substr({value}, 1, {first}), substr({digits}, {first} + 1, length({value}) - {first} - 1))"
    fitting = f"filter(sequence(0, 9), d -> luhn_check(concat({plain.format(head)}, cast(d AS string))) = luhn_check({plain.format(value)}))"
    card = f"concat({head}, cast({fitting}[{number(5)} % size({fitting})] AS string))"
    # The names to draw from in a keyed order, and of these the one at the value's own place: no two values share one.
    listed = lambda names: "array(" + ", ".join(f"'{n}'" for n in names) + ")"
    dealt = "array_sort(transform({}, n -> struct(sha2(concat_ws('|', '" + key + "', {}, n, cast({} AS string)), 256) AS h, n AS n)))[array_position({}, {}) - 1].n"
    female, male = (dealt.format(listed(new), kind, attempt, listed(found), value) for new, found in ((FEMALE, FOUND_FEMALE), (MALE, FOUND_MALE)))
    cases = f"""CASE {kind} WHEN 'email' THEN {mail} WHEN 'ip' THEN {address} WHEN 'phone' THEN {phone} WHEN 'ip6' THEN {address6} WHEN 'iban' THEN {account} WHEN 'token' THEN {token} WHEN 'initial' THEN {initial} WHEN 'card' THEN {card} WHEN 'ssn' THEN {digits} WHEN 'secret' THEN {hexed}
        WHEN 'female' THEN {female} WHEN 'male' THEN {male} ELSE concat({_redrawn(value, '_h')}, {longer}) END"""
    # The digest is bound once, as the one element of an array.
    return F.expr(f"transform(array({digest}), _h -> {cases})[0]")


def surrogate_table(values: DataFrame, key: str, most_rounds: int = 50) -> DataFrame:
    """``value``, ``kind``, ``surrogate`` for distinct values; within a type surrogates differ from each other and from all values.

    Initials are exempt, as a permutation of all letters needs no check.
    """
    now = values.withColumn("attempt", F.lit(0))
    for k in range(most_rounds):
        now = materialize(now.withColumn("surrogate", surrogate(key=key)), "surrogates")
        same = Window.partitionBy("kind", F.lower("surrogate")).orderBy("attempt", F.lower("value"))
        taken = values.select(F.col("kind").alias("_k"), F.lower("value").alias("_v")).distinct()
        hit = now.withColumn("_place", F.dense_rank().over(same)).join(taken, (F.col("kind") == F.col("_k")) & (F.lower("surrogate") == F.col("_v")), "left")
        again = (F.col("kind") != "initial") & ((F.col("_place") > 1) | F.col("_v").isNotNull())
        checked = materialize(hit.select("value", "kind", "attempt", "surrogate", again.alias("again")), "surrogates-checked")
        if checked.where("again").isEmpty():
            return checked.select("value", "kind", "surrogate")
        now = checked.select("value", "kind", (F.col("attempt") + F.col("again").cast("int")).alias("attempt"))
    raise RuntimeError("a type has more distinct values than its format has surrogates")


def _mentions(gap: str) -> str:
    """SQL: a stretch between entities with the words that are parts of the text's names (map ``_own``) replaced."""
    return f"array_join(zip_with(split({gap}, r'{WORD_SQL}', -1), regexp_extract_all({gap}, r'{WORD_SQL}', 0), (g, w) -> concat(g, coalesce(_own[w], w, ''))), '')"


def replace_entities(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", key: str | None = None, whole_names: bool = True) -> DataFrame:
    """One row per input row: id, ``text`` with surrogates, ``n_entities``.

    With ``whole_names`` the words that follow a given name are replaced too; without, only the given name is.
    """
    secret = hashlib.sha256((key or secrets.token_hex(32)).encode()).hexdigest()
    found = any_pattern(whole_names)
    read = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text"))
    # The full pattern is tried only on texts with a digit, an at sign or a word that leads a name.
    has = F.coalesce((F.col("_text").rlike("[0-9@]") | F.col("_text").rlike(LEADS)) & F.col("_text").rlike(found), F.lit(False))
    untouched = read.where(~has).select(F.col("_id").alias(id_col), F.col("_text").alias("text"), F.lit(0).alias("n_entities"))
    held = read.where(has).select("_id", "_text", F.regexp_extract_all("_text", F.lit(found), F.lit(0)).alias("_found"), F.monotonically_increasing_id().alias("_row"))
    held = materialize(held, "surrogates-texts").withColumn("_n", F.size("_found"))
    places = held.select("_row", F.posexplode("_found").alias("_at", "_entity")).select("_row", "_at", F.posexplode(parts_of(F.col("_entity"))).alias("_part", "_piece")).select("_row", "_at", "_part", "_piece.*")
    values = places.select("value").distinct().withColumn("kind", kind_of(F.col("value")))
    table = surrogate_table(materialize(values, "surrogates-values"), secret)
    new = places.join(table, "value").groupBy("_row").agg(F.array_sort(F.collect_list(F.struct("_at", "_part", "lead", "surrogate", "kind", "value"))).alias("_new"))
    names = "filter(_new, x -> x.kind IN ('surname', 'male', 'female'))"
    new = new.withColumn("_own", F.expr(f"map_from_entries(array_distinct(transform({names}, x -> struct(x.value, x.surrogate))))"))
    # Before the first part of an entity comes the text since the last one.
    woven = held.join(new, "_row").withColumn("_between", F.split("_text", found, -1))
    woven = woven.withColumn("_gaps", F.expr(f"IF(size(_own) = 0, _between, transform(_between, gap -> {_mentions('gap')}))"))
    text = F.expr("concat(array_join(transform(_new, x -> concat(IF(x._part = 0, _gaps[x._at], ''), x.lead, x.surrogate)), ''), _gaps[_n])")
    more = F.expr(f"IF(size(_own) = 0, 0, aggregate(_between, 0, (n, gap) -> n + size(filter(regexp_extract_all(gap, r'{WORD_SQL}', 0), w -> _own[w] IS NOT NULL))))")
    return untouched.unionByName(woven.select(F.col("_id").alias(id_col), text.alias("text"), (F.col("_n") + more).alias("n_entities")))
