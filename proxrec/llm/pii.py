"""Keyed surrogates for personal data, in DataFrame expressions only.

Found are e-mail addresses, IPv4 addresses, phone numbers, card-like numbers, social-security-like numbers and names after a form of address; a
name's words are then also found alone in the same document. Each entity is replaced by a keyed permutation of its own format class: digits
stay digits, letters stay letters of their script, case and kind (vowel or consonant), punctuation stays, a name keeps the form of
address, a given name of GIVEN becomes another of its gender and script, other words of a name keep the last letter that marks a gender, a phone number its country code, a card number its first digit and whether its check digit is right,
an address its top-level domain. The permutation is an alternating Feistel network over mixed radices, a keyed step and the network's inverse, so within a
class two entities never get one surrogate (distinctness), none gets itself, one entity always gets the same (coreference, also across
spellings of one number). Words outside GIVEN are permuted on until they lie outside it, so no two words meet there either. ``collisions`` checks distinctness
and coreference over all entities, and lists surrogates that equal another entity's original, as happens to short names; ``checked`` runs it and
takes a further key should two entities meet. Only an address without letters and digits before its top-level domain stays.

Defined results: null texts stay null and have no entities, empty texts stay empty; repeated rows give equal results; entities that overlap
are taken leftmost first; extra columns pass through and those named like a result column are replaced; the key may be any string.
"""

from __future__ import annotations

import unicodedata

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load

#: Forms of address by gender.
TITLES = {
    "m": ("Mr", "Mister", "Sir", "Herr", "Monsieur", "Señor", "Sr", "Don", "Господин"),
    "f": ("Mrs", "Ms", "Miss", "Madam", "Frau", "Madame", "Mme", "Mlle", "Señora", "Señorita", "Sra", "Doña", "Госпожа"),
}
TITLE = "(?:" + "|".join(sorted((t for ts in TITLES.values() for t in ts), key=lambda t: (-len(t), t))) + ")"
#: Given names by script and gender; each stands for another of its row.
GIVEN = (
    "James John Robert Michael William David Richard Thomas Daniel Paul Mark George Peter Henry Martin Hans Karl Klaus Wolfgang Pierre Jean Michel Philippe Luis Carlos Juan José Pedro Antonio Jürgen".split(),
    "Mary Patricia Jennifer Linda Elizabeth Barbara Susan Sarah Karen Anna Laura Emma Julia Helen Alice Ingrid Ursula Monika Sabine Claudia Marie Sophie Isabelle Nathalie Camille María Carmen Ana Lucía Elena".split(),
    "Иван Николай Сергей Алексей Дмитрий Андрей Михаил Владимир Александр Борис".split(),
    "Анна Мария Елена Ольга Наталья Татьяна Ирина Екатерина Светлана Юлия".split(),
    "Νίκος Κώστας Δημήτρης Γιάννης Παύλος Αλέξανδρος".split(),
    "Μαρία Ελένη Κατερίνα Σοφία Άννα Ειρήνη".split(),
)
#: Steps that lead a word out of GIVEN; a step ends inside it with a chance far below one in a thousand.
STEPS = 6
#: Letters that may stand for each other.
DIGITS = "0123456789"
LATIN = "abcdefghijklmnopqrstuvwxyz"
NAME_CLASSES = ("aeiou", "bcdfghjklmnpqrstvwxyz", "áéíóúàèìòùâêîôûäëïöü", "ñç", "аеёиоуыэюя", "бвгджзйклмнпрстфхцчшщ", "ъь", "αεηιουω", "βγδζθκλμνξπρστφχψ")



def other_classes() -> tuple[tuple[str, ...], tuple[str, ...]]:
    """Classes of the cased letters that NAME_CLASSES lacks, by script, page of code points and kind: of lower-case letters with one partner in upper case,
    and of letters without, which stand for each other as they are. None has a single letter."""
    recent = {*map(chr, (0xA7C0, 0xA7C1, 0x2C2F, 0x2C5F, *range(0xA7D0, 0xA7DA))), *map(chr, range(0x1DF00, 0x1E000))}  # younger than Java 17's tables
    found: dict[tuple, list[str]] = {}
    for c in map(chr, range(0x110000)):
        case = unicodedata.category(c)
        if case not in ("Lu", "Ll") or any(c.lower() in a for a in NAME_CLASSES):
            continue
        low = c.lower()
        paired = len(low) == 1 and len(low.upper()) == 1 and low.upper() != low and low.upper().lower() == low
        if paired and case == "Lu":
            continue
        vowel = unicodedata.normalize("NFD", c)[0] in "aeiouyαεηιουωаеиоуыэюя"
        found.setdefault(("pair" if paired else case, c in recent, unicodedata.name(c).split()[0], ord(c) >> 8, vowel), []).append(c)
    for short in range(4, 0, -1):  # lone letters join others of their script, or else of their kind
        for key in [k for k, v in found.items() if len(v) == 1]:
            near = next((k for k in found if k != key and k[:short] == key[:short]), None)
            if near:
                found[near] += found.pop(key)
    return tuple("".join(v) for k, v in found.items() if k[0] == "pair"), tuple("".join(v) for k, v in found.items() if k[0] != "pair")


OTHER_CLASSES, CASELESS_CLASSES = other_classes()
#: The country codes, a set without common prefixes; three digits wherever no shorter one is given. Separators may stand anywhere.
COUNTRY = r"^[+](?:[17]|2[ .()-]*[07]|3[ .()-]*[0-469]|4[ .()-]*[013-9]|5[ .()-]*[1-8]|6[ .()-]*[0-6]|8[ .()-]*[1246]|9[ .()-]*[0-58]|[0-9][ .()-]*[0-9][ .()-]*[0-9])"

LETTER = r"\p{Lu}\p{Ll}0-9"
EMAIL = rf"(?<![{LETTER}._%+-])[{LETTER}._%+-]{{1,64}}@[{LETTER}-]{{1,63}}(?:\.[{LETTER}-]{{1,63}}){{0,125}}\.(?:[Xx][Nn]--[A-Za-z0-9-]{{2,59}}|[\p{{Lu}}\p{{Ll}}]{{2,24}})(?![{LETTER}-])"
OCTET = r"(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
IP = rf"(?<![0-9.]){OCTET}(?:\.{OCTET}){{3}}(?!\.?[0-9])"
PHONE = r"(?<![0-9])\+[0-9]{1,3}[ .-]?\(?[0-9]{2,4}\)?(?:[ .-]?[0-9]{2,4}){2,4}(?![0-9])|(?<![0-9])(?:\([0-9]{3}\) ?|[0-9]{3}[-.])[0-9]{3}[-.][0-9]{4}(?![0-9])"
SSN = r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])"
CARD = r"(?<![0-9])[0-9](?:[ -]?[0-9]){12,18}(?![0-9])"
NAME = rf"(?<!\p{{L}}){TITLE}\.? \p{{Lu}}\p{{Ll}}+(?:[ -]\p{{Lu}}\p{{Ll}}+){{0,2}}"
ANY = "|".join((EMAIL, IP, SSN, PHONE, CARD, NAME))
TYPES = ("email", "ip", "phone", "ssn", "card", "name")
ROUNDS = 8


def quoted(text: str) -> str:
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


def let(name: str, value: str, body: str) -> str:
    """SQL in which ``name`` stands for ``value``, computed once."""
    return f"transform(array({value}), {name} -> {body})[0]"


def permuted(values: str, radices: str, key: str, tweak: str) -> str:
    """SQL: the keyed permutation of array<int> ``values`` where value i lies below radix i.

    In turn one half is shifted, place by place, by digests of the other half; then the first place by a keyed number that is never 0, and the rounds
    are taken back. So no value stays as it is, if the first radix is above 1.
    """
    other = f"CASE WHEN k % 2 = 0 THEN slice(acc, 1 + size(acc) DIV 2 + size(acc) % 2, size(acc)) ELSE slice(acc, 1, size(acc) DIV 2 + size(acc) % 2) END"
    digest = f"sha2(concat_ws('|', {key}, {tweak}, CAST(k AS STRING), CAST(i AS STRING), array_join(transform({other}, q -> CAST(q AS STRING)), ',')), 256)"
    shift = f"CAST(conv(substring({digest}, 1, 12), 16, 10) AS BIGINT)"
    moved = lambda sign: f"CASE WHEN (i < size(acc) DIV 2 + size(acc) % 2) = (k % 2 = 0) THEN CAST(pmod(CAST(v AS BIGINT) {sign} {shift}, rs[i]) AS INT) ELSE v END"
    rounds = lambda ks, start, sign: f"aggregate({ks}, {start}, (acc, k) -> transform(acc, (v, i) -> {moved(sign)}))"
    step = f"CAST(conv(substring(sha2(concat_ws('|', {key}, {tweak}, array_join(transform(rs, q -> CAST(q AS STRING)), ',')), 256), 1, 12), 16, 10) AS BIGINT)"
    there = f"transform({rounds(f'sequence(0, {ROUNDS - 1})', values, '+')}, (v, i) -> CASE WHEN i = 0 THEN CAST(pmod(v + 1 + pmod({step}, greatest(rs[0] - 1, 1)), rs[0]) AS INT) ELSE v END)"
    return let("rs", radices, rounds(f"sequence({ROUNDS - 1}, 0, -1)", there, "-"))


def luhn_check(digits: str) -> str:
    """SQL: the check digit that would follow an array<int> of digits."""
    doubled = "CASE WHEN (size(ds) - i) % 2 = 1 THEN (2 * d) DIV 10 + (2 * d) % 10 ELSE d END"
    return let("ds", digits, f"pmod(-aggregate(transform(ds, (d, i) -> CAST({doubled} AS INT)), 0, (s, d) -> s + d), 10)")


def respelled(word: str, kind: str, key: str) -> str:
    """SQL: the surrogate of a word of the given kind (SQL expressions), character by character."""
    names = " ".join([f"WHEN locate(lower(c), '{a}') > 0 THEN '{a}'" for a in NAME_CLASSES + OTHER_CLASSES] + [f"WHEN locate(c, '{a}') > 0 THEN '{a}'" for a in CASELESS_CLASSES])
    fixed = (
        f"({kind} = 'phone' AND i < length(regexp_extract({word}, {quoted(COUNTRY)}, 0))) OR ({kind} = 'card' AND (i = 0 OR i = length({word}) - 1)) "
        f"OR ({kind} = 'email' AND i >= length({word}) - locate('.', reverse({word}))) OR ({kind} = 'name' AND i = length({word}) - 1)"
    )
    alphabet = f"CASE WHEN {fixed} THEN '' WHEN locate(c, '{DIGITS}') > 0 THEN '{DIGITS}' WHEN {kind} = 'email' AND locate(lower(c), '{LATIN}') > 0 THEN '{LATIN}' WHEN {kind} IN ('name', 'email') THEN CASE {names} ELSE '' END ELSE '' END"
    cs = f"transform(filter(split({word}, ''), c -> c <> ''), (c, i) -> named_struct('c', c, 'a', {alphabet}))"
    active = "transform(filter(cs, y -> y.a <> ''), y -> named_struct('v', CAST(coalesce(nullif(locate(y.c, y.a), 0), locate(lower(y.c), y.a)) - 1 AS INT), 'r', length(y.a)))"
    letter = "substring(y.a, 1 + p[acc.k], 1)"
    rebuilt = f"aggregate(cs, named_struct('k', 0, 'out', ''), (acc, y) -> named_struct('k', acc.k + CASE WHEN y.a <> '' THEN 1 ELSE 0 END, 'out', concat(acc.out, CASE WHEN y.a = '' THEN y.c WHEN locate(y.c, y.a) > 0 THEN {letter} ELSE upper({letter}) END)), acc -> acc.out)"
    plain = let("cs", cs, let("act", active, let("p", permuted("transform(act, y -> y.v)", "transform(act, y -> y.r)", key, f"CASE WHEN {kind} = 'ssn' THEN 'ssn' ELSE {kind} END"), rebuilt)))
    ints = lambda s: f"transform(filter(split({s}, ''), c -> c rlike '[0-9]'), c -> CAST(c AS INT))"
    body = lambda s: f"slice({s}, 1, size({s}) - 1)"
    checked = let("w1", plain, let("was", ints(word), let("now", ints("w1"), f"concat(substring(w1, 1, length(w1) - 1), CAST(pmod({luhn_check(body('now'))} + element_at(was, -1) - {luhn_check(body('was'))}, 10) AS STRING))")))
    octets = f"array_join(transform({permuted(f'transform(split({word}, {quoted(chr(92) + chr(46))}), c -> CAST(c AS INT))', 'array_repeat(256, 4)', key, quoted('ip'))}, c -> CAST(c AS STRING)), '.')"
    return f"CASE WHEN {kind} = 'ip' THEN {octets} WHEN {kind} = 'card' THEN {checked} ELSE {plain} END"


def renamed(word: str, key: str) -> str:
    """SQL: the surrogate of one word of a name."""
    lists = [f"array({', '.join(quoted(n) for n in names)})" for names in GIVEN]
    step = lambda i, n: f"(1 + pmod(CAST(conv(substring(sha2(concat_ws('|', {key}, 'given', '{i}'), 256), 1, 12), 16, 10) AS BIGINT), {n - 1}))"
    given = " ".join(f"WHEN array_contains({a}, {word}) THEN element_at({a}, CAST(1 + pmod(array_position({a}, {word}) - 1 + {step(i, len(GIVEN[i]))}, {len(GIVEN[i])}) AS INT))" for i, a in enumerate(lists))
    every = f"array({', '.join(quoted(n) for names in GIVEN for n in names)})"
    walked = f"aggregate(sequence(1, {STEPS}), {word}, (now, turn) -> CASE WHEN turn = 1 OR array_contains({every}, now) THEN {respelled('now', quoted('name'), key)} ELSE now END)"
    return f"CASE {given} ELSE {walked} END"


def kind_of(hit: str) -> str:
    return (
        f"CASE WHEN locate('@', {hit}) > 0 THEN 'email' WHEN rlike({hit}, {quoted('^' + IP + '$')}) THEN 'ip' WHEN rlike({hit}, {quoted(r'^[0-9]{3}-[0-9]{2}-[0-9]{4}$')}) THEN 'ssn' "
        f"WHEN rlike({hit}, {quoted(r'\p{L}')}) THEN 'name' WHEN rlike({hit}, {quoted('^(?:' + PHONE + ')$')}) THEN 'phone' ELSE 'card' END"
    )


def pseudonymise(docs: DataFrame, key: str, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Replaces the text and adds entities: array<struct<start, end, type, original, surrogate>> with offsets in the original text.

    One narrow pass: no shuffle, no Python. Texts without an entity are only matched once.
    """
    kept = [c for c in (docs.columns if keep is None else keep) if c.lower() != "entities" and c != text_col]
    t = f"`{text_col}`"
    df = docs.select(*[F.col(f"`{c}`") for c in kept], F.col(t))
    df = df.withColumn("_found", F.expr(f"coalesce(rlike({t}, {quoted(ANY)}), false)"))
    titled = f"regexp_extract_all({t}, {quoted(NAME)}, 0)"
    words = f"array_distinct(flatten(transform({titled}, n -> split(regexp_replace(n, {quoted('^' + TITLE + r'[.]? ')}, ''), '[ -]'))))"
    df = df.withColumn("_words", F.expr(f"CASE WHEN _found AND rlike({t}, {quoted(NAME)}) THEN {words} ELSE CAST(array() AS ARRAY<STRING>) END"))
    alone = f"concat({quoted('|' + r'(?<!\p{L})(?:')}, array_join(_words, '|'), {quoted(r')(?!\p{L})')})"
    df = df.withColumn("_pattern", F.expr(f"concat({quoted('(?s)(.*?)(' + ANY)}, CASE WHEN size(_words) > 0 THEN {alone} ELSE '' END, {quoted(r'|\z)')})"))
    pairs = f"zip_with(regexp_extract_all({t}, _pattern, 1), regexp_extract_all({t}, _pattern, 2), (g, h) -> named_struct('gap', g, 'hit', h, 'type', {kind_of('h')}))"
    parts = "CAST(array() AS ARRAY<STRUCT<gap: STRING, hit: STRING, type: STRING>>)"
    df = df.withColumn("_parts", F.expr(f"CASE WHEN _found THEN {pairs} ELSE {parts} END"))
    k = quoted(key)
    is_title = f"rlike(w, {quoted('^' + TITLE + '[.]?$')})"
    name = f"array_join(transform(split(x.hit, ' '), (w, at) -> CASE WHEN at = 0 AND x.hit <> w AND {is_title} THEN w ELSE array_join(transform(split(w, '-'), u -> {renamed('u', k)}), '-') END), ' ')"
    surrogate = f"CASE WHEN x.hit = '' THEN '' WHEN x.type = 'name' THEN {name} ELSE {respelled('x.hit', 'x.type', k)} END"
    df = df.withColumn("_parts", F.expr(f"transform(_parts, x -> named_struct('gap', x.gap, 'hit', x.hit, 'type', x.type, 'surrogate', {surrogate}))"))
    entry = "named_struct('start', acc.at + length(x.gap), 'end', acc.at + length(x.gap) + length(x.hit), 'type', x.type, 'original', x.hit, 'surrogate', x.surrogate)"
    none = "CAST(array() AS ARRAY<STRUCT<start: INT, end: INT, type: STRING, original: STRING, surrogate: STRING>>)"
    df = df.withColumn("entities", F.expr(f"aggregate(_parts, named_struct('at', 0, 'out', {none}), (acc, x) -> named_struct('at', acc.at + length(x.gap) + length(x.hit), 'out', CASE WHEN x.hit = '' THEN acc.out ELSE concat(acc.out, array({entry})) END), acc -> acc.out)"))
    df = df.withColumn(text_col, F.expr(f"CASE WHEN _found THEN array_join(transform(_parts, x -> concat(x.gap, x.surrogate)), '') ELSE {t} END"))
    return df.select(*[F.col(f"`{c}`") for c in kept], F.col(t), "entities")


def canonical(column: str, kind: str) -> str:
    """SQL for what one entity's spellings have in common."""
    return f"CASE WHEN {kind} IN ('phone', 'card', 'ssn') THEN regexp_replace({column}, '[^0-9+]', '') ELSE lower({column}) END"


def collisions(done: DataFrame) -> DataFrame:
    """Surrogates that stand for several originals of a type, or equal an original: type, surrogate, originals, is_original.

    Entities are deduplicated before they are shuffled, so a hot entity is one row a task.
    """
    pairs = done.select(F.explode("entities").alias("e")).select("e.type", F.expr(canonical("e.original", "e.type")).alias("original"), F.expr(canonical("e.surrogate", "e.type")).alias("surrogate")).distinct()
    shared = pairs.groupBy("type", "surrogate").agg(F.count("*").alias("originals"))
    known = pairs.select("type", F.col("original").alias("surrogate")).distinct().withColumn("is_original", F.lit(True))
    return shared.join(known, ["type", "surrogate"], "left").withColumn("is_original", F.coalesce("is_original", F.lit(False))).where("originals > 1 OR is_original")


def checked(docs: DataFrame, key: str, text_col: str = "text", keep: list[str] | None = None, attempts: int = 4) -> DataFrame:
    """pseudonymise, after a check over all entities that no two of a type share a surrogate; a further key is taken if they do."""
    for attempt in range(attempts):
        done = pseudonymise(docs, key if not attempt else f"{key}#{attempt}", text_col, keep)
        if collisions(done).where("originals > 1").isEmpty():
            return done
    raise ValueError(f"entities share surrogates under {attempts} keys")


def op1_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = checked(load(spark, sf_dir, "documents"), key="corpus-surrogates-v1", keep=["doc_id"])
    counts = [F.expr(f"CAST(size(filter(entities, x -> x.type = '{t}')) AS BIGINT)").alias(f"n_{t}") for t in TYPES]
    return done.select("doc_id", *counts, "text")
