"""Personal data: detection and surrogates, in SQL functions only.

A text is cut at every entity that one combined pattern finds; each entity gets a
surrogate of its own type, script and format, made under a key from its canonical
form (so all spellings of one entity, in all documents, get the same one), and the
pieces are joined again. Nothing is shuffled for that.

Numbers, addresses and secrets are moved by a keyed permutation of the strings of
their own format (a Feistel network over characters or octets; check digits are
computed anew), so different entities differ by construction, however many there are.
Names come from syllables. Collision checks run over the distinct entities of all
documents: where two would share a surrogate, or a surrogate is itself a real entity,
all but the first are made anew under a higher attempt, outside of what the first
attempts took. A permuted entity for which no attempt finds a free place (its format is
full) goes back to the first, which no other has. Family names are entities of their
own, shared by all names that hold them. The entities with a raised attempt, or with
titles of several genders, travel to the documents that hold them.

The key is an argument, or the session's ``spark.netprop.pii.key``. Where neither is
set, a call draws one, and its surrogates go with no other call's.
"""

from __future__ import annotations

import secrets
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from netprop.llm import common

KEY_SETTING = "spark.netprop.pii.key"
#: Attempts to find a free surrogate; rounds of the permutation.
ROUNDS, FEISTEL = 12, 6

_OCTET = r"(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)"
_QUAD = rf"{_OCTET}(?:\.{_OCTET}){{3}}"
_HEXTET = "[0-9a-fA-F]{1,4}"
_TITLE_M = r"Mr|Herr|Monsieur|Señor|Sr|Don|Sir|Господин|Κύριος"
_TITLE_F = r"Mrs|Ms|Miss|Frau|Madame|Mme|Mlle|Señora|Señorita|Sra|Srta|Doña|Lady|Госпожа|Κυρία"
_TITLE_N = r"Dr|Prof|Professor"
_NAME = r"[\p{Lu}][\p{Ll}\p{Mn}'’-]{1,40}"

#: Type and pattern, in the order in which they are tried at a place. Each opens with a check of
#: the next characters that fails fast, and looks behind only after it; repetitions without a bound are possessive.
PATTERNS: tuple[tuple[str, str], ...] = (
    ("email", r"(?=[A-Za-z0-9._%+-]{1,64}@)(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}@(?:[A-Za-z0-9-]{1,63}\.){1,8}[A-Za-z]{2,24}"),
    ("secret", r"(?=[A-Za-z0-9_+/.-]{16})(?<=[=:\s\"'])(?<=\b(?i:token|secret|password|passwd|api[_-]?key|access[_-]?key|auth[_-]?key)\s{0,2}[=:]\s{0,2}[\"']?)[A-Za-z0-9_+/.-]{16,}+"),
    ("secret", r"(?=[0-9a-fA-F]{32})(?<![0-9A-Za-z_])(?=[a-fA-F]*+[0-9])(?=[0-9]*+[a-fA-F])[0-9a-fA-F]{32,}+(?![0-9A-Za-z_])"),
    ("iban", r"(?=[A-Z]{2}[0-9]{2})(?<![0-9A-Za-z_])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![0-9A-Za-z_])"),
    ("ipv6", rf"(?=[0-9a-fA-F]{{1,4}}:[0-9a-fA-F])(?<![\w:])(?:{_HEXTET}:){{6}}(?:{_QUAD}(?!\.?[0-9])|{_HEXTET}:{_HEXTET})(?![\w:])"),
    ("ipv6", rf"(?=[0-9a-fA-F]{{0,4}}:[0-9a-fA-F:])(?<![\w:])(?:{_HEXTET}(?::{_HEXTET}){{0,6}}::|::(?=[0-9a-fA-F]))(?:(?:{_HEXTET}:){{0,5}}{_QUAD}(?!\.?[0-9])|{_HEXTET}(?::{_HEXTET}){{0,6}})?(?![\w:])"),
    ("ip", rf"(?=[0-9]{{1,3}}\.[0-9])(?<![0-9.]){_OCTET}(?:\.{_OCTET}){{3}}(?!\.?[0-9])"),
    ("phone", r"\+(?<![\w+]\+)[0-9]{1,3}[ .-]?(?:\([0-9]{1,4}\)|[0-9]{1,4})(?:[ .-]?[0-9]{2,4}){2,4}(?![0-9])"),
    ("phone", r"\((?<!\w\()[0-9]{3}\) ?[0-9]{3}[ .-][0-9]{4}(?![0-9])"),
    ("phone", r"(?=[0-9]{3}[.-][0-9]{3})(?<![\w.-])[0-9]{3}[.-][0-9]{3}[.-][0-9]{4}(?![\w-])"),
    ("ssn", r"(?=[0-9]{3}-[0-9]{2}-)(?<![\w.-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![\w-])"),
    ("card", r"[0-9](?<![\w.-][0-9])(?:[ -]?[0-9]){12,18}(?![\w-])"),
    ("name", rf"(?=\p{{Lu}})(?<= )(?<=\b(?:{_TITLE_M}|{_TITLE_F}|{_TITLE_N})\.?[ ]){_NAME}(?: {_NAME})?"),
)
#: A text without any of this holds no entity; it is passed on as it is. Each pattern needs an @, a digit, two colons
#: or colons between hex letters, a key word with its sign, or a title.
HINT = rf"[@0-9]|::|[a-fA-F]:[a-fA-F]{{1,4}}:|(?i:token|secret|password|passwd|key)\s{{0,2}}[=:]|(?=\p{{Lu}})\b(?:{_TITLE_M}|{_TITLE_F}|{_TITLE_N})\b"
ANY = "|".join(f"(?:{p})" for _, p in PATTERNS)

# Syllables of surrogate names (a consonant and a vowel), and endings by gender and of family names, by script.
_SCRIPTS = {
    "latin": ("b d f g k l m n p r s t v z", "a e i o u", "rin ton lus mer den", "ria lina nette sea dra", "berg well mann ford stein"),
    "cyrillic": ("б в г д з к л м н п р с т ф", "а е и о у", "рин тон лей мир дан", "рия лина нета сея дра", "енко ский цев ухин овец"),
    "greek": ("β γ δ ζ θ κ λ μ ν π ρ σ τ φ", "α ε ι ο υ", "ριν τος λας μης δων", "ρια λινα νετη σια δρα", "ιδης οπου ακης αδης ελης"),
}


def _syllables(script: str) -> list[str]:
    consonants, vowels = (part.split() for part in _SCRIPTS[script][:2])
    return [c + v for c in consonants for v in vowels]


def _let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once."""
    return F.transform(F.array(value), body).getItem(0)


def _digest(*parts: Column | str) -> Column:
    return F.sha2(F.concat_ws("\x1f", *[F.lit(p) if isinstance(p, str) else p for p in parts]), 256)


def luhn_sum(digits: Column) -> Column:
    """Luhn sum modulo 10 of a string of digits: every second digit from the right is doubled, its digits added."""
    n = F.length(digits)
    each = F.transform(F.split(digits, ""), lambda c, i: F.when((n - i) % 2 == 0, F.coalesce(c.try_cast("int"), F.lit(0)) * 2).otherwise(F.coalesce(c.try_cast("int"), F.lit(0))))
    return F.aggregate(each, F.lit(0), lambda a, x: a + F.when(x > 9, x - 9).otherwise(x)) % 10


def mod97(text: Column) -> Column:
    """Remainder by 97 of digits and capitals (A = 10, ...), as bank account numbers are checked."""
    return F.aggregate(
        F.split(text, ""), F.lit(0), lambda a, c: F.when(c == "", a).when(c.rlike("^[0-9]$"), (a * 10 + F.coalesce(c.try_cast("int"), F.lit(0))) % 97).otherwise((a * 100 + F.ascii(c) - 55) % 97)
    )


def compact(entity: Column) -> Column:
    return F.regexp_replace(entity, "[^A-Za-z0-9]", "")


def kind_of(entity: Column, title: Column | None = None) -> Column:
    """Type of a string that the combined pattern found; null where it is none after all (a number that fails its check)."""
    plain = compact(entity)
    hexed = plain.rlike("^(?=.*[0-9])(?=.*[A-Fa-f])[0-9A-Fa-f]{32,}$")
    groups = F.size(F.filter(F.split(entity, ":"), lambda g: g != "")) + entity.contains(".").cast("int")
    return (
        F.when(entity.contains("@"), "email")
        .when(entity.rlike(rf"^{_NAME}(?: {_NAME})?$") & ~entity.rlike("[0-9]"), "name")
        .when(entity.rlike(r"^[0-9a-fA-F]*:[0-9a-fA-F]*:[0-9a-fA-F:.]*$"), F.when(groups <= F.when(entity.contains("::"), 7).otherwise(8), "ipv6"))
        .when(entity.rlike(rf"^{_OCTET}(?:\.{_OCTET}){{3}}$"), "ip")
        .when(entity.rlike(r"^\d{3}-\d{2}-\d{4}$"), "ssn")
        .when(entity.rlike(r"^\+|^\(\d{3}\)|^\d{3}[.-]\d{3}[.-]\d{4}$"), "phone")
        .when(hexed, "secret")
        .when(entity.rlike(r"^\d(?:[ -]?\d){12,18}$"), F.when(luhn_sum(plain) == 0, "card"))
        .when(entity.rlike(r"^[A-Z]{2}\d{2}[A-Z0-9 ]{8,38}$"), F.when(mod97(F.concat(F.substring(plain, 5, 64), F.substring(plain, 1, 4))) == 1, "iban"))
        .when(F.length(entity) >= 16, "secret")
    )


def hextets(entity: Column) -> Column:
    """An IPv6 address as eight groups of four lower-case digits: zeros that ``::`` leaves out are put in, a dotted end becomes two groups."""
    octets = F.split(F.regexp_extract(entity, r"[0-9.]+$", 0), r"\.")
    two = lambda i: F.lpad(F.hex(F.coalesce(F.get(octets, F.lit(i)).try_cast("int"), F.lit(0))), 2, "0")
    dotted = F.concat(F.regexp_replace(entity, r"[0-9.]+$", ""), two(0), two(1), F.lit(":"), two(2), two(3))
    whole = F.when(entity.contains("."), dotted).otherwise(entity)
    part = lambda side: F.filter(F.split(side, ":"), lambda g: g != "")
    head, tail = part(F.substring_index(whole, "::", 1)), part(F.when(whole.contains("::"), F.substring_index(whole, "::", -1)).otherwise(""))
    zeros = F.array_repeat(F.lit("0"), F.greatest(F.lit(8) - F.size(head) - F.size(tail), F.lit(0)))
    return F.lower(F.array_join(F.transform(F.concat(head, zeros, tail), lambda g: F.lpad(g, 4, "0")), ":"))


def canonical(kind: Column, entity: Column) -> Column:
    """One form for all spellings of an entity."""
    hexed = compact(entity).rlike("^[0-9A-Fa-f]{32,}$")
    return F.when(kind == "ipv6", hextets(entity)).when(kind.isin("email", "name"), F.lower(entity)).when(kind.isin("phone", "card", "iban", "ssn"), compact(entity)).when((kind == "secret") & hexed, F.lower(entity)).otherwise(entity)


def permuted(text: Column, *key: Column | str, within: str = "class") -> Column:
    """``text`` moved by a keyed permutation of the strings of its format. Characters but ASCII letters and digits stay.

    Rounds take turns at the even and the odd characters: each is shifted by a hash of
    all others' and its place, which can be undone, so no two texts meet. ``within``:
    a character stays a digit, a small or a capital letter (``class``; ``phone``: the
    first also stays below 2 or not), or is any hex digit (``hex``).
    """

    def moved(c: Column, by: Column, i: Column) -> Column:
        if within == "hex":
            digits = F.lit("0123456789abcdef")
            return F.when(c.rlike("^[0-9a-f]$"), F.substring(digits, (F.pmod(F.instr(digits, c) - 1 + F.pmod(by, F.lit(16)), F.lit(16)) + 1).cast("int"), F.lit(1))).otherwise(c)

        def shifted(a: Column) -> Column:
            turn = lambda low, n: F.chr(F.lit(low) + F.pmod(a - low + F.pmod(by, F.lit(n)), F.lit(n)))
            digit = F.when(i > 0, turn(48, 10)).when(a >= 50, turn(50, 8)).otherwise(turn(48, 2)) if within == "phone" else turn(48, 10)
            return F.when(a.between(48, 57), digit).when(a.between(97, 122), turn(97, 26)).when(a.between(65, 90), turn(65, 26)).otherwise(c)

        return _let(F.ascii(c), shifted)

    def turn(state: Column, r: Column) -> Column:
        others = F.array_join(F.filter(state, lambda c, i: i % 2 != r % 2), "")
        return _let(_digest(*key, r.cast("string"), others), lambda h: F.transform(state, lambda c, i: F.when(i % 2 == r % 2, moved(c, F.xxhash64(h, i), i)).otherwise(c)))

    chars = F.filter(F.split(text, ""), lambda c: c != "")
    return F.array_join(F.aggregate(F.sequence(F.lit(0), F.lit(FEISTEL - 1)), chars, turn), "")


def permuted_address(form: Column, *key: Column | str) -> Column:
    """A dotted address moved by a keyed permutation of all of them: a Feistel network over its two halves."""
    octet = lambda i: F.coalesce(F.get(F.split(form, r"\."), F.lit(i)).try_cast("int"), F.lit(0))
    halves = F.struct((octet(0) * 256 + octet(1)).cast("long").alias("l"), (octet(2) * 256 + octet(3)).cast("long").alias("r"))

    def turn(s: Column, r: Column) -> Column:
        by = F.pmod(F.xxhash64(_digest(*key, r.cast("string"), s["r"].cast("string"))), F.lit(65536))
        return F.struct(s["r"].alias("l"), F.pmod(s["l"] + by, F.lit(65536)).cast("long").alias("r"))

    def shown(s: Column) -> Column:
        return F.concat_ws(".", *[(F.floor(s[h] / 256) if high else F.pmod(s[h], F.lit(256))).cast("string") for h in "lr" for high in (True, False)])

    return _let(F.aggregate(F.sequence(F.lit(0), F.lit(FEISTEL - 1)), halves, turn), shown)


def _name_part(word: Column, given: bool, gender: Column, key: str, attempt: Column) -> Column:
    """Surrogate of one lower-case name word: syllables by script, ending by gender or as a family name.

    Higher attempts have more syllables, so that there are more surrogates than names.
    """

    def build(script: str) -> Column:
        syllables = F.array(*map(F.lit, _syllables(script)))
        male, female, family = (part.split() for part in _SCRIPTS[script][2:])
        n = F.lit(3) + F.when(attempt < 3, attempt).otherwise(attempt * 2)

        def name(h: Column) -> Column:
            pick = lambda options, k: F.element_at(options, (F.pmod(F.xxhash64(h, k), F.size(options)) + 1).cast("int"))
            stem = F.array_join(F.transform(F.sequence(F.lit(1), n), lambda k: pick(syllables, k)), "")
            ending = lambda options: pick(F.array(*map(F.lit, options)), F.lit(0))
            return F.concat(stem, ending(family) if not given else F.when(gender == "f", ending(female)).otherwise(ending(male)))

        return _let(_digest(key, "given" if given else "family", word, attempt.cast("string")), name)

    return F.when(word.rlike(r"^\p{IsCyrillic}"), build("cyrillic")).when(word.rlike(r"^\p{IsGreek}"), build("greek")).otherwise(build("latin"))


def surrogate(kind: Column, form: Column, gender: Column, key: str, attempt: Column) -> Column:
    """Canonical surrogate of a canonical entity that is no name. Equal inputs give equal results everywhere; under one key and attempt, different ones different results."""
    own = (key, kind, attempt.cast("string"))
    # addresses at one domain stay together; example names are reserved and reach nobody
    local, domain, top = F.substring_index(form, "@", 1), F.substring_index(form, "@", -1), F.substring_index(form, ".", -1)
    host = permuted(F.substring(domain, F.lit(1), F.length(domain) - F.length(top) - 1), key, "domain", top)
    email = F.concat(permuted(local, *own, domain), F.lit("@"), host, F.lit(".example."), top)
    first, rest = F.substring(form, 1, 1), F.substring(form, F.lit(2), F.length(form) - 2)
    card = _let(F.concat(first, permuted(rest, *own, first)), lambda c: F.concat(c, ((F.lit(10) - luhn_sum(F.concat(c, F.lit("0")))) % 10).cast("string")))
    country = F.substring(form, 1, 2)
    iban = _let(permuted(F.substring(form, F.lit(5), F.length(form)), *own, country), lambda r: F.concat(country, F.lpad((F.lit(98) - mod97(F.concat(r, country, F.lit("00")))).cast("string"), 2, "0"), r))
    phone = F.concat(first, permuted(F.substring(form, F.lit(2), F.length(form)), *own, first, within="phone"))
    hexed = F.when(form.rlike("^[0-9a-f]{32,}$"), permuted(form, *own, "hex", within="hex"))
    return (
        F.when(kind == "email", email).when(kind == "ip", permuted_address(form, *own)).when(kind == "ipv6", permuted(form, *own, within="hex"))
        .when(kind == "phone", phone).when(kind == "card", card).when(kind == "iban", iban).otherwise(F.coalesce(hexed, permuted(form, *own)))
    )


def family_of(form: Column) -> Column:
    """The word of a name that is the family name: the last, or the only one."""
    return F.substring_index(form, " ", -1)


def full_name(form: Column, gender: Column, key: str, attempt: Column, family: Column) -> Column:
    """Surrogate of a name: ``family`` is the surrogate of its family name, before which a given name is put where the name has one."""
    given = _name_part(F.substring_index(form, " ", 1), True, gender, key, attempt)
    return F.when(form.contains(" "), F.concat_ws(" ", given, family)).otherwise(family)


def dressed(kind: Column, entity: Column, made: Column) -> Column:
    """A canonical surrogate in the format of the entity: punctuation, grouping and capitals."""
    plain = F.filter(F.split(entity, ""), lambda c: c != "")
    used = lambda i: F.length(compact(F.substring(entity, F.lit(1), (i + 1).cast("int"))))
    refill = F.array_join(F.transform(plain, lambda c, i: F.when(c.rlike("^[A-Za-z0-9]$"), F.substring(made, used(i).cast("int"), F.lit(1))).otherwise(c)), "")
    shown = F.when(kind.isin("phone", "card", "iban", "ssn"), refill).when(kind == "name", F.initcap(made)).otherwise(made)
    loud = (entity == F.upper(entity)) & (entity != F.lower(entity)) & kind.isin("email", "secret", "ipv6", "name")
    return F.when(loud, F.upper(shown)).otherwise(shown)


def entities(text: Column) -> Column:
    """Array of entities, in order."""
    return F.regexp_extract_all(text, F.lit(ANY), F.lit(0))


def _gender(before: Column) -> Column:
    return F.when(before.rlike(rf"\b(?:{_TITLE_F})\.? $"), "f").when(before.rlike(rf"\b(?:{_TITLE_M})\.? $"), "m").otherwise("n")


def marked(docs: DataFrame, text_col: str) -> DataFrame:
    """Adds ``_gaps`` (text between entities) and ``_found`` (kind, entity, form, gender): null where the hint is missing."""
    text = F.col(text_col)
    hinted = F.when(text.rlike(HINT), text)
    cut = docs.withColumn("_gaps", F.split(hinted, ANY, -1)).withColumn("_raw", entities(hinted))
    each = F.zip_with(
        F.col("_raw"), F.slice("_gaps", F.lit(1), F.size("_raw")), lambda e, before: F.struct(e.alias("entity"), kind_of(e).alias("kind"), _gender(before).alias("gender"))
    )
    some = F.transform(each, lambda x: F.struct(x.entity.alias("entity"), x.kind.alias("kind"), x.gender.alias("gender"), canonical(x.kind, x.entity).alias("form")))
    return cut.withColumn("_found", F.when(F.size("_raw") > 0, some)).drop("_raw")


def distinct_entities(cut: DataFrame) -> DataFrame:
    """``(kind, form, gender, mixed)`` of all entities; the gender of a form is that of any title it has had, ``mixed`` where it has had several."""
    each = cut.select(F.explode_outer("_found").alias("e"))  # an inner explode would add a filter that finds all entities once more
    rows = each.where("e.kind is not null").select("e.kind", "e.form", "e.gender")
    return rows.groupBy("kind", "form").agg(F.min("gender").alias("gender"), (F.min("gender") != F.max("gender")).alias("mixed"))


def settle(found: DataFrame, key: str, rounds: int = ROUNDS) -> DataFrame:
    """``(kind, form, gender, mixed, attempt, made)`` with distinct ``made`` per kind, none a real ``form`` of that kind.

    Family names are entities of their own (kind ``family``, one row per word): they
    are settled first, and names of two words take the surrogate settled for theirs.
    """
    found = common.checkpointed(found)
    names = found.where("kind = 'name'")
    families = names.select(F.lit("family").alias("kind"), family_of(F.col("form")).alias("form"), F.lit("n").alias("gender"), F.lit(False).alias("mixed")).distinct()

    def word_or_number(attempt: Column) -> Column:
        kind, form, gender = F.col("kind"), F.col("form"), F.col("gender")
        return F.when(kind == "family", _name_part(form, False, gender, key, attempt)).otherwise(surrogate(kind, form, gender, key, attempt))

    out = _settled(found.where("kind <> 'name'").unionByName(families), word_or_number, rounds)
    full = names.where(F.col("form").contains(" ")).withColumn("word", family_of(F.col("form")))
    full = full.join(out.where("kind = 'family'").select(F.col("form").alias("word"), F.col("made").alias("family")), "word").drop("word")
    named = _settled(full, lambda attempt: full_name(F.col("form"), F.col("gender"), key, attempt, F.col("family")), rounds)
    return out.unionByName(named.drop("family"))


def _settled(found: DataFrame, make: Callable[[Column], Column], rounds: int) -> DataFrame:
    """``found`` with ``attempt`` and ``made``, raised until no two ``made`` of a kind are equal and none is a ``form``.

    Raised ones stay out of what all first attempts made. So those that are still not
    free after ``rounds`` can go back to their first, which nothing else has taken if
    first attempts differ by construction (all but names, whose space grows instead).
    """
    from pyspark.sql.window import Window

    first = common.checkpointed(found.withColumn("attempt", F.lit(0)).withColumn("made", make(F.lit(0))))
    now, taken = first, first.select("kind", F.col("form").alias("made"), F.lit(True).alias("real")).unionByName(first.select("kind", "made", F.lit(False).alias("real")))
    taken = taken.groupBy("kind", "made").agg(F.max("real").alias("real"))
    for _ in range(rounds):
        order = Window.partitionBy("kind", "made").orderBy("attempt", "form")
        judged = now.join(taken, ["kind", "made"], "left").withColumn("at", F.row_number().over(order))
        judged = judged.withColumn("again", F.coalesce("real", F.lit(False)) | (F.col("at") > 1) | ((F.col("attempt") > 0) & F.col("real").isNotNull()))
        judged = common.checkpointed(judged.select(*found.columns, (F.col("attempt") + F.col("again").cast("int")).alias("attempt"), "made", "again"))
        if common.is_empty(judged.where("again")):
            return judged.drop("again")
        now = judged.withColumn("made", F.when(F.col("again"), make(F.col("attempt"))).otherwise(F.col("made"))).drop("again")
    back = F.col("again") & ~F.col("kind").isin("name", "family")
    return common.checkpointed(judged.withColumn("attempt", F.when(back, 0).otherwise(F.col("attempt"))).withColumn("made", F.when(F.col("again"), make(F.col("attempt"))).otherwise(F.col("made"))).drop("again"))


def key_of(spark: SparkSession) -> str:
    return spark.conf.get(KEY_SETTING, None) or secrets.token_hex(16)


def replace(docs: DataFrame, key: str | None = None, text_col: str = "text", count_col: str = "n_entities") -> DataFrame:
    """``docs`` with entities in ``text_col`` replaced, plus ``count_col`` (int; one of that name is replaced). All other columns and rows stay.

    Null and empty texts stay as they are. Repeated rows and ids need no care: a
    surrogate depends on the entity, the key and the corpus's entities alone.
    """
    key = key or key_of(docs.sparkSession)
    cut = marked(docs, text_col)
    settled = settle(distinct_entities(cut), key)
    raised = settled.where((F.col("attempt") > 0) | (F.col("mixed") & F.col("form").contains(" ") & (F.col("kind") == "name")))
    raised = common.checkpointed(raised.select("kind", "form", "attempt", "gender"))
    known = F.lit(None).cast("map<string,struct<attempt:int,gender:string>>")
    if not common.is_empty(raised):  # to the texts that hold them, by content
        needs = lambda e: F.array(F.struct(e.kind.alias("kind"), e.form.alias("form")), F.struct(F.when(e.kind == "name", "family").alias("kind"), family_of(e.form).alias("form")))
        holds = cut.select(F.xxhash64(text_col).alias("_h"), F.sha2(F.col(text_col), 256).alias("_s"), F.explode(F.flatten(F.transform("_found", needs))).alias("e"))
        holds = holds.select("_h", "_s", "e.kind", "e.form").join(raised, ["kind", "form"])
        holds = holds.select("_h", "_s", F.struct(F.concat_ws("\x1f", "kind", "form"), F.struct("attempt", "gender")).alias("p")).groupBy("_h", "_s").agg(F.map_from_entries(F.collect_set("p")).alias("_up"))
        cut = cut.withColumn("_h", F.xxhash64(text_col)).withColumn("_s", F.sha2(F.col(text_col), 256)).join(holds, ["_h", "_s"], "left").drop("_h", "_s")
        known = F.col("_up")

    def settled_as(kind: Column | str, form: Column) -> Column:
        return F.element_at(known, F.concat_ws("\x1f", F.lit(kind) if isinstance(kind, str) else kind, form))

    def put(e: Column) -> Column:
        own = settled_as(e.kind, e.form)
        up, gender = F.coalesce(own["attempt"], F.lit(0)), F.coalesce(own["gender"], e.gender)
        word = family_of(e.form)
        family = _name_part(word, False, gender, key, F.coalesce(settled_as("family", word)["attempt"], F.lit(0)))
        made = F.when(e.kind == "name", full_name(e.form, gender, key, up, family)).otherwise(surrogate(e.kind, e.form, e.gender, key, up))
        return F.when(e.kind.isNull(), e.entity).otherwise(dressed(e.kind, e.entity, made))

    n = F.size(F.filter("_found", lambda e: e.kind.isNotNull()))
    joined = F.concat(F.array_join(F.zip_with(F.slice("_gaps", F.lit(1), F.size("_found")), F.col("_found"), lambda gap, e: F.concat(gap, put(e))), ""), F.element_at("_gaps", -1))
    text = F.when(F.col("_found").isNotNull(), joined).otherwise(F.col(text_col))
    count = F.coalesce(F.when(F.col("_found").isNotNull(), n), F.lit(0)).cast("int")
    return cut.withColumns({text_col: text, count_col: count}).select(*[c for c in docs.columns if c != count_col], count_col)
