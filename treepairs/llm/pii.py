"""Personal data: detection and keyed surrogates, with DataFrame functions only.

Entities are e-mail addresses, telephone numbers, payment cards, IBANs, social security numbers, IPv4 addresses, secrets
(mixed tokens of 20 characters or more) and persons: names after a title, in any case, or after a cue word, and from there
on every mention of the same names in the same text, with or without a title. A surrogate is a function of a key, the kind
and the entity's canonical form, so mentions of one entity agree however they are written (coreference); a person's names are
entities of their own, so "Mr Smith", "John Smith" and "SMITH" agree. It is written in the format of the mention: digits for
digits, letters for letters of the same script in their case, octets of as many digits, the country prefix, mail domain and
title kept, check digits where the original had right ones (cards and IBANs), given names with an ending of the gender that
most titles before them have.

Distinctness: surrogates of all entities of the corpus are compared with each other and with all real entities; whoever
collides takes the next attempt, until no collision is left. From the third attempt on, formats that may be exhausted
(short mail names, short octets, names) get longer.

Defined cases: null and empty texts are returned as they are with no entities; entities are looked up by text, so rows that
repeat an id or have a null one do not meet; rows that repeat a text get the same one; very long texts are handled whole, in
one row; an empty table gives an empty result; other columns are kept by :func:`replace_entities`, whatever their names, and
``text`` and ``n_entities`` are set.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import checkpointed, unused

# Titles before a person's name, by gender, and words before a person's full name.
FEMALE_TITLES = ["Mrs", "Ms", "Miss", "Frau", "Señora", "Sra", "Madame", "Mme", "Госпожа", "Κυρία"]
MALE_TITLES = ["Mr", "Herr", "Señor", "Sr", "Monsieur", "Господин", "Κύριος"]
TITLES = ["Dr", "Prof", "Professor"]
CUES = ["met", "contact", "named", "dear", "name is", "name:", "signed", "regards,", "sincerely,", "attn:", "heißt", "s'appelle", "se llama"]

MAIL = r"(?<![\p{L}\p{N}._%+-])[\p{L}\p{N}][\p{L}\p{N}._%+-]*+@[\p{L}\p{N}-]+(?:\.[\p{L}\p{N}-]+)+"
def _any_case(words: list[str]) -> str:
    """One of the words in any case; a look at the first letter rules most places out."""
    first = "".join(sorted({c for w in words for c in (w[0].lower(), w[0].upper())}))
    return f"(?=[{first}])(?iu:" + "|".join(sorted(words, key=len, reverse=True)) + ")"


_TITLE = _any_case(FEMALE_TITLES + MALE_TITLES + TITLES)
_CUE = r"(?<=(?<!\p{L})(?iu:" + "|".join(CUES) + ") )"
_WORD = r"(?:\p{Lu}\p{Ll}++|\p{Lu}{2,}+)(?!\p{L})"
NAME = rf"(?<!\p{{L}}){_TITLE}\.? {_WORD}(?: {_WORD})?"
CUED = rf"(?=\p{{Lu}}){_CUE}(?!{_TITLE}\b){_WORD} {_WORD}"
PHONE = r"(?<![0-9+])\+[0-9]{1,3}[ .-]?\(?[0-9]{1,4}\)?(?:[ .-]?[0-9]{2,4}){2,4}(?![0-9])|(?<![0-9])\([0-9]{3}\) ?[0-9]{3}-[0-9]{4}(?![0-9])|(?<![0-9-])[0-9]{3}-[0-9]{3}-[0-9]{4}(?![0-9-])"
_OCTET = r"(?:25[0-5]|2[0-4][0-9]|1[0-9]{2}|[0-9]{1,2})"
ADDRESS = rf"(?<![0-9.]){_OCTET}(?:\.{_OCTET}){{3}}(?![0-9]|\.[0-9])"
SOCIAL = r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])"
IBAN = r"(?<![0-9A-Za-z])[A-Z]{2}[0-9]{2}(?:[A-Z0-9]{11,30}|(?: [A-Z0-9]{4}){2,7}(?: [A-Z0-9]{1,3})?)(?![0-9A-Za-z])"
CARD = r"(?<![0-9A-Za-z])[0-9]{4}(?:[ -]?[0-9]{4}){2}[ -]?[0-9]{1,7}(?![0-9A-Za-z])"
SECRET = r"(?<![0-9A-Za-z_-])(?=[A-Za-z_-]*[0-9])(?=[0-9_-]*[A-Za-z])[0-9A-Za-z_-]{20,}(?![0-9A-Za-z_-])"
ENTITY = "|".join([MAIL, NAME, CUED, PHONE, ADDRESS, SOCIAL, IBAN, CARD, SECRET])
#: What every entity has: a digit, an at sign, a title or a cue. Most texts have none, and this is quick to see.
HINT = f"[0-9@]|{_TITLE}\\.? \\p{{Lu}}|{_any_case(CUES)} \\p{{Lu}}"


def kind_of(entity: Column) -> Column:
    whole = [("email", MAIL), ("name", r"[\p{L}.' ]+"), ("phone", PHONE), ("ip", ADDRESS), ("ssn", SOCIAL), ("iban", IBAN), ("card", CARD)]
    out = F.lit("secret")
    for name, pattern in reversed(whole):
        out = F.when(entity.rlike(f"^(?:{pattern})$"), name).otherwise(out)
    return out


def canonical(kind: Column, entity: Column) -> Column:
    """The form in which mentions agree; a telephone number without a country prefix is one of the North American plan."""
    digits = F.regexp_replace(entity, "[^0-9]", "")
    return F.when((kind == "phone") & ~entity.startswith("+"), F.concat(F.lit("1"), digits)).when(kind.isin("phone", "card", "ssn"), digits).when(kind == "iban", F.lower(F.replace(entity, F.lit(" "), F.lit("")))).otherwise(F.lower(entity))


def _names(entity: Column) -> Column:
    """The names of a person's mention, without the title."""
    return F.split(F.regexp_replace(entity, rf"^{_TITLE}\.? ", ""), " ")


def _byte(stream: Column, i: Column) -> Column:
    """The ``i``-th byte of a hexadecimal stream of 64 bytes, over and over."""
    return F.conv(F.substring(stream, 2 * F.pmod(i, F.lit(64)).cast("int") + 1, F.lit(2)), 16, 10).cast("int")


def _letter(first: str, count: int, byte: Column) -> Column:
    return F.substring(F.lit("".join(chr(ord(first) + k) for k in range(count))), F.pmod(byte, F.lit(count)) + 1, F.lit(1))


def _spelled(stream: Column, text: Column, hexadecimal: Column) -> Column:
    """Digits for digits and letters for letters of their script, a-f for hexadecimal tokens."""

    def one(c: Column, i: Column) -> Column:
        b = _byte(stream, i)
        letter = F.when(c.rlike(r"\p{IsCyrillic}"), _letter("а", 32, b)).when(c.rlike(r"\p{IsGreek}"), _letter("α", 17, b)).when(hexadecimal, _letter("a", 6, b)).otherwise(_letter("a", 26, b))
        return F.when(c.rlike("[0-9]"), _letter("0", 10, b)).when(c.rlike(r"\p{L}"), letter).otherwise(c)

    return F.array_join(F.transform(F.split(text, ""), one), "")


def _octets(stream: Column, text: Column, wide: Column) -> Column:
    def one(c: Column, i: Column) -> Column:
        b = _byte(stream, i) * 256 + _byte(stream, i + 8)
        return F.when(wide | (F.length(c) == 3), 100 + F.pmod(b, F.lit(156))).when(F.length(c) == 2, 10 + F.pmod(b, F.lit(90))).otherwise(1 + F.pmod(b, F.lit(9))).cast("string")

    return F.array_join(F.transform(F.split(text, r"\."), one), ".")


def _syllables(stream: Column, at: int, count: Column, script: Column) -> Column:
    def one(i: Column) -> Column:
        b = _byte(stream, i + at)
        parts = {"latin": ("bdfgklmnprstvz", "aeiou"), "cyrillic": ("бвгдзклмнпрст", "аеиоу"), "greek": ("βγδκλμνπρστφ", "αειου")}
        pick = lambda s, x: F.substring(F.lit(s), F.pmod(x, F.lit(len(s))) + 1, F.lit(1))
        spelled = {k: F.concat(pick(c, b), pick(v, F.floor(b / 16).cast("int"))) for k, (c, v) in parts.items()}
        return F.when(script == "cyrillic", spelled["cyrillic"]).when(script == "greek", spelled["greek"]).otherwise(spelled["latin"])

    return F.array_join(F.transform(F.sequence(F.lit(1), count), one), "")


def _person(stream: Column, canon: Column, gender: Column, attempt: Column) -> Column:
    """One name in lower case, with an ending of the gender (f, m or none) in the script of the name."""
    script = F.when(canon.rlike(r"\p{IsCyrillic}"), "cyrillic").when(canon.rlike(r"\p{IsGreek}"), "greek").otherwise("latin")
    endings = {"cyrillic": ("на", "ан", "ов"), "greek": ("να", "νος", "ης"), "latin": ("na", "no", "er")}
    by_gender = lambda e: F.when(gender == "f", e[0]).when(gender == "m", e[1]).otherwise(e[2])
    ending = F.when(script == "cyrillic", by_gender(endings["cyrillic"])).when(script == "greek", by_gender(endings["greek"])).otherwise(by_gender(endings["latin"]))
    return F.concat(_syllables(stream, 0, F.lit(3) + attempt.cast("int"), script), ending)


def _luhn(number: Column) -> Column:
    """The number with its last digit made right."""
    head = F.substring(number, F.lit(1), F.length(number) - 1)
    digit = F.filter(F.sequence(F.lit(0), F.lit(9)), lambda d: F.call_function("luhn_check", F.concat(head, d.cast("string"))))
    return F.concat(head, digit[0].cast("string"))


def _remainder(number: Column) -> Column:
    """The IBAN remainder of a lower-case number, letters read as 10 to 35."""

    def step(r: Column, c: Column) -> Column:
        value = F.ascii(c) - F.when(c.rlike("[a-z]"), F.lit(87)).otherwise(F.lit(48))
        return F.pmod(r * F.when(value > 9, F.lit(100)).otherwise(F.lit(10)) + value, F.lit(97))

    turned = F.concat(F.substring(number, F.lit(5), F.length(number)), F.substring(number, F.lit(1), F.lit(4)))
    return F.aggregate(F.split(turned, ""), F.lit(0), step)


def _iban(canon: Column, spelled: Column) -> Column:
    """Country, check digits and account; the digits are made right where the original had right ones."""
    country, account = F.substring(canon, F.lit(1), F.lit(2)), F.substring(spelled, F.lit(5), F.length(spelled))
    digits = F.lpad((98 - _remainder(F.concat(country, F.lit("00"), account))).cast("string"), 2, "0")
    return F.when(_remainder(canon) == 1, F.concat(country, digits, account)).otherwise(spelled)


def candidate(key: str, kind: Column, canon: Column, gender: Column, attempt: Column) -> Column:
    """The surrogate's canonical form."""
    seed = F.concat_ws("\x1f", F.lit(key), kind, canon, attempt.cast("string"))
    stream = F.concat(F.sha2(seed, 256), F.sha2(F.concat(F.lit("+"), seed), 256))
    local, domain = F.split_part(canon, F.lit("@"), F.lit(1)), F.split_part(canon, F.lit("@"), F.lit(2))
    longer = F.when(attempt >= 3, F.concat(local, F.repeat(F.lit("x"), attempt.cast("int")))).otherwise(local)
    no = F.lit(False)
    mail = F.concat(_spelled(stream, longer, no), F.lit("@"), domain)
    kept = F.when(kind == "phone", F.greatest(F.length(canon) - 10, F.lit(0))).when(kind == "iban", F.lit(2)).otherwise(F.lit(0))
    spelled = F.concat(F.substring(canon, F.lit(1), kept), _spelled(stream, F.substring(canon, kept + 1, F.length(canon)), canon.rlike("^[0-9a-f]+$")))
    card = F.when(F.call_function("luhn_check", canon), _luhn(spelled)).otherwise(spelled)
    return F.when(kind == "email", mail).when(kind == "ip", _octets(stream, canon, attempt >= 3)).when(kind == "name", _person(stream, canon, gender, attempt)).when(kind == "card", card).when(kind == "iban", _iban(canon, spelled)).otherwise(spelled)


def _cased(name: Column, like: Column) -> Column:
    return F.when((F.length(like) > 1) & (F.upper(like) == like), F.upper(name)).otherwise(F.initcap(name))


def written(kind: Column, entity: Column, surrogate: Column) -> Column:
    """The surrogate in the format of the mention."""
    count = F.length(F.regexp_replace(entity, "[^0-9]", ""))
    spare = F.length(surrogate) - count  # digits of a country prefix that the mention leaves out

    def digit(c: Column, i: Column) -> Column:
        nth = F.length(F.regexp_replace(F.substring(entity, F.lit(1), i + 1), "[^0-9]", ""))
        return F.when(c.rlike("[0-9]"), F.substring(surrogate, nth + spare, F.lit(1))).otherwise(c)

    def letter(c: Column, i: Column) -> Column:
        nth = F.length(F.replace(F.substring(entity, F.lit(1), i + 1), F.lit(" "), F.lit("")))
        s = F.substring(surrogate, nth, F.lit(1))
        return F.when(c == " ", c).when(c.rlike(r"\p{Lu}"), F.upper(s)).otherwise(s)

    chars = F.split(entity, "")
    upper = F.when((kind == "email") & (F.upper(entity) == entity), F.upper(surrogate)).otherwise(surrogate)
    return (
        F.when(kind.isin("phone", "card", "ssn"), F.array_join(F.transform(chars, digit), ""))
        .when(kind.isin("iban", "secret"), F.array_join(F.transform(chars, letter), ""))
        .otherwise(upper)
    )


def surrogates(entities: DataFrame, key: str) -> DataFrame:
    """kind, canon, surrogate for distinct (kind, canon) with a gender, without collisions among them or with a real entity."""
    real = entities.select("kind", F.col("canon").alias("surrogate")).withColumn("real", F.lit(True))
    state = checkpointed(entities.withColumn("attempt", F.lit(0)))
    while True:
        named = state.withColumn("surrogate", candidate(key, F.col("kind"), F.col("canon"), F.col("gender"), F.col("attempt")))
        order = Window.partitionBy("kind", "surrogate").orderBy("attempt", "canon")
        judged = named.withColumn("nth", F.row_number().over(order)).join(real, ["kind", "surrogate"], "left")
        judged = checkpointed(judged.select("kind", "canon", "gender", "attempt", "surrogate", ((F.col("nth") > 1) | F.col("real").isNotNull()).alias("clash")))
        if judged.filter("clash").isEmpty():
            return judged.select("kind", "canon", "surrogate")
        state = judged.select("kind", "canon", "gender", (F.col("attempt") + F.col("clash").cast("int")).alias("attempt"))


def _pattern(text: Column) -> Column:
    """The entities of a text: the names that it gives with a title or a cue are looked for without one as well."""
    people = F.array_distinct(F.flatten(F.transform(F.regexp_extract_all(text, F.lit(f"{NAME}|{CUED}"), F.lit(0)), _names)))
    people = F.filter(people, lambda n: F.length(n) > 1)
    each = F.array_join(F.transform(people, lambda n: F.concat(F.lower(n), F.lit("|"), F.upper(n), F.lit("|"), F.initcap(n))), "|")
    one = F.concat(F.lit("(?<!\\p{L})(?:"), each, F.lit(")(?!\\p{L})"))
    # A name in lower case alone may be a word like another: it counts only as a capitalised or upper-case word.
    mention = F.concat(F.lit("(?=\\p{Lu})"), one, F.lit("(?: (?=\\p{Lu})"), one, F.lit(")*"))
    return F.when(F.size(people) > 0, F.concat(F.lit(f"{MAIL}|{NAME}|"), mention, F.lit("|" + ENTITY))).otherwise(F.lit(ENTITY))


def _gender(entity: Column) -> Column:
    title = lambda names: entity.rlike("^(?iu:" + "|".join(names) + r")\.? ")
    return F.when(title(FEMALE_TITLES), "f").when(title(MALE_TITLES), "m")


def replace_entities(docs: DataFrame, key: str, text_col: str = "text") -> DataFrame:
    """All columns, with the entities of the text replaced, and ``n_entities``."""
    text = F.col(text_col)
    some = F.coalesce(text.rlike(HINT) & text.rlike(ENTITY), F.lit(False))
    digest, pattern, table = (unused([*docs.columns, "n_entities"], n) for n in ("digest", "pattern", "surrogates"))
    ours = docs.filter(some).withColumn(digest, F.sha2(text.cast("binary"), 256)).withColumn(pattern, _pattern(text))
    matches = F.regexp_extract_all(text, F.col(pattern), F.lit(0))
    found = ours.select(F.col(digest).alias("digest"), F.explode(F.array_distinct(matches)).alias("entity")).withColumn("kind", kind_of(F.col("entity")))
    # A person's names are entities of their own; the first of two takes the gender of the title.
    names = F.when(F.col("kind") == "name", _names(F.col("entity"))).otherwise(F.array("entity"))
    parts = found.select("digest", "kind", F.col("entity").alias("whole"), F.size(names).alias("of"), F.posexplode(names).alias("nth", "entity"))
    parts = parts.withColumn("canon", canonical(F.col("kind"), F.col("entity")))
    parts = parts.withColumn("vote", F.when((F.col("kind") == "name") & (F.col("nth") == 0) & (F.col("of") > 1), _gender(F.col("whole"))))
    parts = checkpointed(parts.select("digest", "kind", "entity", "canon", "vote"))
    votes = F.count_if(F.col("vote") == "f") - F.count_if(F.col("vote") == "m")
    entities = parts.groupBy("kind", "canon").agg(votes.alias("v"), F.count("vote").alias("cast")).select("kind", "canon", F.when(F.col("cast") == 0, "").when(F.col("v") > 0, "f").otherwise("m").alias("gender"))
    known = surrogates(entities, key)
    form = F.when(F.col("kind") == "name", _cased(F.col("surrogate"), F.col("entity"))).otherwise(written(F.col("kind"), F.col("entity"), F.col("surrogate")))
    mapped = parts.select("digest", "kind", "entity", "canon").distinct().join(known, ["kind", "canon"]).select("digest", F.struct("entity", form.alias("to")).alias("pair"))
    maps = mapped.groupBy(F.col("digest").alias(digest)).agg(F.map_from_entries(F.collect_set("pair")).alias(table))
    lookup = lambda e: F.coalesce(F.element_at(F.col(table), e), e)
    person = lambda e: F.concat(F.regexp_extract(e, rf"^(?:{_TITLE}\.? )?", 0), F.array_join(F.transform(_names(e), lookup), " "))
    named = F.transform(matches, lambda e: F.when(F.map_contains_key(F.col(table), e), F.element_at(F.col(table), e)).otherwise(person(e)))
    woven = F.array_join(F.flatten(F.zip_with(F.split(text, F.col(pattern)), named, lambda c, e: F.array(c, F.coalesce(e, F.lit(""))))), "")
    touched = ours.join(maps, digest).withColumn("n_entities", F.size(matches).cast("long")).withColumn(text_col, woven)
    rest = docs.filter(~some).withColumn("n_entities", F.lit(0).cast("long"))
    return touched.select(*[F.col(f"`{c}`") for c in rest.columns]).unionByName(rest)
