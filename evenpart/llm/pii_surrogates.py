"""Operator 6: personal data replaced by keyed surrogates of the same type.

One alternation of patterns marks entities inside a text; the marked text is split, and every entity is rewritten in
place by array functions.  A surrogate is a function of a key, the entity's canonical form and an attempt number, so
the same person, address or number gets the same surrogate in every document and every spelling (coreference):
phone numbers keep their separators and country code, card numbers their length, first digit and a right check digit,
account numbers (IBAN) their country, grouping and right check digits, e-mail addresses the classes of the characters of
the local part, secrets their length and alphabet, tokens of known services their prefix, addresses the form of an IPv4
or IPv6 address (in ranges that are never routed).  A name is replaced word by word: the last word is a family name, the
words before it are given names of the gender of the title, all in the script of the original, so that "Mr A B", "Mr B"
and "Mrs C B" keep the family they share.  Names are found by a title or by a cue before them ("my name is"); names that
stand alone are not looked for.

Most texts hold none of it: ``TRIGGERS``, one cheap necessary condition of each pattern, tells which texts the
alternation has to run over at all.

Collision checks: the distinct canonical forms of the table get their surrogates; where two forms of a type meet in
one surrogate, or a surrogate equals a real entity of the table, all but the first take the next attempt, until every
form has a surrogate of its own.  Forms left with attempts above 0 are the only ones that need a join with the texts,
and that join is left out when there are none.

The key is the caller's: without it surrogates of short numbers could be tried out.

Defined results: null text stays null with no entity; the mark character U+FDD0 becomes a space where a text holds it; a
text of any length is rewritten whole; where two patterns fit at one place the earlier in ``PATTERNS`` wins; repeated rows
are rewritten alike; an empty table gives no rows; other columns pass through, but for those called entity_kinds or
n_entities, which the results of those names replace.
"""

from __future__ import annotations

import secrets

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evenpart.llm.columns import fresh
from evenpart.plans.scratch import cut
from evenpart.sources.tables import read_table

MARK = "﷐"
#: Titles, by the gender of the names that follow them, and titles and cues that tell none (fixed values).
TITLES = {"m": ("Mr", "Herr", "Monsieur", "Señor", "Sr", "г-н"), "f": ("Mrs", "Ms", "Miss", "Frau", "Madame", "Mme", "Señora", "Sra", "г-жа"), "u": ("Dr", "Prof", "Professor", "name is", "Name:", "signed by")}
_ALL_TITLES = "|".join(sorted((t for ts in TITLES.values() for t in ts), key=lambda t: -len(t)))
OCTET = r"(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])"
#: Type and pattern, in order of precedence.
PATTERNS = {
    "email": r"[A-Za-z0-9._%+\-]+@[A-Za-z0-9\-]+(?:\.[A-Za-z0-9\-]+)*\.[A-Za-z]{2,24}",
    "secret": r"(?<![A-Za-z0-9])[0-9a-f]{32,128}(?![A-Za-z0-9])",
    "token": r"(?<![A-Za-z0-9])(?:(?:AKIA|ASIA)[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{36}|xox[abprs]-[A-Za-z0-9\-]{10,72}|sk_(?:live|test)_[A-Za-z0-9]{16,64})(?![A-Za-z0-9])",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])",
    "ipv6": r"(?<![0-9A-Za-z:])(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}(?![0-9A-Za-z:])|(?<![0-9A-Za-z:])(?:[0-9A-Fa-f]{1,4}:){1,6}(?::[0-9A-Fa-f]{1,4}){1,6}(?![0-9A-Za-z:])",
    "phone": r"(?<![0-9A-Za-z])\+?[0-9]{1,3}[ .\-]?\([0-9]{2,4}\)[ .\-]?[0-9]{3,4}[ .\-]?[0-9]{3,4}(?![0-9A-Za-z])|(?<![0-9A-Za-z])\+[0-9]{1,3}(?:[ .\-][0-9]{2,4}){2,4}(?![0-9A-Za-z])",
    "ssn": r"(?<![0-9A-Za-z\-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9A-Za-z\-])",
    "card": r"(?<![0-9A-Za-z])[0-9]{4}(?:[ \-]?[0-9]{4}){3}(?![0-9A-Za-z])|(?<![0-9A-Za-z])[0-9]{13,19}(?![0-9A-Za-z])",
    "ipv4": rf"(?<![0-9A-Za-z.])(?:{OCTET}\.){{3}}{OCTET}(?![0-9A-Za-z]|\.[0-9])",
    "name": rf"(?<!\p{{L}})(?:{_ALL_TITLES})\.? \p{{Lu}}\p{{L}}+(?:[ \-]\p{{Lu}}\p{{L}}+){{0,2}}",
}
#: What every text must hold that a pattern fits (the regular expression of one alternation, and plain strings).
TRIGGERS = {
    "email": "[A-Za-z0-9]@[A-Za-z0-9]|[._%+\\-]@[A-Za-z0-9]|@-", "secret": "[0-9a-f]{32}", "token": "AKIA|ASIA|gh[pousr]_|xox[abprs]-|sk_(?:live|test)_", "iban": "[A-Z]{2}[0-9]{2}",
    "ipv6": "[0-9A-Fa-f]:[0-9A-Fa-f:]", "phone": "[0-9]{3}|\\+[0-9]", "ssn": "[0-9]{3}", "card": "[0-9]{3}", "ipv4": "[0-9]\\.[0-9]",
}
TRIGGER = "|".join(dict.fromkeys(TRIGGERS.values()))
KINDS = tuple(PATTERNS)
#: Syllables of made-up names by script (fixed values).
SYLLABLES = {
    "latin": "ba be bi bo da de di do fa fe fi fo ga ge gi go ka ke ki ko la le li lo ma me mi mo na ne ni no".split(),
    "cyrillic": "ба бе би бо да де ди до фа фе фи фо га ге ги го ка ке ки ко ла ле ли ло ма ме ми мо на не ни но".split(),
    "greek": "βα βε βι βο δα δε δι δο φα φε φι φο γα γε γι γο κα κε κι κο λα λε λι λο μα με μι μο να νε νι νο".split(),
}
#: Endings of given names (m, f, u) and of family names by script (fixed values).
ENDINGS = {"latin": ("n", "na", "l", "rt"), "cyrillic": ("н", "на", "л", "рт"), "greek": ("ς", "να", "λ", "ρτ")}


def suspect(text: Column) -> Column:
    """Whether ``text`` may hold an entity."""
    titled = [F.contains(text, F.lit(t)) for ts in TITLES.values() for t in ts]
    out = F.regexp_like(text, F.lit(TRIGGER))
    for t in titled:
        out = out | t
    return out


def segments(text: Column) -> Column:
    """Plain text and entities in turn: entities are at odd places."""
    whole = "|".join(f"(?:{p})" for p in PATTERNS.values())
    clean = F.replace(text, F.lit(MARK), F.lit(" "))
    return F.when(suspect(text), F.split(F.regexp_replace(clean, whole, f"{MARK}$0{MARK}"), MARK)).when(text.isNotNull(), F.array(clean))


def kind_of(entity: Column) -> Column:
    out = F.lit(None).cast("string")
    for kind, pattern in reversed(PATTERNS.items()):
        out = F.when(F.regexp_like(entity, F.lit(f"^(?:{pattern})$")), F.lit(kind)).otherwise(out)
    return out


def _script(name: Column) -> Column:
    return F.when(F.regexp_like(name, F.lit(r"\p{IsCyrillic}")), "cyrillic").when(F.regexp_like(name, F.lit(r"\p{IsGreek}")), "greek").otherwise("latin")


def canonical(kind: Column, entity: Column) -> Column:
    """What two spellings of one entity share."""
    digits = F.regexp_replace(entity, "[^0-9]", "")
    return F.when(kind.isin("phone", "card", "ssn"), digits).when(kind.isin("email", "ipv6"), F.lower(entity)).when(kind == "iban", F.replace(entity, F.lit(" "), F.lit(""))).otherwise(entity)


def _title(entity: Column) -> Column:
    return F.regexp_extract(entity, rf"^((?:{_ALL_TITLES})\.? )", 1)


def parts(kind: Column, entity: Column) -> Column:
    """array<struct<kind, canon, piece>>: an entity, or the words of a name; the canon of a given name is led by its gender."""
    title = F.regexp_extract(entity, rf"^({_ALL_TITLES})", 1)
    gender = F.when(title.isin(*TITLES["f"]), "f").when(title.isin(*TITLES["m"]), "m").otherwise("u")
    words = F.split(F.substring(entity, F.length(_title(entity)) + 1, F.length(entity)), "(?<=[ -])")
    bare = lambda w: F.regexp_replace(w, "[ -]$", "")
    last = lambda ws, i: i == F.size(ws) - 1
    named = _let(words, lambda ws: F.transform(ws, lambda w, i: F.struct(F.when(last(ws, i), "family").otherwise("given").alias("kind"), F.when(last(ws, i), bare(w)).otherwise(F.concat(gender, bare(w))).alias("canon"), w.alias("piece"))))
    return F.when(kind == "name", named).otherwise(F.array(F.struct(kind.alias("kind"), canonical(kind, entity).alias("canon"), entity.alias("piece"))))


def _stream(kind: Column, canon: Column, attempt: Column, key: str) -> Column:
    """128 hex digits that depend on the key."""
    seed = F.concat_ws("\x1f", F.lit(key), kind, canon, attempt.cast("string"))
    return F.concat(F.sha2(seed, 256), F.sha2(F.concat(F.lit("+"), seed), 256))


def _nibble(stream: Column, i: Column) -> Column:
    return F.conv(F.substring(stream, i + 1, F.lit(1)), 16, 10).cast("int")


def _byte(stream: Column, i: Column) -> Column:
    return F.conv(F.substring(stream, 2 * i + 1, F.lit(2)), 16, 10).cast("int")


def _chars(text: Column) -> Column:
    return F.filter(F.split(text, ""), lambda c: c != "")


def _check_digit(body: Column) -> Column:
    """The digit that makes ``body`` and itself pass the Luhn sum."""
    n = F.length(body)
    total = F.aggregate(
        F.transform(_chars(body), lambda c, i: F.when((n - i) % 2 == 1, F.when(c.cast("int") > 4, c.cast("int") * 2 - 9).otherwise(c.cast("int") * 2)).otherwise(c.cast("int"))),
        F.lit(0),
        lambda a, x: a + x,
    )
    return ((10 - total % 10) % 10).cast("string")


def surrogate(kind: Column, canon: Column, attempt: Column, key: str) -> Column:
    """The canonical form of the surrogate."""
    s = _stream(kind, canon, attempt, key)
    at = lambda i: F.pmod(i, F.lit(64)).cast("int")
    digit = lambda i: (_byte(s, at(i)) % 10).cast("string")
    letter = lambda i: F.substring(F.lit("abcdefghijklmnopqrstuvwxyz"), _byte(s, at(i)) % 26 + 1, F.lit(1))
    # the country code of a phone number and the first digit of a card stay
    phone = F.array_join(F.transform(_chars(canon), lambda c, i: F.when(i < F.greatest(F.length(canon) - 10, F.lit(1)), c).otherwise(digit(i))), "")
    body = F.array_join(F.transform(_chars(F.substring(canon, F.lit(1), F.length(canon) - 1)), lambda c, i: F.when(i == 0, c).otherwise(digit(i))), "")
    card = F.concat(body, _check_digit(body))
    ssn = F.array_join(F.transform(_chars(canon), lambda c, i: digit(i)), "")
    local, domain = F.substring_index(canon, "@", 1), F.substring_index(canon, "@", -1)
    mail = F.concat(
        F.array_join(F.transform(_chars(local), lambda c, i: F.when(F.regexp_like(c, F.lit("[0-9]")), digit(i)).when(F.regexp_like(c, F.lit("[a-z]")), letter(i)).otherwise(c)), ""),
        F.lit("@h"), F.substring(F.sha2(F.concat_ws("\x1f", F.lit(key), domain), 256), 1, 10), F.lit(".invalid"),
    )
    secret = F.substring(s, F.lit(1), F.length(canon))
    ip = F.concat_ws(".", (240 + _byte(s, F.lit(0)) % 15).cast("string"), _byte(s, F.lit(1)).cast("string"), _byte(s, F.lit(2)).cast("string"), _byte(s, F.lit(3)).cast("string"))
    upper = lambda i: F.substring(F.lit("ABCDEFGHIJKLMNOPQRSTUVWXYZ"), _byte(s, at(i)) % 26 + 1, F.lit(1))
    classed = lambda c, i: F.when(F.regexp_like(c, F.lit("[0-9]")), digit(i)).when(F.regexp_like(c, F.lit("[a-z]")), letter(i)).when(F.regexp_like(c, F.lit("[A-Z]")), upper(i)).otherwise(c)
    prefix = F.length(F.regexp_extract(canon, "^(AKIA|ASIA|gh[pousr]_|xox[abprs]-|sk_(?:live|test)_)", 1))
    token = F.concat(F.substring(canon, F.lit(1), prefix), F.array_join(F.transform(_chars(F.substring(canon, prefix + 1, F.length(canon))), classed), ""))
    account = F.array_join(F.transform(_chars(F.substring(canon, 5, 1000)), classed), "")
    iban = F.concat(F.substring(canon, 1, 2), _iban_check(F.substring(canon, 1, 2), account), account)
    ip6 = F.concat(F.lit("2001:db8:"), F.array_join(F.transform(F.sequence(F.lit(0), F.lit(5)), lambda i: F.substring(s, 4 * i + 1, F.lit(4))), ":"))
    female, male = F.substring(canon, 1, 1) == "f", F.substring(canon, 1, 1) == "m"
    script, name = _script(canon), None
    for kind_of_script, syllables in SYLLABLES.items():
        listed, (m, f, u, family) = F.array(*map(F.lit, syllables)), ENDINGS[kind_of_script]
        spelt = F.concat(*[F.get(listed, _byte(s, F.lit(i)) % len(syllables)) for i in range(4)], F.when(kind == "family", family).when(female, f).when(male, m).otherwise(u))
        made = F.initcap(spelt)
        name = made if name is None else F.when(script == kind_of_script, made).otherwise(name)
    out = name
    for k, v in {"email": mail, "secret": secret, "phone": phone, "ssn": ssn, "card": card, "ipv4": ip, "ipv6": ip6, "token": token, "iban": iban}.items():
        out = F.when(kind == k, v).otherwise(out)
    return out


def _iban_check(country: Column, account: Column) -> Column:
    """The two check digits: 98 less the number (letters count from 10) modulo 97."""
    value = lambda c: F.when(F.regexp_like(c, F.lit("[0-9]")), c.cast("int")).otherwise(F.ascii(c) - 55)
    rest = F.aggregate(_chars(F.concat(account, country, F.lit("00"))), F.lit(0), lambda a, c: (a * F.when(value(c) > 9, 100).otherwise(10) + value(c)) % 97)
    return F.lpad((98 - rest).cast("string"), 2, "0")


def rendered(kind: Column, piece: Column, made: Column) -> Column:
    """``made`` in the format of ``piece``."""
    chars = _chars(piece)
    taken = F.when(kind == "iban", "[^0-9A-Za-z]").otherwise("[^0-9]")
    before = lambda i: F.length(F.call_function("regexp_replace", F.substring(piece, F.lit(1), i), taken, F.lit("")))  # noqa: E731  characters of the canonical form to the left
    held = F.when(kind == "iban", "[0-9A-Za-z]").otherwise("[0-9]")
    spaced = F.array_join(F.transform(chars, lambda c, i: F.when(F.regexp_like(c, held), F.substring(made, before(i) + 1, F.lit(1))).otherwise(c)), "")
    return F.when(kind.isin("phone", "card", "ssn", "iban"), spaced).when(kind.isin("given", "family"), F.concat(made, F.regexp_extract(piece, "([ -])$", 1))).otherwise(made)


def _let(value: Column, body) -> Column:
    return F.transform(F.array(value), body)[0]


def entities_of(text: Column) -> Column:
    """array<struct<kind, canon, piece>> of one text, in order."""
    found = F.filter(segments(text), lambda _, i: i % 2 == 1)
    return F.flatten(F.transform(found, lambda e: _let(kind_of(e), lambda k: parts(k, e))))


def attempts(docs: DataFrame, key: str, text: str = "text", rounds: int = 64, maker=surrogate) -> DataFrame:
    """(kind, canon, attempt) for every distinct entity of the table; surrogates are then distinct and not real ones."""
    table = cut(docs.where(F.col(text).isNotNull()).select(F.explode(entities_of(F.col(text))).alias("e")).groupBy("e.kind", "e.canon").agg(F.lit(0).alias("attempt")))
    real = table.select("kind", F.col("canon").alias("made"), F.lit(True).alias("taken"))
    for _ in range(rounds):
        made = table.withColumn("made", maker(F.col("kind"), F.col("canon"), F.col("attempt"), key))
        order = Window.partitionBy("kind", "made").orderBy("attempt", "canon")
        judged = made.withColumn("place", F.row_number().over(order)).join(real, ["kind", "made"], "left")
        again = F.coalesce("taken", F.lit(False)) | (F.col("place") > 1)
        table = cut(judged.select("kind", "canon", (F.col("attempt") + again.cast("int")).alias("attempt"), again.alias("again")))
        moved = not table.where("again").isEmpty()
        table = table.drop("again")
        if not moved:
            return table
    raise RuntimeError(f"surrogates still collide after {rounds} rounds")


def replace_entities(docs: DataFrame, key: str, text: str = "text", doc_id: str = "doc_id", maker=surrogate) -> DataFrame:
    """``docs`` with ``text`` rewritten, and entity_kinds (comma-joined, in order of the text) and n_entities added."""
    i, late, done = fresh(docs, "_id", "_late", "_done")
    turned = attempts(docs, key, text, maker=maker).where("attempt > 0")
    out = docs
    if not turned.isEmpty():
        held = docs.select(F.col(doc_id).alias("id"), F.explode(entities_of(F.col(text))).alias("e")).select("id", "e.kind", "e.canon").distinct().join(turned, ["kind", "canon"])
        later = held.groupBy(F.col("id").alias(i)).agg(F.map_from_entries(F.collect_list(F.struct(F.concat_ws(":", "kind", "canon"), "attempt"))).alias(late))
        out = docs.join(later, docs[doc_id].eqNullSafe(later[i]), "left").drop(i)
    else:
        out = docs.withColumn(late, F.lit(None).cast("map<string,int>"))

    def rewrite(e: Column) -> Column:
        def piece(p: Column) -> Column:
            tries = F.coalesce(F.element_at(late, F.concat_ws(":", p["kind"], p["canon"])), F.lit(0))
            return rendered(p["kind"], p["piece"], maker(p["kind"], p["canon"], tries, key))

        return _let(kind_of(e), lambda k: F.struct(k.alias("kind"), F.concat(F.when(k == "name", _title(e)).otherwise(""), F.array_join(F.transform(parts(k, e), piece), "")).alias("text")))

    plain = lambda s: F.struct(F.lit(None).cast("string").alias("kind"), s.alias("text"))
    pieces = F.transform(segments(F.col(text)), lambda s, n: F.when(n % 2 == 1, rewrite(s)).otherwise(plain(s)))
    # written as one struct, so that the pieces are made once and both columns read from it
    joined = _let(pieces, lambda p: F.struct(F.array_join(F.transform(p, lambda x: x["text"]), "").alias("text"), F.filter(F.transform(p, lambda x: x["kind"]), lambda k: k.isNotNull()).alias("kinds")))
    kinds = F.col(done)["kinds"]
    made = {text: F.col(done)["text"], "entity_kinds": F.coalesce(F.array_join(kinds, ","), F.lit("")), "n_entities": F.greatest(F.coalesce(F.size(kinds), F.lit(0)), F.lit(0)).cast("long")}
    return out.withColumn(done, joined).withColumns(made).drop(done, late)


#: The setting that holds the caller's key; without it a run draws a key of its own, which nothing keeps.
KEY_SETTING = "spark.evenpart.surrogate.key"


def run_key(spark: SparkSession) -> str:
    return spark.conf.get(KEY_SETTING, None) or secrets.token_hex(32)


def op6_pii_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return replace_entities(read_table(spark, sf_dir, "documents", "doc_id", "text"), key=run_key(spark))
