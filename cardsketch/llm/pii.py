"""Personal data replaced by keyed, type-consistent surrogates, with built-in expressions only.

An entity's letters and digits are exchanged by a keyed Feistel permutation over the strings of its
shape: each place keeps its class (digit; vowel or consonant, lower or upper; accented; Cyrillic), so
format and script stay, one entity has one surrogate everywhere, and two entities never share one.
Given names of a list move along a keyed cycle of their gender and script; IP addresses within all
addresses, dates of birth within DAYS; a card or bank account whose check digits are right keeps
right ones.  Honorifics, country codes, final domains and words for streets stay.

A permutation of all strings of a shape may hit another entity of the corpus.  The collision check
finds such entities and exchanges them again under another tweak, those made of letters with some more
letters, until no surrogate is an original or shared.  Where a shape is so full that ATTEMPTS tweaks
don't do, all its entities take one permutation of the shape: still one to one, though a surrogate may then
be some other person's.  The check's table has a row for each distinct entity, and nothing of it comes to
the driver.  A name with and without honorific is one entity.

Forms: e-mail addresses, IPv4, IPv6, cards, bank accounts (IBAN), phones (+country code; 3-3-4; French pairs;
a German area code), numbers of the form 3-2-4, dates after a word for birth, street addresses (English, French,
German, Spanish), and names: a listed given name and a surname, one or two capitalised words after an honorific,
or two after words such as "my name is".  An account with wrong check digits is none.

Null text stays null; empty text has no entity.  Repeated rows get equal texts, ties don't occur.  Texts may be
of any length: all patterns are possessive where they repeat groups.  Only the id and text columns are read.
"""

from __future__ import annotations

from functools import reduce
from hashlib import sha256

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import discard, stored

KEY = "surrogates-1"
ROUNDS, ATTEMPTS, FULL = 6, 8, 1000
#: Most texts with exchanged entities whose ids are sent to all tasks, so that texts need not move.
SENT = 1 << 20
FIRST_DAY, DAYS = "1900-01-01", 270 * 271
# fixed values: given names by gender and script, honorifics, words for streets
FEMALE = ("Mary Patricia Jennifer Linda Elizabeth Barbara Susan Jessica Margaret Sandra Julia Laura Sophie Camille Ingrid Katharina Lucia Carmen Isabel Beatriz "
          "Jane Maria María Anna Emma Olivia Sarah Alice Emily Claire Chloé Amélie Élodie Greta Heike Sabine Pilar Dolores Mei Fatima Aisha Priya Yuki").split()
MALE = ("James Robert John Michael William David Richard Joseph Thomas Charles Daniel Matthew Anthony Pierre Jacques Hans Jürgen Carlos Javier Miguel "
        "Peter Paul George Edward Henry Andrew Jean François Étienne Klaus Wolfgang Stefan Pablo José Luis Wei Hiroshi Ahmed Mohammed Omar Raj Arjun Ivan").split()
FEMALE_CYRILLIC = "Анна Мария Елена Ольга Наталья Ирина Татьяна Светлана".split()
MALE_CYRILLIC = "Иван Пётр Сергей Алексей Дмитрий Николай Михаил Андрей".split()
HONORIFICS = "Mr Mrs Ms Miss Dr Herr Frau Señora Señor Monsieur Madame Mme".split()
STREETS = "Street St Avenue Ave Road Rd Lane Ln Drive Dr Boulevard Blvd rue avenue boulevard place chemin Calle Avenida Plaza de la del du des le".split()
STREET_ENDS = "straße strasse weg platz gasse".split()
CLASSES = (
    "0123456789", "aeiou", "bcdfghjklmnpqrstvwxyz", "AEIOU", "BCDFGHJKLMNPQRSTVWXYZ", "àáâãäåæèéêëìíîïòóôõöøùúûüý", "çñß", "ÀÁÂÃÄÅÆÈÉÊËÌÍÎÏÒÓÔÕÖØÙÚÛÜÝ", "ÇÑ",
    "аеёиоуыэюя", "бвгджзйклмнпрстфхцчшщ", "АЕЁИОУЫЭЮЯ", "БВГДЖЗЙКЛМНПРСТФХЦЧШЩ",
)
HEX_CLASSES = ("0123456789abcdef", "ABCDEF")
LISTS = (FEMALE, MALE, FEMALE_CYRILLIC, MALE_CYRILLIC)
_START, _END = r"(?<![\p{L}\p{N}])", r"(?![\p{L}\p{N}])"
_WORD = r"\p{Lu}(?:[\p{L}'-]{0,40}\p{L})"
_GIVEN = "|".join(dict.fromkeys(n for names in LISTS for n in names))
_ASKED = "[Mm]y name is|[Nn]ame:|[Ii]ch heiße|[Jj]e m'appelle|[Mm]e llamo|[Mm]eine? Name ist|[Ss]igned(?: by)?:?|[Mm]i nombre es"
NAME = rf"{_START}(?=\p{{Lu}})(?:(?:{'|'.join(HONORIFICS)})\.? {_WORD}(?: {_WORD})?|(?:{_GIVEN}) {_WORD}|(?<=(?:{_ASKED}) ){_WORD} {_WORD}){_END}"
_LABEL = "[A-Za-z0-9]++(?:-++[A-Za-z0-9]++)*+"
_BORN = r"(?:[Bb]orn|[Gg]eboren|[Nn]ée?|[Nn]acid[oa]|[Dd]ate of birth|DOB|geb\.|Geburtsdatum)(?: on| am| le| el)?:?"
FORMS = {
    "email": rf"(?<![\p{{L}}\p{{N}}._%+-])[\p{{L}}\p{{N}}._%+-]{{1,64}}+@{_LABEL}(?:\.{_LABEL}){{1,126}}+(?<=\.[A-Za-z]{{2,24}})(?![A-Za-z0-9])",
    "iban": r"(?<![\p{L}0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){3,7}+(?: ?[A-Z0-9]{1,3})?(?![\p{L}0-9])",
    "ipv6": r"(?<![\p{L}0-9:.])(?:(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}|(?:[0-9A-Fa-f]{1,4}:){1,6}(?::[0-9A-Fa-f]{1,4}){1,6})(?![\p{L}0-9:])",
    "ip": r"(?<![0-9.])(?:(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])\.){3}(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])(?![0-9]|\.[0-9])",
    "card": r"(?<![\p{L}0-9])[0-9]{4}(?: [0-9]{4} [0-9]{4} [0-9]{4}|-[0-9]{4}-[0-9]{4}-[0-9]{4}|[0-9]{11,12})(?![\p{L}0-9])",
    "phone": r"(?<![\p{L}0-9])(?:(?:\+[0-9]{1,3}[ .-]?)?(?:\([0-9]{3}\) ?|[0-9]{3}[ .-])[0-9]{3}[ .-][0-9]{4}|\+[1-9][0-9]{0,2}[ .-]?(?:\([0-9]{1,4}\)[ .-]?)?[0-9]{1,4}(?:[ .-]?[0-9]{2,8}){1,5}+|0[1-9](?:[ .][0-9]{2}){4}|0[1-9][0-9]{1,3}[ /][0-9]{5,8})(?![\p{L}0-9])",
    "ssn": r"(?<![\p{L}0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![\p{L}0-9-])",
    "birth": rf"(?<=(?<![\p{{L}}\p{{N}}]){_BORN} )(?:[0-9]{{4}}-[0-9]{{2}}-[0-9]{{2}}|[0-9]{{2}}\.[0-9]{{2}}\.[0-9]{{4}}|[0-9]{{2}}/[0-9]{{2}}/[0-9]{{4}})(?![\p{{L}}0-9])",
    "address": rf"(?<![\p{{L}}\p{{N}}])(?:[0-9]{{1,5}}[a-z]?,? (?:(?:rue|avenue|boulevard|place|chemin) (?:(?:de la|de|du|des|la|le) )?\p{{Lu}}\p{{L}}{{1,40}}|(?:\p{{Lu}}\p{{L}}{{1,40}} ){{1,3}}(?:Street|St|Avenue|Ave|Road|Rd|Lane|Ln|Drive|Dr|Boulevard|Blvd))|\p{{Lu}}\p{{L}}{{0,40}}(?:{'|'.join(STREET_ENDS)}) [0-9]{{1,4}}[a-z]?|(?:Calle|Avenida|Plaza) (?:(?:de la|del|de) )?\p{{Lu}}\p{{L}}{{1,40}},? [0-9]{{1,4}})(?![\p{{L}}0-9])",
    "name": NAME,
}
ANY = "|".join(f"(?:{p})" for p in FORMS.values())
#: Kinds whose surrogates may be longer than they are.
LETTERED = ("email", "address", "name")


def _bound(x: Column, f) -> Column:
    """f(x), with x worked out once."""
    return F.get(F.transform(F.array(x), f), F.lit(0))


def _alphabet(c: Column, classes: tuple[str, ...]) -> Column:
    return F.coalesce(*[F.when(F.instr(F.lit(a), c) > 0, F.lit(a)) for a in classes], F.lit(""))


def _instr(a: Column, c: Column) -> Column:
    return F.call_function("instr", a, c).cast("long") - 1


def _half(own: Column, other: Column, radix: Column, r: Column, tweak: Column) -> Column:
    """own, each place moved by a keyed hash of other."""
    h = F.sha2(F.concat_ws("|", tweak, r.cast("string"), F.array_join(other.cast("array<string>"), ",")), 256)
    return _bound(h, lambda d: F.transform(own, lambda v, i: F.pmod(v + F.conv(F.substr(d, (i % 32) * 2 + 1, F.lit(2)), 16, 10).cast("long"), F.get(radix, i))))


def _permuted(s: Column, tweak: Column, classes: tuple[str, ...] = CLASSES) -> Column:
    """s under the keyed permutation of its shape."""
    def on(chars: Column) -> Column:
        n = F.size(chars)
        m = F.floor(n / 2).cast("int")
        alpha = F.transform(chars, lambda c: _alphabet(c, classes))
        value = F.transform(chars, lambda c: F.greatest(F.lit(0).cast("long"), _instr(_alphabet(c, classes), c)))

        def go(t: Column) -> Column:
            rl, rr = F.slice(t["radix"], 1, m), F.slice(t["radix"], m + 1, n - m)
            first = F.struct(F.slice(t["value"], 1, m).alias("l"), F.slice(t["value"], m + 1, n - m).alias("r"))

            def step(x: Column, k: Column) -> Column:
                return F.when(k % 2 == 0, F.struct(_half(x["l"], x["r"], rl, k, tweak).alias("l"), x["r"].alias("r"))).otherwise(F.struct(x["l"].alias("l"), _half(x["r"], x["l"], rr, k, tweak).alias("r")))

            done = F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), first, step, lambda x: F.concat(x["l"], x["r"]))
            return _bound(done, lambda v: F.array_join(F.transform(chars, lambda c, i: F.when(F.get(t["alpha"], i) == "", c).otherwise(F.substr(F.get(t["alpha"], i), (F.get(v, i) + 1).cast("int"), F.lit(1)))), ""))

        return _bound(F.struct(alpha.alias("alpha"), value.alias("value"), F.transform(alpha, lambda a: F.greatest(F.lit(1), F.length(a)).cast("long")).alias("radix")), go)

    return F.when(F.length(s) == 0, s).otherwise(_bound(F.regexp_extract_all(s, F.lit("(?s)."), F.lit(0)), on))


def _drawn(tweak: Column, what: str, k: Column, x: Column) -> Column:
    """A number under 65,536 by a keyed hash."""
    return F.conv(F.substr(F.sha2(F.concat_ws("|", tweak, F.lit(what), k.cast("string"), x.cast("string")), 256), F.lit(1), F.lit(4)), 16, 10).cast("long")


def _ip(s: Column, tweak: Column) -> Column:
    part = lambda o, i: F.get(o, F.lit(i)).cast("long")

    def step(x: Column, k: Column) -> Column:
        return F.struct(x["b"].alias("a"), x["a"].bitwiseXOR(_drawn(tweak, "ip", k, x["b"])).alias("b"))

    halves = _bound(F.split(s, r"\."), lambda o: F.struct((part(o, 0) * 256 + part(o, 1)).alias("a"), (part(o, 2) * 256 + part(o, 3)).alias("b")))
    return F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), halves, step, lambda x: F.concat_ws(".", *[F.floor(v).cast("string") for v in (x["a"] / 256, x["a"] % 256, x["b"] / 256, x["b"] % 256)]))


def _birth(s: Column, tweak: Column) -> Column:
    """A date within DAYS from FIRST_DAY moves among them and keeps its format; days go before months
    where both are possible.  What is no such date is permuted as digits."""
    sep = F.when(s.rlike("^[0-9]{4}-"), "-").when(F.contains(s, F.lit(".")), ".").otherwise("/")
    us = (sep == "/") & (F.substr(s, F.lit(4), F.lit(2)).cast("int") > 12)
    form = F.when(sep == "-", "yyyy-MM-dd").when(sep == ".", "dd.MM.yyyy").when(us, "MM/dd/yyyy").otherwise("dd/MM/yyyy")
    parsed = F.coalesce(*[F.when(form == f, F.try_to_timestamp(s, F.lit(f))) for f in ("yyyy-MM-dd", "dd.MM.yyyy", "MM/dd/yyyy", "dd/MM/yyyy")])
    day = F.datediff(F.to_date(parsed), F.lit(FIRST_DAY).cast("date")).cast("long")

    def step(x: Column, k: Column) -> Column:
        return F.when(k % 2 == 0, F.struct(F.pmod(x["a"] + _drawn(tweak, "birth", k, x["b"]), F.lit(270)).alias("a"), x["b"].alias("b"))).otherwise(F.struct(x["a"].alias("a"), F.pmod(x["b"] + _drawn(tweak, "birth", k, x["a"]), F.lit(271)).alias("b")))

    def move(d: Column) -> Column:
        first = F.struct(F.floor(d / 271).alias("a"), F.pmod(d, F.lit(271)).alias("b"))
        new = F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), first, step, lambda x: F.date_add(F.lit(FIRST_DAY).cast("date"), (x["a"] * 271 + x["b"]).cast("int")))
        return _bound(new, lambda n: F.coalesce(*[F.when(form == f, F.date_format(n, f)) for f in ("yyyy-MM-dd", "dd.MM.yyyy", "MM/dd/yyyy", "dd/MM/yyyy")]))

    return _bound(day, lambda d: F.when(d.between(0, DAYS - 1), move(d)).otherwise(_permuted(s, tweak)))


def _luhn(digits: Column) -> Column:
    """What the digits and a check digit must add up to, modulo 10; the last digit is doubled."""
    n = F.length(digits)
    return F.aggregate(F.sequence(F.lit(1), n), F.lit(0).cast("long"), lambda a, i: a + _bound(F.substr(digits, i, F.lit(1)).cast("long"), lambda d: F.when((n - i) % 2 == 0, F.floor(d * 2 / 10) + d * 2 % 10).otherwise(d))) % 10


def _card(s: Column, tweak: Column) -> Column:
    """All digits but the last permuted; the last moves by as much as the check sum."""
    head, last = F.substr(s, F.lit(1), F.length(s) - 1), F.substr(s, F.length(s), F.lit(1)).cast("long")
    plain = lambda x: F.regexp_replace(x, r"[^0-9]", "")
    return _bound(_permuted(head, tweak), lambda h: F.concat(h, F.pmod(last + _luhn(plain(head)) - _luhn(plain(h)), F.lit(10)).cast("string")))


def _mod97(account: Column) -> Column:
    """The account, its first four letters last, letters as 10 to 35, modulo 97."""
    x = F.concat(F.substr(account, F.lit(5), F.length(account)), F.substr(account, F.lit(1), F.lit(4)))
    place = lambda c: _instr(F.lit("0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ"), c)
    return F.aggregate(F.sequence(F.lit(1), F.length(x)), F.lit(0).cast("long"), lambda a, i: _bound(place(F.substr(x, i, F.lit(1))), lambda v: (F.when(v > 9, a * 100).otherwise(a * 10) + v) % 97))


def _compact(e: Column) -> Column:
    return F.regexp_replace(e, " ", "")


def _iban(s: Column, tweak: Column) -> Column:
    """The country stays, the account is permuted, the check digits follow."""
    body = _permuted(F.substr(s, F.lit(5), F.length(s)), tweak)
    return _bound(body, lambda b: F.concat(F.substr(s, F.lit(1), F.lit(2)), F.lpad((98 - _mod97(F.concat(F.substr(s, F.lit(1), F.lit(2)), F.lit("00"), _compact(b)))).cast("string"), 2, "0"), b))


def cycle(names: list[str], key: str, attempt: int) -> dict[str, str]:
    """Each name's successor along a keyed cycle of all."""
    order = sorted(names, key=lambda n: sha256(f"{key}|{attempt}|{n}".encode()).hexdigest())
    return dict(zip(order, [*order[1:], order[0]]))


def _listed(w: Column, attempt: Column, key: str) -> Column:
    """The successor of a listed given name, else null; cycles are by attempt, modulo ATTEMPTS."""
    def of(names: list[str]) -> Column:
        new = F.array(*[F.array(*[F.lit(c[n]) for n in names]) for c in (cycle(names, key, a) for a in range(ATTEMPTS))])
        return _bound(F.array_position(F.array(*map(F.lit, names)), w), lambda p: F.when(p > 0, F.get(F.get(new, F.pmod(attempt, F.lit(ATTEMPTS))), (p - 1).cast("int"))))
    return F.when(w.rlike(rf"^(?:{_GIVEN})$"), F.coalesce(*map(of, LISTS)))


def _extra(w: Column, attempt: Column) -> Column:
    """w with two letters of its script more for each attempt from the third on."""
    n = F.when(attempt < FULL, F.greatest(F.lit(0), attempt - 1)).otherwise(F.lit(0))
    return F.concat(w, F.repeat(F.when(w.rlike(r"\p{IsCyrillic}$"), F.lit("на")).otherwise(F.lit("na")), n.cast("int")))


def _name(e: Column, tweak: Column, attempt: Column, key: str) -> Column:
    """Words permuted, the last with more letters at need; a listed first word moves within its list."""
    def of(words: Column) -> Column:
        last = F.size(words) - 1
        plain = lambda w, i: _permuted(F.when(i == last, _extra(w, attempt)).otherwise(w), tweak)
        return F.array_join(F.transform(words, lambda w, i: F.coalesce(F.when((i == 0) & (last > 0), _listed(w, attempt, key)), plain(w, i))), " ")
    return _bound(F.split(e, " "), of)


def _address(e: Column, tweak: Column, attempt: Column) -> Column:
    """Numbers and names permuted, words for streets kept; the longest word gets more letters at need."""
    ends = rf"(?:{'|'.join(STREET_ENDS)})$"

    def word(w: Column) -> Column:
        tail = F.regexp_extract(w, ends, 0)
        stem = F.substr(w, F.lit(1), F.length(w) - F.length(tail))
        return F.when(F.regexp_replace(w, ",$", "").isin(STREETS), w).otherwise(F.concat(_permuted(F.when(stem.rlike(r"^\p{Lu}"), _extra(stem, attempt)).otherwise(stem), tweak), tail))
    return F.array_join(F.transform(F.split(e, " "), word), " ")


def canonical(e: Column) -> Column:
    """The entity without honorific."""
    return F.regexp_replace(e, rf"^(?:{'|'.join(HONORIFICS)})\.? (?=\p{{Lu}})", "")


def kind_of(e: Column) -> Column:
    tests = [(F.contains(e, F.lit("@")), "email"), (e.rlike(rf"^(?:{FORMS['iban']})$"), "iban"), (e.rlike(rf"^(?:{FORMS['ipv6']})$"), "ipv6")]
    tests += [(e.rlike(rf"^(?:{FORMS[k]})$"), k) for k in ("ip", "card", "phone", "ssn")]
    tests += [(e.rlike(r"^(?:[0-9]{4}-[0-9]{2}-[0-9]{2}|[0-9]{2}[./][0-9]{2}[./][0-9]{4})$"), "birth"), (e.rlike("[0-9]"), "address")]
    kind = reduce(lambda x, t: F.when(t[0], F.lit(t[1])).otherwise(x), reversed(tests), F.lit("name"))
    return F.when((kind == "iban") & (_mod97(_compact(e)) != 1), F.lit("none")).otherwise(kind)


def surrogate(e: Column, attempt: Column, key: str = KEY) -> Column:
    """What stands for a canonical entity."""
    def of(kind: Column) -> Column:
        tweak = F.concat_ws("|", F.lit(key), kind, attempt.cast("string"))
        tail, head = F.regexp_extract(e, r"(?:\.example)?\.[A-Za-z]+$", 0), F.regexp_extract(e, r"^(?:\+[0-9]{1,3})?", 0)
        at = F.instr(e, "@")
        local, domain = F.substr(e, F.lit(1), at - 1), F.substr(e, at, F.length(e) - at + 1 - F.length(tail))
        return (
            F.when(kind == "email", F.concat(_permuted(F.concat(_extra(local, attempt), domain), tweak), tail))
            .when(kind == "ip", _ip(e, tweak)).when(kind == "card", _card(e, tweak)).when(kind == "iban", _iban(e, tweak))
            .when(kind == "ipv6", _permuted(e, tweak, HEX_CLASSES)).when(kind == "birth", _birth(e, tweak))
            .when(kind == "name", _name(e, tweak, attempt, key)).when(kind == "address", _address(e, tweak, attempt)).when(kind == "none", e)
            .otherwise(F.concat(head, _permuted(F.substr(e, F.length(head) + 1, F.length(e)), tweak)))
        )
    return _bound(kind_of(e), of)


def _entities(text: Column) -> Column:
    """The entities of a text in order.  Texts without digits and @ can only have names."""
    return F.when(text.rlike(r"[0-9@]"), F.regexp_extract_all(text, F.lit(ANY), F.lit(0))).otherwise(F.regexp_extract_all(text, F.lit(NAME), F.lit(0)))


def _shape(e: Column) -> Column:
    """Equal for entities of one kind whose letters and digits have equal classes, place by place."""
    marks = "0aA" + "".join(chr(0x2460 + i) for i in range(len(CLASSES)))
    own = "".join(CLASSES)
    to = "".join(marks[3 + k] * len(a) for k, a in enumerate(CLASSES))
    return F.concat_ws("|", kind_of(e), F.translate(e, own, to), F.when(e.rlike(rf"^(?:{_GIVEN}) "), F.regexp_extract(e, "^[^ ]+", 0)))


def clashes(docs: DataFrame, text_col: str = "text", key: str = KEY) -> DataFrame:
    """(entity, attempt, surrogate) of the canonical entities whose first surrogate clashes with another
    entity or surrogate of the corpus; attempt is the tweak under which it doesn't."""
    e = docs.select(F.explode(_entities(F.col(text_col).cast("string"))).alias("e")).select(canonical(F.col("e")).alias("entity")).distinct()
    e = e.where(kind_of(F.col("entity")) != "none")
    new = lambda x: x.select("entity", "attempt", surrogate(F.col("entity"), F.col("attempt"), key).alias("surrogate"))
    t, rounds = stored(new(e.withColumn("attempt", F.lit(0)))), 0
    while True:
        taken = t.where(F.col("attempt") < FULL).join(t.select(F.col("entity").alias("surrogate")), "surrogate", "left_semi")
        # of those that share a surrogate, entities of a full shape keep it first, then those of fewer attempts
        rank = F.struct((F.col("attempt") < FULL).alias("free"), "attempt", "entity")
        shared = t.groupBy("surrogate").agg(F.count("*").alias("n"), F.min(rank).alias("owner")).where("n > 1")
        bad = stored(taken.select("entity").union(t.join(shared, "surrogate").where(rank != F.col("owner")).select("entity")).distinct())
        if not bad.head(1):
            return t.where("attempt > 0")
        rounds += 1
        if rounds <= ATTEMPTS:
            moved = t.join(bad, "entity", "left_semi").withColumn("attempt", F.col("attempt") + 1)
        else:  # no tweak does: all entities of these shapes take one permutation of the shape
            full = t.join(bad, "entity", "left_semi").groupBy(_shape(F.col("entity")).alias("shape")).agg((F.greatest(F.max("attempt"), F.lit(FULL - 1)) + 1).alias("to"))
            moved = t.withColumn("shape", _shape(F.col("entity"))).join(full, "shape").select("entity", F.col("to").alias("attempt"))
        moved = stored(moved.select("entity", "attempt"))
        again = stored(t.join(moved, "entity", "left_anti").union(new(moved)))
        for x in (t, bad, moved):
            discard(x)
        t = again


def replace(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", key: str = KEY) -> DataFrame:
    """(id, text, n_entities, n_email, ... a column for each form): texts with surrogates."""
    moved = clashes(docs, text_col, key)
    x = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).withColumn("found", _entities(F.col("text")))
    again = lambda e: F.lit(0)
    if moved.head(1):
        x = x.withColumn("th", F.xxhash64("text"))
        hit = x.select("id", "th", F.explode(F.array_distinct(F.transform("found", canonical))).alias("entity")).join(moved.select("entity", "attempt"), "entity")
        hit = stored(hit.groupBy("id", "th").agg(F.map_from_entries(F.collect_set(F.struct("entity", "attempt"))).alias("moved")).select(F.col("id").alias("i"), F.col("th").alias("h"), "moved"))
        x = x.join(F.broadcast(hit) if hit.count() <= SENT else hit, F.col("id").eqNullSafe(F.col("i")) & (F.col("th") == F.col("h")), "left").drop("i", "h", "th")
        again = lambda e: F.coalesce(F.element_at("moved", e), F.lit(0))
    pattern = F.when(F.col("text").rlike(r"[0-9@]"), F.lit(ANY)).otherwise(F.lit(NAME))
    gaps = F.when(pattern == ANY, F.split("text", ANY, -1)).otherwise(F.split("text", NAME, -1))
    one = lambda e: _bound(canonical(e), lambda c: F.concat(F.substr(e, F.lit(1), F.length(e) - F.length(c)), surrogate(c, again(c), key)))
    text = F.array_join(F.zip_with(gaps, F.concat(F.transform("found", one), F.array(F.lit(""))), lambda a, b: F.concat(F.coalesce(a, F.lit("")), F.coalesce(b, F.lit("")))), "")
    x = x.withColumn("kinds", F.filter(F.transform("found", lambda e: kind_of(canonical(e))), lambda k: k != "none")).withColumn("out", F.when(F.size("found") > 0, text).otherwise(F.col("text")))
    is_kind = lambda n: lambda k: k == n
    size = lambda a: F.coalesce(F.size(a), F.lit(0))
    counts = [size(F.filter("kinds", is_kind(n))).alias(f"n_{n}") for n in FORMS]
    return x.select(F.col("id").alias(id_col), F.col("out").alias("text"), size("kinds").alias("n_entities"), *counts)
