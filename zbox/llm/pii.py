"""Personal data replaced by surrogates, in DataFrame functions only.

Entities are found by one alternation of patterns and replaced by keyed surrogates of the same kind:
digits for digits, letters of the same script and case for letters, punctuation kept; an address of
the network keeps four octets, a card and an account number pass their check digits before and after, the
account number keeps its country, a date stays a date, a person keeps the honorific and gets a name of the
same gender, script and number of words. A surrogate depends on the secret key and the normalised entity
alone, so one entity has one surrogate everywhere. Names are keyed word by word: a family name has one
surrogate whoever bears it, with or without honorific. A person introduced by an honorific is found again
in the same text by the bare full name in any case, and by the family name as written or in capitals.

Collision check: over all documents, two entities (of names: two words) may not share a surrogate and a
surrogate may not be some other entity of the corpus. Those that break this are keyed again, and again,
until none does; only these exceptions are joined back to their documents. Initials and dates are moved all
by the same keyed step, which cannot bring two together."""

from __future__ import annotations

from hashlib import sha256

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import free_name, materialize

# Honorifics by gender (f, m, or n for neither).
HONORIFICS = {
    "f": ("Mrs", "Ms", "Miss", "Madam", "Frau", "Señora", "Sra", "Señorita", "Madame", "Mme", "Mlle", "Signora", "Госпожа"),
    "m": ("Mr", "Sir", "Herr", "Señor", "Monsieur", "Signor", "Господин"),
    "n": ("Dr", "Prof"),
}
# Syllables and endings of made-up names, per script.
SYLLABLES = {
    "latin": "ba be bo da de di fa fe ga ge ka ke la le li lo ma me mi na ne ni ra re ri ro sa se ta te va ve".split(),
    "cyrillic": "ба бе бо да де ди фа фе га ге ка ке ла ле ли ло ма ме ми на не ни ра ре ри ро са се та те ва ве".split(),
}
ENDINGS = {"latin": {"f": "na", "m": "ron", "n": "len"}, "cyrillic": {"f": "на", "m": "рон", "n": "лен"}}
#: Letters are shifted within their own alphabet.
ALPHABETS = ("0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "абвгдежзийклмнопрстуфхцчшщъыьэюя", "АБВГДЕЖЗИЙКЛМНОПРСТУФХЦЧШЩЪЫЬЭЮЯ", "αβγδεζηθικλμνξοπρστυφχψω", "ΑΒΓΔΕΖΗΘΙΚΛΜΝΞΟΠΡΣΤΥΦΧΨΩ")

# Words that a postal address ends with.
STREETS = ("Street", "St", "Road", "Rd", "Avenue", "Ave", "Lane", "Ln", "Drive", "Dr", "Boulevard", "Blvd", "Court", "Ct", "Square", "Sq", "Way", "Place", "Pl")

_TITLES = "|".join(sorted({x for h in HONORIFICS.values() for t in h for x in (t, t.upper())}, key=lambda t: (-len(t), t)))
_DATE = r"(?:\d{4}-\d{2}-\d{2}|\d{1,2}\.\d{1,2}\.\d{4}|\d{1,2}/\d{1,2}/\d{4}|\d{1,2}-\d{1,2}-\d{4})"
_LOCAL = r"[\p{L}\p{N}._%+'-]"
_OCTET = r"(?:25[0-5]|2[0-4]\d|1\d\d|\d{1,2})"
_KEYWORD = r"(?i:token|secret|password|passwd|api[_-]?key|access[_-]?key|private[_-]?key|auth)"
_PASSWORD = r"(?i:password|passwd|api[_-]?key|access[_-]?key|private[_-]?key)"
_MARK = r"[^\s\"'<>,;]"  # what a secret without quotes runs over
_SOME = r"(?=(?:[^\s\"'\p{L}0-9]*+[\p{L}0-9]){4})"  # four characters that a surrogate can move
#: A digit of an international number, with or without a mark before it; the last group has two digits or more.
_DIGITS = r"(?:(?:[ .-](?=\d{2}|\d[ .-]\d{2}))?\d)"
_INITIALS = r"\p{Lu}\.(?:-?\p{Lu}\.)*+"
_NAME = rf"(?:{_INITIALS}|\p{{Lu}}[\p{{L}}\p{{M}}’'-]*+)"
#: Pattern per kind, in order of precedence. Each is linear: it starts at a token's edge or a literal.
PATTERNS = {
    "email": rf"(?<!{_LOCAL}){_LOCAL}++@[\p{{L}}\p{{N}}-]{{1,63}}(?:\.[\p{{L}}\p{{N}}-]{{1,63}}){{1,8}}",
    "secret": rf"(?<![\p{{L}}\p{{N}}]){_KEYWORD}[\"']?[\x20\t]{{0,3}}(?:[=:][\x20\t]{{0,3}}(?:\"{_SOME}[^\"\s]{{4,}}+(?=\"|\z)|'{_SOME}[^'\s]{{4,}}+(?='|\z)|[\"']?{_SOME}{_MARK}{{12,}}+)|(?:=|(?<={_PASSWORD}[\"']?[\x20\t]{{0,3}}):|:(?=[\x20\t]{{0,3}}[\"']?\p{{L}}*+(?!\.*+(?:[\s\"'<>,;]|\z)){_MARK}))[\x20\t]{{0,3}}[\"']?{_SOME}{_MARK}{{4,}}+)",
    "key": r"(?<![0-9A-Za-z])(?:[0-9a-f]{32,128}|[0-9A-F]{32,128}|AKIA[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{36}|sk-[A-Za-z0-9]{20,64})(?![0-9A-Za-z])",
    "ip": rf"(?<![\d.])(?:{_OCTET}\.){{3}}{_OCTET}(?!\d|\.\d)",
    "phone": r"(?<![\d+])(?:\+[1-9]\d{0,3}[ .-]?\(\d{1,5}\)" + _DIGITS + r"{5,15}(?!\d)|\+[1-9]\d{0,3}(?=[ .-])" + _DIGITS + r"{6,16}(?!\d)|\+\d{1,3}[ .-]?\(\d{1,4}\)[ .-]?\d{2,4}[ .-]\d{2,4}(?:[ .-]\d{2,4})?|\+\d{1,3}(?:[ .-]\d{2,4}){2,4}|\+\d{9,14}|\(\d{3}\)[ .-]?\d{3}[ .-]\d{4}|\d{3}[.-]\d{3}[.-]\d{4})(?!\d)",
    "ssn": r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])",
    "card": r"(?<!\d)(?:\d{13,19}|\d{4}(?:[ -]\d{4}){3}|\d{4}[ -]\d{6}[ -]\d{5})(?!\d)",
    "birth_date": rf"(?<!\p{{L}})(?i:dob|date of birth|birth ?date|born(?: on)?|geboren am|geburtsdatum|n[ée]e? le|nacid[oa] el|nat[oa] il)[\x20\t]{{0,3}}[:=]?[\x20\t]{{0,3}}{_DATE}(?!\d)",
    "address": rf"(?<![\p{{L}}\p{{N}}])\d{{1,5}}[A-Za-z]?(?:\x20\p{{Lu}}[\p{{L}}'’-]{{1,30}}){{1,4}}\x20(?:{'|'.join(STREETS)})(?!\p{{L}})",
    "iban": r"(?<![\p{L}\p{N}])[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![\p{L}\p{N}])",
    "person": rf"(?<!\p{{L}})(?:{_TITLES})\.?\x20{_NAME}(?:\x20{_NAME})*+",
}
PATTERN = "|".join(f"(?:{p})" for p in PATTERNS.values())
#: What every entity holds: a quick test before the patterns.
HINT = rf"[0-9@]|{_KEYWORD}|(?<!\p{{L}})(?:{_TITLES})\.?\x20\p{{Lu}}"


def _kind(e: Column, names: Column | None = None) -> Column:
    """The kind of an entity: the first pattern that it matches whole; 'none' of a number whose check digits
    are wrong, which stays as it is. ``names``: the row's bare names, lower case."""
    kind = F.coalesce(*(F.when(F.rlike(e, F.lit(f"^(?:{p})$")), F.lit(k)) for k, p in PATTERNS.items()), F.lit("key"))
    kind = F.when((kind == "card") & ~_luhn_holds(e) | (kind == "iban") & ~_iban_holds(e), F.lit("none")).otherwise(kind)
    return kind if names is None else F.when(F.array_contains(names, F.lower(e)), F.lit("name")).otherwise(kind)


def _value(e: Column, kind: Column) -> Column:
    """What of an entity is replaced: of ``name = value`` the value."""
    value = F.when(kind == "secret", F.regexp_extract(e, r"[=:][\x20\t]{0,3}[\"']?(.*)$", 1))
    return value.when(kind == "birth_date", F.regexp_extract(e, rf"({_DATE})$", 1)).otherwise(e)


def _normal(e: Column, kind: Column) -> Column:
    """Spellings of one entity fall together: digits of numbers, lower case of the rest."""
    return F.when(kind.isin("phone", "card", "ssn"), F.regexp_replace(e, r"[^0-9]", "")).when(kind == "iban", F.replace(e, F.lit(" "), F.lit(""))).when(kind.isin("given", "family"), F.replace(F.lower(e), F.lit("."), F.lit(""))).when(kind == "ip", e).otherwise(F.lower(_value(e, kind)))


def _stream(key: str, kind: Column, normal: Column, attempt: Column) -> Column:
    seed = F.concat_ws("\x1f", F.lit(key), kind, attempt.cast("string"), normal)
    return F.concat(F.sha2(seed, 256), F.sha2(F.concat(seed, F.lit("\x1f2")), 512))


def _let(value: Column, body) -> Column:
    """``body(value)`` with the value worked out once: a column named inside a lambda would be made anew
    for every element."""
    return F.get(F.transform(F.array(value), lambda x: body(x)), F.lit(0))


def _draw(stream: Column, i: Column, below: int) -> Column:
    """The i-th number (from 0) below ``below``, out of four hex digits."""
    return F.pmod(F.conv(F.substr(stream, F.pmod(i * 4, F.lit(188)) + 1, F.lit(4)), 16, 10).cast("int"), F.lit(below))


def _spelled(text: Column, stream: Column) -> Column:
    """Each digit or letter moved within its alphabet by one place or more, so none stays itself."""
    at = lambda i: F.substr(text, i, F.lit(1))
    # a digit's number counts digits and letters only, so that spellings of one number agree
    index = lambda i: F.length(F.regexp_replace(F.substr(text, F.lit(1), i), r"[^\p{L}\p{N}]", ""))
    return F.array_join(F.transform(F.sequence(F.lit(1), F.greatest(F.length(text), F.lit(1))), lambda i: _moved(at(i), index(i), stream)), "")


def _moved(c: Column, i: Column, stream: Column) -> Column:
    moved = [
        F.when(F.instr(F.lit(a), c) > 0, F.substr(F.lit(a), F.pmod(F.instr(F.lit(a), c) + _draw(stream, i, len(a) - 1), F.lit(len(a))) + 1, F.lit(1)))
        for a in ALPHABETS
    ]
    other = F.when(F.rlike(c, F.lit(r"\p{L}")), F.substr(F.lit(ALPHABETS[1]), _draw(stream, i, 26) + 1, F.lit(1)))
    return F.coalesce(*moved, other, c)


def _each(text: Column, move) -> Column:
    """``move(character, its number from 1)`` for every character, in time linear in the length."""
    return F.array_join(F.transform(F.split(text, ""), lambda c, i: move(c, i + 1)), "")


def _hex_spelled(text: Column, stream: Column) -> Column:
    low, up = F.lit("0123456789abcdef"), F.lit("0123456789ABCDEF")
    move = lambda a, c, i: F.substr(a, F.pmod(F.instr(a, c) + _draw(stream, i, 15), F.lit(16)) + 1, F.lit(1))
    alphabet = F.when(F.rlike(text, F.lit("[A-F]")), up).otherwise(low)
    return _each(text, lambda c, i: move(alphabet, c, i))


def _check_digit(prefix: Column) -> Column:
    """Luhn's check digit of a number without its last digit."""

    def add(total: Column, i: Column) -> Column:
        d = F.substr(prefix, F.length(prefix) - i + 1, F.lit(1)).cast("int") * F.when(F.pmod(i, F.lit(2)) == 1, 2).otherwise(1)
        return total + F.when(d > 9, d - 9).otherwise(d)

    total = F.aggregate(F.sequence(F.lit(1), F.length(prefix)), F.lit(0), add)
    return F.pmod(10 - F.pmod(total, F.lit(10)), F.lit(10)).cast("string")


def _luhn_holds(e: Column) -> Column:
    digits = F.regexp_replace(e, "[^0-9]", "")
    head = F.substr(digits, F.lit(1), F.length(digits) - 1)
    return F.when(F.length(digits) < 2, False).otherwise(F.concat(head, _check_digit(head)) == digits)


def _card(new: Column) -> Column:
    new_head = F.regexp_replace(F.substr(new, F.lit(1), F.length(new) - 1), "[^0-9]", "")
    return F.concat(F.substr(new, F.lit(1), F.length(new) - 1), _check_digit(new_head))


def _mod97(text: Column) -> Column:
    """A number of digits and letters (A is 10), modulo 97."""

    def add(total: Column, c: Column) -> Column:
        digit = F.ascii(c) < 58
        return F.pmod(total * F.when(digit, 10).otherwise(100) + F.ascii(c) - F.when(digit, 48).otherwise(55), F.lit(97))

    return F.aggregate(F.split(text, ""), F.lit(0), add)


def _iban_holds(e: Column) -> Column:
    bare = F.replace(e, F.lit(" "), F.lit(""))
    return F.when(F.rlike(bare, F.lit("^[A-Z]{2}[0-9]{2}[0-9A-Z]{8,30}$")), _mod97(F.concat(F.substr(bare, F.lit(5)), F.substr(bare, F.lit(1), F.lit(4)))) == 1).otherwise(False)


def _iban(e: Column, new: Column) -> Column:
    """The same country, the rest moved, new check digits; spaces stay."""
    country = F.substr(e, F.lit(1), F.lit(2))
    check = 98 - _mod97(F.concat(F.replace(new, F.lit(" "), F.lit("")), country, F.lit("00")))
    return F.concat(country, F.lpad(check.cast("string"), 2, "0"), new)


def _date(value: Column, key: str) -> Column:
    """The date some keyed number of days later, in its own form; day first where both readings are dates."""
    days = int(sha256(f"{key}\x1fdays".encode()).hexdigest()[:8], 16) % 3000 + 400

    def moved(form: str, width: str) -> Column:
        day = F.try_to_timestamp(value, F.lit(form)).cast("date")
        return F.when(F.rlike(value, F.lit(width)) & day.isNotNull(), F.date_format(F.date_add(day, days), form))

    made = [moved("yyyy-MM-dd", r"^\d{4}-")]
    for mark in "./-":
        for form in (f"d{mark}M{mark}yyyy", f"M{mark}d{mark}yyyy"):
            padded = form.replace("d", "dd", 1).replace("M", "MM", 1)
            at = rf"^\d{{2}}\{mark}\d{{2}}\{mark}"
            made += [moved(padded, at), moved(form, rf"^\d+\{mark}")]
    return F.coalesce(*made, F.translate(value, "0123456789", "1234567890"))


def _email(e: Column, key: str, local: Column) -> Column:
    domain = F.substring_index(e, "@", -1)
    host = F.substr(F.translate(F.sha2(F.concat(F.lit(f"{key}\x1fdomain\x1f"), F.lower(domain)), 256), "0123456789", "ghijklmnop"), F.lit(1), F.lit(10))
    ends = F.element_at(F.array(F.lit("com"), F.lit("net"), F.lit("org")), F.pmod(F.length(domain), F.lit(3)).cast("int") + 1)
    new = F.concat(local, F.lit("@"), host, F.lit(".example."), ends)
    return F.when((F.upper(e) == e) & (F.lower(e) != e), F.upper(new)).otherwise(new)


def _title(e: Column) -> Column:
    return F.regexp_extract(e, r"^([^\x20.]+\.?)", 1)


def _gender(title: Column) -> Column:
    bare = F.upper(F.rtrim(F.replace(title, F.lit("."), F.lit(""))))
    of = lambda g: bare.isin(*(t.upper() for t in HONORIFICS[g]))
    return F.when(of("f"), "f").when(of("m"), "m").otherwise("n")


def _name_words(e: Column) -> Column:
    return F.split(F.substr(e, F.length(_title(e)) + 2), "\x20")


def _is_initials(w: Column) -> Column:
    return F.rlike(w, F.lit(rf"^(?:{_INITIALS}|\p{{Lu}})$"))


def _stem(w: Column, kind: Column, attempt: Column, key: str) -> Column:
    """The made-up name of a word, lower case: four syllables of its script, more with every attempt."""

    def drawn(stream: Column) -> Column:
        def of(script: str) -> Column:
            table = F.array(*(F.lit(x) for x in SYLLABLES[script]))
            return F.array_join(F.transform(F.sequence(F.lit(0), 3 + attempt), lambda i: F.element_at(table, _draw(stream, i, 32) + 1)), "")

        return F.when(F.rlike(w, F.lit(r"\p{IsCyrillic}")), of("cyrillic")).otherwise(of("latin"))

    return _let(_stream(key, kind, _normal(w, kind), attempt), drawn)


def _person(e: Column, key: str, attempts) -> Column:
    """``attempts(kind, word)`` gives the attempt of a name's word."""
    title, names = _title(e), _name_words(e)
    gender = _gender(title)
    step = int(sha256(f"{key}\x1finitials".encode()).hexdigest()[:8], 16) % 20 + 1

    def initial(c: Column, i: Column) -> Column:
        moved = [F.when(F.instr(F.lit(a), c) > 0, F.substr(F.lit(a), F.pmod(F.instr(F.lit(a), c) + (step - 1), F.lit(len(a))) + 1, F.lit(1))) for a in ALPHABETS]
        return F.coalesce(*moved, c)

    def name(w: Column, i: Column) -> Column:
        family = i == F.size(names) - 1
        kind = F.when(family, "family").otherwise("given")
        cyrillic = F.rlike(w, F.lit(r"\p{IsCyrillic}"))
        ending = F.coalesce(*(F.when(gender == g, F.when(cyrillic, ENDINGS["cyrillic"][g]).otherwise(ENDINGS["latin"][g])) for g in "fmn"))
        new = F.concat(F.initcap(_stem(w, kind, attempts(kind, w), key)), F.when(family, F.lit("")).otherwise(ending))
        bare = F.replace(w, F.lit("."), F.lit(""))
        new = F.when((F.upper(w) == w) & (F.length(bare) > 1) & ~F.contains(w, F.lit(".")), F.upper(new)).when(F.lower(w) == w, F.lower(new)).otherwise(new)
        # initials stay initials, but a last name is always a whole one: 26 letters cannot tell people apart
        return F.when(_is_initials(w) & ~family, _each(w, initial)).when(F.endswith(w, F.lit(".")), F.concat(new, F.lit("."))).otherwise(new)

    return F.concat(title, F.lit(" "), F.array_join(F.transform(names, name), " "))


def _address(e: Column, number: Column, stream: Column, key: str) -> Column:
    """Number and names moved, the kind of street kept."""
    word = lambda w, i: F.when(i == 0, number).when(w.isin(*STREETS), w).otherwise(F.initcap(_stem(F.concat(w, F.lit("\x1f"), stream), F.lit("street"), F.lit(0), key)))
    return F.array_join(F.transform(F.split(e, "\x20"), word), " ")


def surrogate(e: Column, kind: Column, attempts, key: str, whole: bool = True) -> Column:
    """The replacement of entity ``e``; ``attempts(kind, entity)`` gives the attempt. ``whole`` False: of
    persons there are name words alone."""
    attempt = attempts(kind, e)
    # what is moved letter by letter stands in the expression once
    part = (
        F.when(kind == "email", F.substring_index(e, "@", 1)).when(kind == "iban", F.substr(e, F.lit(5))).when(kind == "address", F.substring_index(e, " ", 1))
        .when(kind.isin("none", "ip", "birth_date", "person", "given", "family", "secret"), F.lit("")).otherwise(e)
    )
    spelled = lambda stream: _let(_spelled(part, stream), lambda new: _made(e, kind, attempts, key, stream, new, whole))
    return _let(_stream(key, kind, _normal(e, kind), attempt), spelled)


def _made(e: Column, kind: Column, attempts, key: str, stream: Column, new: Column, whole: bool) -> Column:
    value = _value(e, kind)
    octets = F.array_join(F.transform(F.split(e, r"\."), lambda o, i: F.pmod(o.cast("int") + 1 + _draw(stream, i, 255), F.lit(256)).cast("string")), ".")
    prefix = F.substr(e, F.lit(1), F.length(e) - F.length(value))
    hexed = F.rlike(value, F.lit("^(?:[0-9a-f]+|[0-9A-F]+)$"))
    return (
        F.when(kind == "none", e)
        .when(kind == "email", _email(e, key, new))
        .when(kind == "ip", octets)
        .when(kind == "card", _card(new))
        .when(kind == "iban", _iban(e, new))
        .when(kind == "birth_date", F.concat(prefix, _date(value, key)))
        .when(kind == "address", _address(e, new, stream, key))
        .when(kind == "person" if whole else kind.isin("given", "family"), _person(e, key, attempts) if whole else _stem(e, kind, attempts(kind, e), key))
        .when(kind.isin("secret", "key") & hexed, F.concat(prefix, _hex_spelled(value, stream)))
        .when(kind == "secret", F.concat(prefix, _each(value, lambda c, i: _moved(c, i, stream))))
        .otherwise(new)
    )


def find_entities(text: Column) -> Column:
    """The entities of a text, in order, repeats included; null and plain texts have none."""
    return F.when(F.rlike(text, F.lit(HINT)), F.regexp_extract_all(text, F.lit(PATTERN), F.lit(0))).otherwise(F.array().cast("array<string>"))


def introduced(entities: Column) -> Column:
    """Bare names of the persons among a text's entities: (name, title) of the full name, if it has two words
    or more, and of the family name; names in capitals too, longer ones first."""
    persons = F.filter(entities, lambda e: F.rlike(e, F.lit(f"^(?:{PATTERNS['person']})$")))

    def of(e: Column) -> Column:
        words = _name_words(e)
        family, full = F.element_at(words, -1), F.array_join(words, " ")
        one = lambda n: F.struct(n.alias("name"), _title(e).alias("title"))
        bare = F.rtrim(F.translate(family, ".", " "))
        names = F.array(one(full), one(bare), one(F.upper(bare)))
        return F.filter(names, lambda n: F.length(n["name"]) > 2)

    found = F.array_distinct(F.flatten(F.transform(persons, of)))
    return F.when(F.size(persons) == 0, F.array().cast("array<struct<name:string,title:string>>")).otherwise(F.reverse(F.array_sort(found, lambda a, b: F.length(a["name"]) - F.length(b["name"]))))


def _with_names(names: Column) -> Column:
    """The pattern of a text that introduces persons: the kinds first, then its names, full ones in any case."""
    quoted = F.transform(names, lambda n: F.concat(F.when(F.contains(n["name"], F.lit(" ")), "(?iu:").otherwise("(?:"), F.lit("\\Q"), F.replace(n["name"], F.lit("\\E"), F.lit("")), F.lit("\\E)")))
    return F.concat(F.lit(PATTERN + r"|(?<![\p{L}\p{N}])(?:"), F.array_join(quoted, "|"), F.lit(r")(?![\p{L}\p{N}])"))


def _name_parts(e: Column) -> Column:
    """(kind, word) of the whole words of a person's name."""
    names = _name_words(e)
    parts = F.transform(names, lambda w, i: F.struct(F.when(i == F.size(names) - 1, "family").otherwise("given").alias("kind"), w.alias("e")))
    return F.filter(parts, lambda x: (x["kind"] == "family") | ~_is_initials(x["e"]))


def _distinct_entities(docs: DataFrame, text: str) -> DataFrame:
    found = docs.select(F.explode_outer(find_entities(F.col(f"`{text}`"))).alias("e")).filter(F.col("e").isNotNull())
    found = found.groupBy("e").agg(F.lit(1)).select("e")
    found = found.withColumn("kind", _kind(F.col("e"))).filter(~F.col("kind").isin("none", "birth_date"))
    each = F.when(F.col("kind") == "person", _name_parts(F.col("e"))).otherwise(F.array(F.struct("kind", "e")))
    found = found.select(F.explode(each).alias("x")).select("x.kind", "x.e")
    return found.withColumn("normal", _normal(F.col("e"), F.col("kind"))).groupBy("kind", "normal").agg(F.min("e").alias("e"))


def resolve_collisions(entities: DataFrame, key: str, max_rounds: int = 20) -> DataFrame | None:
    """(kind, normal, attempt) of the entities that need another attempt than the first; None if no
    entity does."""
    tasks = 4 * entities.sparkSession.sparkContext.defaultParallelism  # few bytes, much work: not for one task
    state = materialize(entities.repartition(tasks, "normal").withColumn("attempt", F.lit(0)))
    moved = False
    for _ in range(max_rounds):
        # in one go: a column that the next one names many times would be made as many times
        made = _let(surrogate(F.col("e"), F.col("kind"), lambda kind, e: F.col("attempt"), key, whole=False), lambda s: _normal(s, F.col("kind")))
        made = materialize(state.withColumn("s", made))
        first = made.groupBy("kind", "s").agg(F.min("normal").alias("owner"), F.count("*").alias("k")).filter("k > 1").select("kind", "s", "owner")
        shared = made.join(first, ["kind", "s"]).filter(F.col("normal") != F.col("owner")).select("kind", "normal")
        real = made.join(state.select("kind", F.col("normal").alias("s")), ["kind", "s"], "left_semi").select("kind", "normal")
        again = materialize(shared.unionByName(real).distinct())
        if again.isEmpty():
            return state.filter("attempt > 0").select("kind", "normal", "attempt") if moved else None
        moved = True
        state = materialize(state.repartition(tasks, "normal").join(again.withColumn("again", F.lit(1)), ["kind", "normal"], "left").withColumn("attempt", F.col("attempt") + F.coalesce("again", F.lit(0))).drop("again"))
    raise RuntimeError(f"surrogates still collide after {max_rounds} attempts")


def replace(docs: DataFrame, key: str, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with ``text`` rewritten and n_entities and entities (map from kind to number) added;
    columns of these two names, in any case, are replaced.

    Null text stays null and has no entities; empty text stays empty; a text without entities is
    returned as it is; whole texts are read, of any length. Repeated rows are rewritten alike. Null ids are
    carried. An empty table gives an empty result."""
    exceptions = resolve_collisions(_distinct_entities(docs, text), key)
    docs = docs.select(*(F.col(f"`{c}`") for c in docs.columns if c.lower() not in ("n_entities", "entities")))
    columns, t = docs.columns, F.col(f"`{text}`")
    e, k, s, o, b = (free_name(docs, x) for x in ("_e", "_k", "_s", "_o", "_b"))
    df = docs.withColumn(e, find_entities(t)).withColumn(b, introduced(F.col(e)))
    again = F.size(b) > 0  # only these texts are searched a second time
    df = df.withColumn(e, F.when(again, F.regexp_extract_all(t, _with_names(F.col(b)), F.lit(0))).otherwise(F.col(e)))
    bare = F.transform(b, lambda n: F.lower(n["name"]))
    df = df.withColumn(f"{b}l", bare).withColumn(k, F.transform(e, lambda x: _kind(x, F.col(f"{b}l"))))
    if exceptions is not None:
        row = F.struct(F.col(f"`{id_col}`").alias("id"), F.xxhash64(t).alias("h"))
        each = F.flatten(F.zip_with(F.col(e), F.col(k), lambda x, kind: F.when(kind == "person", _name_parts(x)).otherwise(F.array(F.struct(kind.alias("kind"), x.alias("e"))))))
        of = df.filter(F.size(e) > 0).select(row.alias("row"), F.explode(each).alias("x"))
        of = of.select("row", "x.kind", _normal(F.col("x.e"), F.col("x.kind")).alias("normal")).distinct().join(exceptions, ["kind", "normal"])
        of = of.groupBy("row").agg(F.map_from_entries(F.collect_list(F.struct(F.concat_ws("\x1f", "kind", "normal"), "attempt"))).alias(o))
        df = df.withColumn(f"{o}r", row).join(of.withColumnRenamed("row", f"{o}w"), F.col(f"{o}r").eqNullSafe(F.col(f"{o}w")), "left").drop(f"{o}r", f"{o}w")
        attempts = lambda kind, x: F.coalesce(F.try_element_at(F.col(o), F.concat_ws("\x1f", kind, _normal(x, kind))), F.lit(0))
    else:
        attempts = lambda kind, x: F.lit(0)

    def titled(x: Column, kind: Column) -> Column:
        """A bare name becomes a person by the title that it was introduced with, which goes again later."""
        title = F.get(F.filter(b, lambda n: F.lower(n["name"]) == F.lower(x)), F.lit(0))["title"]
        title = F.when(kind == "name", F.concat(title, F.lit(" "))).otherwise(F.lit(""))
        return F.struct(F.concat(title, x).alias("e"), F.when(kind == "name", "person").otherwise(kind).alias("kind"), F.length(title).alias("drop"))

    df = df.withColumn(f"{s}t", F.zip_with(F.col(e), F.col(k), titled))
    new = F.transform(f"{s}t", lambda x: F.substr(surrogate(x["e"], x["kind"], attempts, key), x["drop"] + 1))
    df = df.withColumn(s, F.when(F.size(e) > 0, F.concat(new, F.array(F.lit("")))))
    between = F.when(again, F.split(t, _with_names(F.col(b)), -1)).otherwise(F.split(t, PATTERN, -1))
    rewritten = F.when(F.size(e) > 0, F.array_join(F.zip_with(between, F.col(s), lambda x, y: F.concat(x, y)), "")).otherwise(t)
    number = lambda name: F.size(F.filter(k, lambda y: (y == name) | (y == "name") if name == "person" else y == name))
    count = F.create_map(*(x for name in PATTERNS for x in (F.lit(name), number(name))))
    n = F.size(F.filter(k, lambda y: y != "none"))
    return df.select(*(rewritten.alias(c) if c == text else F.col(f"`{c}`") for c in columns), n.cast("long").alias("n_entities"), count.alias("entities"))
