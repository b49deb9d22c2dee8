"""Surrogates for personal data, in DataFrame functions only.

Mentions of electronic addresses, network addresses, phone, account and identity numbers, and names after a title are
found in the whole text, and in the same text further mentions of those names without a title. A mention is made of
units (the digits of a number, the local part and the domain of an address, the given name and the surname of a person).
Each distinct unit of the corpus gets a surrogate from a keyed hash that keeps its kind: as many digits, the country code
of a phone number by the numbering plan, the check digits of an account number as valid as they were, letters for letters,
the script of a name and the gender of its title. A mention is then written with its units' surrogates in its own format
and case, so one unit has one surrogate in whatever format it appears: a phone number with or without country code, spaces
or brackets, a network address in full or shortened.

A name after a title that tells no gender (Dr, Prof) takes the gender that other mentions of the given name tell, where they
agree. Names are only found through a title; of further mentions, words of three letters or more, written as with the title
or in capitals, are taken for the same person.

Collision checks: a candidate is accepted only if no other unit of its kind has it and no unit of the corpus equals it;
the others try again with the next attempt, until all are distinct.

Inputs: null texts stay null; texts without mentions, empty ones among them, stay as they are; texts of any length are read
whole; where patterns overlap, the mention that begins first is taken, then the first kind of the list; repeated rows get
equal results; an empty table gives none; extra columns, of whatever name, are not returned.
"""

from __future__ import annotations

import os

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cubedensity.llm.common import bind, content_key, durable, where_marked

#: setting of the session that holds the secret key
KEY_SETTING = "cubedensity.surrogates.key"
MOST_ROUNDS = 40

#: fixed values: titles, by the gender that they tell
TITLES = {
    "m": ["Mr", "Mister", "Sir", "Herr", "Hr", "Monsieur", "Señor", "Sr", "Don", "Господин", "Κύριος", "السيد", "श्री"],
    "f": ["Mrs", "Ms", "Miss", "Madam", "Lady", "Frau", "Fr", "Madame", "Mme", "Mademoiselle", "Mlle", "Señora", "Sra", "Señorita", "Srta", "Doña", "Госпожа", "Κυρία", "السيدة", "श्रीमती"],
    "n": ["Dr", "Prof", "Professor", "Docteur", "Доктор"],
}
_longest_first = lambda words: "|".join(sorted(words, key=lambda w: (-len(w), w)))
_TITLE = "(?:" + _longest_first(TITLES["m"] + TITLES["f"] + TITLES["n"]) + ")"
_LEAD = "(?:" + _TITLE + "\\.?[ \\u00A0])+"
_EDGE, _END = "(?<![\\p{L}\\p{N}])", "(?![\\p{L}\\p{N}])"
_CASELESS = "[\\p{IsArabic}\\p{IsDevanagari}]{2,}"
_CASED = "\\p{Lu}[\\p{L}'’-]+"
_HEX = "[0-9A-Fa-f]{1,4}"
#: fixed values: country codes of one and two digits; all others have three
COUNTRY = "1|7|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]"
#: the country code of numbers in the national format that the patterns know
HOME = "1"

#: fixed values: patterns of mentions, the first that fits decides the kind
PATTERNS = {
    "email": "(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\\.[A-Za-z0-9-]+)*\\.[A-Za-z]{2,}" + _END,
    "ip": "(?<![\\p{L}\\p{N}.])(?:(?:25[0-5]|2[0-4]\\d|1?\\d?\\d)\\.){3}(?:25[0-5]|2[0-4]\\d|1?\\d?\\d)(?![\\p{L}\\p{N}])(?!\\.\\d)",
    "ip6": "(?<![\\p{L}\\p{N}:.])(?=[0-9A-Fa-f:]*\\d)(?:(?:" + _HEX + ":){7}" + _HEX + "|(?:" + _HEX + ":){1,6}:(?:" + _HEX + "(?::" + _HEX + "){0,5})?)(?![\\p{L}\\p{N}:])",
    "iban": _EDGE + "[A-Z]{2}\\d{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?" + _END,
    "phone": "(?<![\\p{L}\\p{N}+])\\+\\d{1,3}[ .-]?(?:\\(\\d{1,4}\\)|\\d{1,4})(?:[ .-]?\\d{2,4}){2,4}" + _END
    + "|(?<![\\p{L}\\p{N}])\\(\\d{3}\\) ?\\d{3}[ .-]\\d{4}" + _END
    + "|(?<![\\p{L}\\p{N}.-])\\d{3}([ .-])\\d{3}\\1\\d{4}(?![\\p{L}\\p{N}])",
    "identity": "(?<![\\p{L}\\p{N}-])\\d{3}-\\d{2}-\\d{4}(?![\\p{L}\\p{N}-])",
    "account": _EDGE + "(?:\\d{4}[ -]){3}\\d{4}" + _END + "|" + _EDGE + "\\d{13,19}" + _END,
    "name": _EDGE + _LEAD + "(?:" + _CASED + "(?: " + _CASED + "){0,2}|" + _CASELESS + "(?: " + _CASELESS + ")?)",
}
#: the phone alternative uses its own group, numbered from the start of the whole expression
MENTION = "|".join(f"(?:{p})" for p in PATTERNS.values())

#: fixed values: syllables for names, by script
SYLLABLES = {
    "latin": "ba be bo da de do fa fe ga go ha he ja jo ka ko la le lo ma me mo na ne no pa pe ra re ro sa se so ta te to va ve wa ze".split(),
    "cyrillic": "ба бе бо да де до за ка ко ла ле ма ме ми на не ни па пе ра ре ро са се со та те то ва ви".split(),
    "greek": "βα γα δα δε θα κα κο λα λε λι μα με νι πα πε ρα ρε σα σε τα τε φα χα".split(),
    "arabic": "با بي دا دي را ري سا سي فا كا كي لا لي ما مي نا ني ها وا يا".split(),
    "devanagari": "का की गा जा ता ती दा दी ना नी पा पी बा मा मी रा री ला ली वा सा सी हा".split(),
}
#: fixed values: endings of given names and surnames, by script and gender
ENDINGS = {
    ("latin", "given", "m"): "rd", ("latin", "given", "f"): "lia", ("latin", "surname", "m"): "nder", ("latin", "surname", "f"): "nder",
    ("cyrillic", "given", "m"): "слав", ("cyrillic", "given", "f"): "лина", ("cyrillic", "surname", "m"): "нов", ("cyrillic", "surname", "f"): "нова",
    ("arabic", "given", "m"): "ر", ("arabic", "given", "f"): "رة", ("arabic", "surname", "m"): "ري", ("arabic", "surname", "f"): "ري",
    ("devanagari", "given", "m"): "श", ("devanagari", "given", "f"): "ता", ("devanagari", "surname", "m"): "वाल", ("devanagari", "surname", "f"): "वाल",
    ("greek", "given", "m"): "νος", ("greek", "given", "f"): "νη", ("greek", "surname", "m"): "κης", ("greek", "surname", "f"): "κη",
}

#: scripts whose surnames have one form for both genders
ONE_SURNAME = ("latin", "arabic", "devanagari")


def key_of(spark: SparkSession) -> str:
    """The secret key of the session's setting; where it is unset, a new one, so that surrogates hold for one run only."""
    return spark.conf.get(KEY_SETTING, None) or os.urandom(32).hex()


def mentions(text: Column, pattern: Column | None = None) -> Column:
    return F.regexp_extract_all(text, F.lit(MENTION) if pattern is None else pattern, F.lit(0))


def kind_of(mention: Column) -> Column:
    out = None
    for kind, p in PATTERNS.items():
        whole = mention.rlike(f"^(?:{p})$")
        out = F.when(whole, kind) if out is None else out.when(whole, kind)
    return out.otherwise("account")


def _digits(c: Column) -> Column:
    return F.regexp_replace(c, "\\D", "")


def _script(word: Column) -> Column:
    out = F.when(word.rlike("\\p{IsCyrillic}"), "cyrillic").when(word.rlike("\\p{IsGreek}"), "greek")
    return out.when(word.rlike("\\p{IsArabic}"), "arabic").when(word.rlike("\\p{IsDevanagari}"), "devanagari").otherwise("latin")


def _gender(mention: Column) -> Column:
    """The gender that the titles of a mention tell: m, f, or n where they tell none."""
    says = lambda g: mention.rlike("^(?:" + _TITLE + "\\.?[ \\u00A0])*(?:" + _longest_first(TITLES[g]) + ")\\.?[ \\u00A0]")
    return F.when(says("f"), "f").when(says("m"), "m").otherwise("n")


def _name_words(mention: Column) -> Column:
    return F.filter(F.split(F.regexp_replace(mention, "^" + _LEAD, ""), " "), lambda w: w != "")


def _country(digits: Column) -> Column:
    """The country code that the digits of an international number begin with."""
    return F.regexp_extract(digits, f"^(?:{COUNTRY}|\\d{{3}})", 0)


def _phone(mention: Column) -> Column:
    """Country code and national digits, whatever the format; a bracketed trunk zero is no digit of the number."""
    digits = _digits(F.replace(mention, F.lit("(0)"), F.lit("")))
    code = F.when(mention.startswith("+"), _country(digits)).otherwise(HOME)
    national = F.when(mention.startswith("+"), F.substring(digits, F.length(_country(digits)) + 1, F.lit(40))).otherwise(digits)
    return F.concat_ws("-", code, national)


def _groups(address: Column) -> Column:
    """The eight groups of a network address of the long kind, in lower case and without leading zeros."""
    cut = lambda part: F.filter(F.split(part, ":"), lambda g: g != "")
    left, right = cut(F.substring_index(address, "::", 1)), cut(F.substring_index(address, "::", -1))
    gap = F.array_repeat(F.lit("0"), F.greatest(F.lit(0), 8 - F.size(left) - F.size(right)))
    every = F.when(address.contains("::"), F.concat(left, gap, right)).otherwise(cut(address))
    return F.transform(every, lambda g: F.regexp_replace(F.lower(g), "^0+(?=.)", ""))


def units(kind: Column, mention: Column, hint: Column | None = None) -> Column:
    """The units of a mention, in the order in which it is written; a word that is known as a name has its unit as ``hint``."""
    unit = lambda k, n: F.struct(k.alias("kind"), n.alias("norm"))
    low = F.lower(mention)
    words, g = _name_words(mention), _gender(mention)
    # the sex of a surname is left out of its unit where the script does not tell it, so that it stays one unit
    told = lambda w, what: F.when(_script(w).isin(*ONE_SURNAME), "m").otherwise(F.when(g == "n", "m").otherwise(g)) if what == "surname" else g
    part = lambda w, what: unit(F.concat_ws("/", F.lit("name"), F.lit(what), _script(w), told(w, what)), F.lower(w))
    every = (
        F.when(kind == "email", F.array(unit(F.lit("local"), F.substring_index(low, "@", 1)), unit(F.lit("domain"), F.substring_index(low, "@", -1))))
        .when(kind == "name", F.transform(words, lambda w, i: F.when(i == F.size(words) - 1, part(w, "surname")).otherwise(part(w, "given"))))
        .when(kind == "phone", F.array(unit(F.lit("phone"), _phone(mention))))
        .when(kind == "ip", F.array(unit(F.lit("ip"), mention)))
        .when(kind == "ip6", F.array(unit(F.lit("ip6"), F.array_join(_groups(mention), ":"))))
        .when(kind == "iban", F.array(unit(F.lit("iban"), F.regexp_replace(mention, " ", ""))))
        .otherwise(F.array(unit(kind, _digits(mention))))
    )
    return every if hint is None else F.when(hint.isNotNull(), F.array(unit(hint, low))).otherwise(every)


def _stream(key: str, *parts: Column) -> Column:
    """256 hexadecimal digits of a keyed hash (nested, so that messages cannot be extended)."""
    message = F.sha2(F.concat_ws("\0", F.lit(key + ":inner"), *parts), 256)
    return F.concat(F.sha2(F.concat(F.lit(key + ":outer0"), message), 512), F.sha2(F.concat(F.lit(key + ":outer1"), message), 512))


def _byte(stream: Column, i: Column) -> Column:
    return F.conv(F.substring(stream, 1 + 2 * F.pmod(i, F.lit(128)), F.lit(2)), 16, 10).cast("int")


def _chars(norm: Column, stream: Column) -> Column:
    """Letters for letters, digits for digits, the rest as it is."""
    letter = lambda i: F.substring(F.lit("abcdefghijklmnopqrstuvwxyz"), 1 + F.pmod(_byte(stream, i), F.lit(26)), F.lit(1))
    digit = lambda i: F.substring(F.lit("0123456789"), 1 + F.pmod(_byte(stream, i), F.lit(10)), F.lit(1))
    each = F.transform(
        F.split(norm, ""),
        lambda c, i: F.when(c.rlike("^[a-z]$"), letter(i)).when(c.rlike("^[A-Z]$"), F.upper(letter(i))).when(c.rlike("^[0-9]$"), digit(i)).otherwise(c),
    )
    return F.array_join(each, "")


def check_sum(digits: Column) -> Column:
    """Sum of digits modulo 10 with every second one, from the right, doubled and folded."""
    chars = F.reverse(F.split(digits, ""))
    value = F.transform(chars, lambda c, i: F.when(i % 2 == 0, c.cast("int")).otherwise(F.pmod(c.cast("int") * 2, F.lit(10)) + F.floor(c.cast("int") / 5).cast("int")))
    return F.pmod(F.aggregate(value, F.lit(0), lambda a, x: a + x), F.lit(10))


def _account(norm: Column, made: Column) -> Column:
    """Keep the first digit, and a check sum as valid as it was."""
    body = F.concat(F.substring(norm, 1, 1), F.substring(made, F.lit(2), F.length(norm) - 2))
    last = F.pmod(check_sum(norm) - check_sum(F.concat(body, F.lit("0"))), F.lit(10))
    return F.concat(body, last.cast("string"))


def remainder(code: Column) -> Column:
    """Remainder by 97 of a code whose first four characters go to the end and whose letters count from ten."""
    turned = F.concat(F.substring(code, 5, 60), F.substring(code, 1, 4))
    digits = F.array_join(F.transform(F.split(turned, ""), lambda c: F.when(c.rlike("[A-Z]"), (F.ascii(c) - 55).cast("string")).otherwise(c)), "")
    return F.aggregate(F.split(digits, ""), F.lit(0), lambda a, c: F.pmod(a * 10 + F.coalesce(c.try_cast("int"), F.lit(0)), F.lit(97)))


def _iban(norm: Column, made: Column) -> Column:
    """Keep the country; check digits that are valid if they were, and leave the same remainder if not."""
    country, body = F.substring(norm, 1, 2), F.substring(made, 5, 60)
    open_ = remainder(F.concat(country, F.lit("00"), body))
    check = F.when(remainder(norm) == 1, 98 - open_).otherwise(F.pmod(remainder(norm) - open_, F.lit(97)))
    return F.concat(country, F.lpad(check.cast("string"), 2, "0"), body)


def _ip6(norm: Column, stream: Column, attempt: Column) -> Column:
    """Groups for groups: the first stays, and zeros stay in the first attempts, so that shortened forms stay so."""
    hexed = lambda i: F.lower(F.conv((1 + F.pmod(_byte(stream, 2 * i) * 256 + _byte(stream, 2 * i + 1), F.lit(65535))).cast("string"), 10, 16))
    each = F.transform(F.split(norm, ":"), lambda g, i: F.when((i == 0) | (g == "0") & (attempt < 3), g).otherwise(hexed(i)))
    return F.array_join(each, ":")


def _ip(norm: Column, stream: Column) -> Column:
    octet = lambda i: (1 + F.pmod(_byte(stream, F.lit(2 * i)) * 256 + _byte(stream, F.lit(2 * i + 1)), F.lit(254))).cast("string")
    head = (
        F.when(norm.startswith("10."), F.lit("10."))
        .when(norm.startswith("192.168."), F.lit("192.168."))
        .otherwise(F.concat((11 + F.pmod(_byte(stream, F.lit(9)), F.lit(110))).cast("string"), F.lit(".")))
    )
    rest = F.when(norm.startswith("192.168."), F.concat_ws(".", octet(1), octet(2))).otherwise(F.concat_ws(".", octet(1), octet(2), octet(3)))
    return F.concat(head, rest)


def _name(kind: Column, stream: Column, attempt: Column) -> Column:
    """Syllables of the script; more of them after some attempts, so that a free name is always found."""
    out = None
    endings = ENDINGS | {(script, "given", "n"): "" for script in SYLLABLES}
    for (script, what, gender), ending in endings.items():
        table = F.array(*map(F.lit, SYLLABLES[script]))
        count = F.lit(2 if what == "given" else 3) + F.floor(attempt / 3).cast("int")
        made = F.transform(F.sequence(F.lit(1), count), lambda i: F.get(table, F.pmod(_byte(stream, 2 * i) * 256 + _byte(stream, 2 * i + 1), F.lit(len(SYLLABLES[script])))))  # noqa: B023
        value = F.concat(F.array_join(made, ""), F.lit(ending))
        same = kind == f"name/{what}/{script}/{gender}"
        out = F.when(same, value) if out is None else out.when(same, value)
    return out.otherwise(F.lit(None))


def candidate(kind: Column, norm: Column, attempt: Column, key: str) -> Column:
    """The surrogate of a unit at an attempt."""

    def made(stream):
        chars = _chars(norm, stream)
        label = F.concat(F.array_join(F.transform(F.sequence(F.lit(0), 7 + F.floor(attempt / 3).cast("int")), lambda i: F.substring(F.lit("abcdefghijklmnopqrstuvwxyz"), 1 + F.pmod(_byte(stream, i), F.lit(26)), F.lit(1))), ""), F.lit(".example.org"))
        # a short local part has few forms of its own shape, so later attempts make it longer
        grown = F.concat(chars, F.when(attempt >= 3, F.concat(F.lit("."), F.substring(stream, F.lit(200), F.floor(attempt / 3).cast("int") + 2))).otherwise(""))
        return (
            F.when(kind == "local", grown)
            .when(kind == "domain", label)
            .when(kind == "ip", _ip(norm, stream))
            .when(kind == "ip6", _ip6(norm, stream, attempt))
            .when(kind == "account", _account(norm, chars))
            .when(kind == "phone", F.concat(F.substring_index(norm, "-", 1), F.lit("-"), _chars(F.substring_index(norm, "-", -1), stream)))
            .when(kind == "iban", _iban(norm, chars))
            .when(kind.startswith("name/"), _name(kind, stream, attempt))
            .otherwise(chars)
        )

    return bind(_stream(key, kind, norm, attempt.cast("string")), made)


def assign(found: DataFrame, key: str) -> DataFrame:
    """``(kind, norm)`` distinct -> ``(kind, norm, surrogate)``, all surrogates of a kind distinct and none a real unit.

    Kinds that are written alike (both sexes of a surname) share one family of names.
    """
    family = F.regexp_replace("kind", "/[mfn]$", "")
    taken = durable(found.select("kind", "norm", family.alias("family")))
    real = taken.select("family", F.col("norm").alias("surrogate")).distinct()
    done, left, attempt = None, taken, 0
    while True:
        tried = left.withColumn("surrogate", candidate(F.col("kind"), F.col("norm"), F.lit(attempt), key))
        first = tried.groupBy("family", "surrogate").agg(F.min(F.struct("kind", "norm")).alias("w"))
        free = first.join(real, ["family", "surrogate"], "left_anti")
        if done is not None:
            free = free.join(done.select("family", "surrogate"), ["family", "surrogate"], "left_anti")
        won = free.select("w.kind", "w.norm", "family", "surrogate")
        done = durable(won if done is None else done.union(won))
        left = durable(left.join(done.select("kind", "norm"), ["kind", "norm"], "left_anti"))
        if left.isEmpty():
            return done.select("kind", "norm", "surrogate")
        attempt += 1
        if attempt == MOST_ROUNDS:
            raise RuntimeError("no free surrogates: a kind has more units than forms")


def _refill(mention: Column, digits: Column, skip: Column) -> Column:
    """Digits into the places of a mention's digits, in its own format; the first ``skip`` digits stay."""
    start = F.struct(F.lit(0).alias("n"), F.lit("").alias("s"))

    def step(at, c):
        is_digit = c.rlike("^[0-9]$")
        new = F.when(is_digit & (at["n"] >= skip), F.substring(digits, at["n"] - skip + 1, F.lit(1))).otherwise(c)
        return F.struct((at["n"] + is_digit.cast("int")).alias("n"), F.concat(at["s"], new).alias("s"))

    return F.aggregate(F.split(mention, ""), start, step, lambda at: at["s"])


def _refill_all(mention: Column, chars: Column) -> Column:
    """All letters and digits of a spaced code."""
    start = F.struct(F.lit(1).alias("n"), F.lit("").alias("s"))

    def step(at, c):
        gap = c == " "
        new = F.when(gap, c).otherwise(F.substring(chars, at["n"], F.lit(1)))
        return F.struct((at["n"] + (~gap).cast("int")).alias("n"), F.concat(at["s"], new).alias("s"))

    return F.aggregate(F.split(mention, ""), start, step, lambda at: at["s"])


def _cased(word: Column, like: Column) -> Column:
    """A lower-case word in the case of another: all capitals, or capitals where the other has them."""
    each = F.transform(F.split(word, ""), lambda c, i: F.when(F.substring(like, i + 1, F.lit(1)).rlike("\\p{Lu}"), F.upper(c)).otherwise(c))
    return F.when((like == F.upper(like)) & (F.length(like) > 1), F.upper(word)).otherwise(F.array_join(each, ""))


def _shortened(mention: Column, made: Column) -> Column:
    """The eight groups of a surrogate, shortened where the mention is and the groups that it leaves out are zero."""
    groups = F.split(made, ":")
    count = lambda part: F.size(F.filter(F.split(part, ":"), lambda g: g != ""))
    left, right = count(F.substring_index(mention, "::", 1)), count(F.substring_index(mention, "::", -1))
    gap = F.slice(groups, left + 1, F.greatest(F.lit(0), 8 - left - right))
    short = F.concat(F.array_join(F.slice(groups, F.lit(1), left), ":"), F.lit("::"), F.array_join(F.slice(groups, 9 - right, right), ":"))
    out = F.when(mention.contains("::") & F.forall(gap, lambda g: g == "0"), short).otherwise(made)
    return F.when((mention == F.upper(mention)) & mention.rlike("[A-F]"), F.upper(out)).otherwise(out)


def render(kind: Column, mention: Column, made: Column) -> Column:
    """A mention written with the surrogates of its units, given in order."""
    one = F.get(made, F.lit(0))
    skip = F.when(mention.startswith("+"), F.length(F.substring_index(one, "-", 1))).otherwise(0)
    trunk = lambda c, a, b: F.replace(c, F.lit(a), F.lit(b))
    title, words = F.regexp_extract(mention, "^" + _LEAD, 0), _name_words(mention)
    return (
        F.when(kind == "email", F.when(mention == F.upper(mention), F.upper(F.concat_ws("@", one, F.get(made, F.lit(1))))).otherwise(F.concat_ws("@", one, F.get(made, F.lit(1)))))
        .when(kind == "ip", one)
        .when(kind == "ip6", _shortened(mention, one))
        .when(kind == "name", F.concat(title, F.array_join(F.zip_with(made, words, lambda m, w: _cased(m, F.coalesce(w, F.lit("")))), " ")))
        .when(kind == "iban", _refill_all(mention, one))
        .when(kind == "phone", trunk(_refill(trunk(mention, "(0)", "(\0)"), F.substring_index(one, "-", -1), skip), "(\0)", "(0)"))
        .otherwise(_refill(mention, one, F.lit(0)))
    )


def _with_gender(flat: DataFrame) -> DataFrame:
    """Given names whose title tells no gender get the one that all others of the name tell."""
    bare = F.regexp_replace("kind", "/[mfn]$", "")
    known = flat.filter("kind like 'name/given/%' and kind not like '%/n'").groupBy(bare.alias("bare"), "norm")
    known = known.agg(F.min("kind").alias("lo"), F.max("kind").alias("hi")).filter("lo = hi").select("bare", F.col("norm").alias("_norm"), F.col("lo").alias("told"))
    open_ = flat.filter("kind like 'name/given/%/n'")
    met = open_.join(known, (bare == F.col("bare")) & (F.col("norm") == F.col("_norm")), "left")
    return flat.filter("kind not like 'name/given/%/n'").union(met.select("mention", "hint", "at", F.coalesce("told", "kind").alias("kind"), "norm"))


def surrogates(found: DataFrame, key: str) -> DataFrame:
    """``found(mention, hint)`` distinct -> ``(mention, hint, kind, written)``; a hint is the unit kind of a known name."""
    hint = F.col("hint")
    kind = F.when(hint.isNotNull(), "name").otherwise(kind_of(F.col("mention")))
    parts = durable(found.select("mention", "hint", kind.alias("kind")).withColumn("units", units(F.col("kind"), F.col("mention"), hint)))
    flat = parts.select("mention", "hint", F.posexplode("units").alias("at", "u")).select("mention", "hint", "at", "u.kind", "u.norm")
    flat = durable(_with_gender(flat))
    given = assign(flat.select("kind", "norm").distinct(), key)
    made = flat.join(given, ["kind", "norm"]).groupBy(F.col("mention").alias("_m"), F.col("hint").alias("_k")).agg(F.array_sort(F.collect_list(F.struct("at", "surrogate"))).alias("m"))
    return parts.join(made, (F.col("mention") == F.col("_m")) & F.col("hint").eqNullSafe(F.col("_k"))).select(
        "mention", "hint", "kind", render(F.col("kind"), F.col("mention"), F.transform("m", lambda x: x["surrogate"])).alias("written")
    )


def _people(found: DataFrame) -> DataFrame:
    """``(_kid, _kh, people, pattern)`` of texts that name someone: the unit of each word of a name, and a pattern that
    finds those words too."""
    named = found.filter(F.col("mention").rlike("^" + _LEAD))
    words = _name_words(F.col("mention"))
    each = named.select("_kid", "_kh", F.explode(F.arrays_zip(words.alias("w"), units(F.lit("name"), F.col("mention")).alias("u"))).alias("x"))
    each = each.filter(F.length("x.w") >= 3).select("_kid", "_kh", F.struct(F.col("x.w").alias("w"), F.col("x.u.kind").alias("kind")).alias("x"))
    held = each.groupBy("_kid", "_kh").agg(F.array_sort(F.collect_set("x")).alias("people"))
    names = F.array_distinct(F.flatten(F.transform("people", lambda x: F.array(x["w"], F.upper(x["w"])))))
    longest = F.array_sort(names, lambda a, b: F.when(F.length(a) != F.length(b), F.length(b) - F.length(a)).when(a < b, -1).when(a > b, 1).otherwise(0))
    return held.withColumn("pattern", F.concat(F.lit(f"{MENTION}|{_EDGE}(?:"), F.array_join(longest, "|"), F.lit(f"){_END}")))


def _again(texts: DataFrame, people: DataFrame) -> DataFrame:
    """``(_kid, _kh, at, mention, hint)`` of texts that name someone, with the further mentions of the names."""
    who = people.select(F.col("_kid").alias("_pid"), F.col("_kh").alias("_ph"), "people", "pattern")
    held = texts.join(who, F.col("_kid").eqNullSafe(F.col("_pid")) & (F.col("_kh") == F.col("_ph")))
    each = held.select("_kid", "_kh", "people", F.posexplode(mentions(F.col("text"), F.col("pattern"))).alias("at", "mention"))
    known = F.filter("people", lambda x: F.lower(x["w"]) == F.lower("mention"))
    return each.select("_kid", "_kh", "at", "mention", F.get(known, F.lit(0))["kind"].alias("hint")).distinct()


def replace(docs: DataFrame, key: str) -> DataFrame:
    """``(doc_id, text, n_replaced, kinds)`` for every row of ``docs(doc_id, text)``."""
    keyed = docs.select("doc_id", "text", *content_key())
    here = durable(
        keyed.filter(F.col("text").rlike(MENTION)).select("_kid", "_kh", F.posexplode(mentions(F.col("text"))).alias("at", "mention")).distinct()
    )
    people = durable(_people(here))
    found = here.withColumn("hint", F.lit(None).cast("string"))
    if not people.isEmpty():
        who = people.select(F.col("_kid").alias("_pid"), F.col("_kh").alias("_ph"))
        rest = found.join(who, F.col("_kid").eqNullSafe(F.col("_pid")) & (F.col("_kh") == F.col("_ph")), "left_anti")
        found = durable(rest.union(_again(where_marked(keyed, people)[0], people)))
    table = durable(surrogates(found.select("mention", "hint").distinct(), key))
    made = table.select(F.col("mention").alias("_m"), F.col("hint").alias("_k"), "kind", "written")
    lists = (
        found.join(made, (F.col("mention") == F.col("_m")) & F.col("hint").eqNullSafe(F.col("_k")))
        .groupBy(F.col("_kid").alias("_did"), F.col("_kh").alias("_dh"))
        .agg(F.array_sort(F.collect_list(F.struct("at", "written", "kind"))).alias("found"))
    )
    who = people.select(F.col("_kid").alias("_pid"), F.col("_kh").alias("_ph"), "pattern")
    lists = durable(lists.join(who, F.col("_did").eqNullSafe(F.col("_pid")) & (F.col("_dh") == F.col("_ph")), "left").select("_did", "_dh", "found", "pattern"))
    held, free = where_marked(keyed, lists.select(F.col("_did").alias("_kid"), F.col("_dh").alias("_kh")))
    joined = held.join(lists, F.col("_kid").eqNullSafe(F.col("_did")) & (F.col("_kh") == F.col("_dh")), "left")
    gaps = F.when(F.col("pattern").isNull(), F.split("text", MENTION, -1)).otherwise(F.split(F.col("text"), F.col("pattern"), -1))
    woven = F.array_join(F.zip_with(gaps, "found", lambda g, f: F.concat(F.coalesce(g, F.lit("")), F.coalesce(f["written"], F.lit("")))), "")
    some = F.col("found").isNotNull()
    changed = joined.select(
        "doc_id",
        F.when(some, woven).otherwise(F.col("text")).alias("text"),
        F.when(some, F.size("found")).otherwise(0).cast("long").alias("n_replaced"),
        F.when(some, F.array_join(F.array_sort(F.array_distinct(F.transform("found", lambda f: f["kind"]))), ",")).otherwise("").alias("kinds"),
    )
    return changed.union(free.select("doc_id", "text", F.lit(0).cast("long"), F.lit("")))
