"""Keyed surrogates for personal data, with DataFrame functions alone.

Detected entities are replaced by values of the same type, script, case and format; a key, without which nothing can be
traced back, decides which.

* Names.  A name is found behind a title (Mrs, Herr, господин and so on) or as a common given name with a surname.
  Each of its parts gets a name of its own, so "Mrs. Anna Smith", "Anna Smith" and "Mr. Smith" share the surrogates of
  "Anna" and "Smith" (coreference).  Latin, Cyrillic and Greek parts become as many letters, consonants and vowels in
  turn, drawn by a keyed hash, and end as feminine or masculine as the part itself does; parts in scripts without case
  become as many letters drawn from the same script.  Titles stay.
* E-mail addresses, telephone numbers, identity and card numbers, bank accounts, IP addresses and secrets become a
  keyed permutation of their own characters' places in their alphabets: digits stay digits, separators stay.  Passes
  over the even and the odd places mix everything, and one place is shifted by a step that is never zero.  Card numbers
  keep their first digit and whether their check digit holds, bank accounts their country and whether their check
  digits hold, addresses their last two labels, telephone numbers their country code.

Checks over the corpus keep surrogates apart: an attempt that equals a real value of the corpus, or the surrogate of
another value, is replaced by the next attempt's, until none is open.  Later attempts draw from a wider space (one
more letter or place each eighth attempt), so a crowded format can't run out.  Most values stand at their
first attempt; ``MAX_REPAIRS`` bounds the table of others that is put into the plan, and beyond it they are joined.

All patterns are linear: a run of letters is entered at its first character only, and repeats are possessive.  Entities have the lengths their formats allow: 64 characters in front of an @, 63
a label, 128 hexadecimal digits in a secret.

Defined results: null texts stay null with no entities; texts without entities stay as they are; rows are judged alone,
so ids may repeat or be null; all other columns stay, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .spool import kept

MAX_REPAIRS = 2000
MAX_ATTEMPTS = 400
MARK = "\u0001"

#: Alphabets whose letters may stand for each other.
ALPHABETS = ["0123456789", "aeiou", "bcdfghjklmnpqrstvwxyz", "áéíóúàèìòùâêîôûäëïöüãõåæøœ", "çñšžčđłśźńć", "аеёиоуыэюя", "бвгджзйклмнпрстфхцчшщ", "αεηιουω", "βγδζθκλμνξπρστφχψ"]
HEX = "0123456789abcdef"
#: Consonants, vowels, and last letters of feminine and of masculine forms, by script.
LETTERS = {
    "latin": ("bdfghjklmnprstvwz", "aeiou", "aei", "nrsldokmt"),
    "cyrillic": ("бвгджзклмнпрстфхч", "аеиоу", "ая", "вннрйкмл"),
    "greek": ("βγδζθκλμνπρστφχ", "αειο", "αη", "ςνρ"),
}
#: First and last code point of letters that may stand for each other, by script without case.
RANGES = [
    (0x0561, 0x0586), (0x05D0, 0x05EA), (0x0627, 0x063A), (0x0641, 0x064A), (0x0915, 0x0939), (0x0995, 0x09A8), (0x0E01, 0x0E2E), (0x10D0, 0x10F0), (0x1200, 0x1246),
    (0x3042, 0x3093), (0x30A2, 0x30F3), (0x4E00, 0x9FA5), (0xAC00, 0xD7A3),
]
#: Common given names, by which a name without a title is found.
FEMALE = "Alexandra Alice Amelia Ana Andrea Anna Anne Antonia Barbara Carla Carmen Caroline Catherine Charlotte Christina Claire Claudia Diana Elena Elisabeth Elizabeth Emily Emma Eva Francesca Gabriela Hannah Helen Irina Isabel Jane Jennifer Jessica Julia Karen Karin Katharina Kate Laura Linda Lisa Lucy Margaret Maria Marie Martha Mary Monika Natalia Nicole Olga Olivia Patricia Paula Rachel Rebecca Rosa Ruth Sabine Sandra Sarah Sofia Sophie Stefanie Susan Susanne Svetlana Teresa Ursula Valentina Victoria Анна Елена Ирина Мария Наталья Ольга Светлана Татьяна Елени Μαρία Ελένη Κατερίνα".split()
MALE = "Adam Alexander Andreas Andrew Anthony Antonio Benjamin Bernd Bruno Carlos Charles Christian Christopher Daniel David Diego Dmitri Edward Emil Eric Fernando Francisco Frank Frederik George Georg Hans Heinrich Henry Ivan Jack Jacques James Javier Jean Johann John Jonas Jorge Joseph José Juan Karl Klaus Lars Louis Luis Lukas Manuel Marco Mark Martin Matthew Max Michael Miguel Nicolas Oliver Pablo Patrick Paul Pedro Peter Philip Pierre Rafael Richard Robert Sebastian Sergei Simon Stefan Stephen Thomas Tobias Vladimir Walter William Wolfgang Александр Алексей Андрей Дмитрий Иван Михаил Николай Сергей Γιώργος Νίκος Δημήτρης".split()
TITLES = "Mr Mrs Ms Miss Mx Dr Prof Sir Madam Herr Frau Monsieur Madame Mademoiselle Mme Mlle Señor Señora Señorita Sr Sra Srta Господин господин Госпожа госпожа Κύριος Κυρία".split()

#: Patterns of the entity types.
_OCTET = r"(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)"
_H = "[0-9A-Fa-f]"
_PART = r"(?:\p{Lu}[\p{L}\p{M}]*+(?:['’-]\p{L}[\p{L}\p{M}]*+){0,3}+|[\p{IsHan}\p{IsHiragana}\p{IsKatakana}\p{IsHangul}]{1,4}|\p{Lo}[\p{Lo}\p{M}]*+)"
_TITLE = rf"(?:{'|'.join(TITLES)})(?![\p{{L}}\p{{M}}])"
WORD_PATTERNS = {  # begin where no letter or digit stands before
    "email": r"(?<![._%+-])[\p{L}\p{N}._%+-]{1,64}+@[A-Za-z0-9-]{1,63}+(?:\.[A-Za-z0-9-]{1,63}+){0,20}(?<=\.[A-Za-z]{2,24})",
    "iban": r"[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![\p{L}\p{N}])",
    "secret": r"(?:AKIA[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{36}|sk-[A-Za-z0-9]{20,200}+|[0-9a-fA-F]{32,128}+)(?![\p{L}\p{N}_])",
    "ipv6": rf"(?:(?:{_H}{{1,4}}:){{7}}{_H}{{1,4}}|{_H}{{3,4}}(?::{_H}{{1,4}}){{0,5}}::(?:{_H}{{1,4}}(?::{_H}{{1,4}}){{0,5}})?)(?![\p{{L}}\p{{N}}:])",
    "person": rf"(?:(?:{'|'.join(TITLES)})\.? {_PART}(?: (?!{_TITLE}){_PART}){{0,2}}+|(?:{'|'.join(FEMALE + MALE)})(?: (?!{_TITLE}){_PART}){{1,2}}+)",
}
NUMBER_PATTERNS = {
    "phone": r"\+\d{1,3}[ .-]?(?:\(\d{1,4}\)|\d{2,4})(?:[ .-]?\d{2,4}){2,3}(?!\d)|(?<![\d.-])(?:\(\d{3}\) ?|\d{3}[ .-])\d{3}[ .-]\d{4}(?![\d-])",
    "ip": rf"(?<![\d.])(?:{_OCTET}\.){{3}}{_OCTET}(?![\d]|\.\d)",
    "ssn": r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])",
    "card": r"(?<![\d-])(?:\d{4}[ -]\d{4}[ -]\d{4}[ -]\d{4}|\d{13,19}+)(?![\d-])",
}
TYPES = [*WORD_PATTERNS, *NUMBER_PATTERNS]
ANY = rf"(?:(?<![\p{{L}}\p{{M}}\p{{N}}])(?:{'|'.join(WORD_PATTERNS.values())})|(?=[0-9+(])(?:{'|'.join(NUMBER_PATTERNS.values())}))"
_RUN = r"[\p{L}\p{M}]+"


def _let(value: Column, body) -> Column:
    """The body of a value that is computed once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def kind_of(e: Column) -> Column:
    return (
        F.when(e.contains("@"), "email")
        .when(e.rlike(r"^\+|^\(?[0-9]{3}\)?[ .-]?[0-9]{3}[ .-][0-9]{4}$"), "phone")
        .when(e.rlike(r"^[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+$"), "ip")
        .when(e.rlike(r"^[0-9]{3}-[0-9]{2}-[0-9]{4}$"), "ssn")
        .when(e.rlike(r"^[0-9 -]{13,23}$"), "card")
        .when(e.rlike(r"(?i)^[0-9a-f:]+$") & e.contains(":"), "ipv6")
        .when(e.rlike(r"^(?i:AKIA[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{36}|sk-[A-Za-z0-9]{20,200}|[0-9a-f]{32,128})$"), "secret")
        .when(e.rlike(r"(?i)^[a-z]{2}[0-9]{2}[a-z0-9 ]{12,}$"), "iban")
        .otherwise("person")
    )


# names


def name_parts(e: Column) -> Column:
    """The runs of letters of a person's name, without the title."""
    bare = F.regexp_replace(e, rf"^(?:{'|'.join(TITLES)})\.? ", "")
    return F.regexp_extract_all(bare, F.lit(_RUN), F.lit(0))


def _pick(values: list[str], draw: Column) -> Column:
    return F.element_at(F.array(*map(F.lit, values)), (F.pmod(draw, F.lit(len(values))) + 1).cast("int"))


def _letter(code: Column) -> Column:
    return F.decode(F.unhex(F.lpad(F.hex(code), 4, "0")), "UTF-16BE")


def _cased_like(name: Column, part: Column) -> Column:
    first = F.substring(part, 1, 1)
    shouted = (F.upper(part) == part) & (F.lower(part) != part) & (F.length(part) > 1)
    big = (F.upper(first) == first) & (F.lower(first) != first)
    return _let(name, lambda n: F.when(shouted, F.upper(n)).when(big, F.concat(F.upper(F.substring(n, 1, 1)), F.substring(n, F.lit(2), F.length(n)))).otherwise(n))


def name_surrogate(part: Column, key: str, attempt: Column | int = 0) -> Column:
    """The surrogate of a part of a name, in the part's case; the part's lower-case form alone decides it."""
    tried = F.lit(attempt) if isinstance(attempt, int) else attempt
    low = F.lower(part)
    female = low.isin([n.lower() for n in FEMALE]) | (low.rlike("[aàáâãåаяαηή]$") & ~low.isin([n.lower() for n in MALE]))
    wider = F.floor(tried / 8).cast("int")

    def drawn(h: Column) -> Column:
        def draw(*k) -> Column:
            return F.xxhash64(h, *(x if isinstance(x, Column) else F.lit(x) for x in k))

        def spoken(script: str) -> Column:
            consonants, vowels, fem, masc = ([*x] for x in LETTERS[script])
            inner = F.length(low) + wider - 1
            lead = F.pmod(draw("lead"), F.lit(2))
            letter = lambda i: F.when(F.pmod(i + lead, F.lit(2)) == 0, _pick(consonants, draw(i, 1))).otherwise(_pick(vowels, draw(i, 2)))
            body = F.when(inner > 0, F.array_join(F.transform(F.sequence(F.lit(1), F.greatest(inner, F.lit(1))), letter), "")).otherwise("")
            return F.concat(body, F.when(female, _pick(fem, draw("last"))).otherwise(_pick(masc, draw("last"))))

        def lettered() -> Column:
            long_ = F.concat(low, F.repeat(F.substring(low, 1, 1), wider))

            def one(c: Column, i: Column) -> Column:
                code = F.ascii(c)
                out = None
                for a, b in RANGES:
                    new = _letter(F.lit(a) + F.pmod(draw(i, "letter"), F.lit(b - a + 1)))
                    out = F.when(code.between(a, b), new) if out is None else out.when(code.between(a, b), new)
                return out.otherwise(F.when(c.rlike(r"\p{M}"), c).otherwise(_pick([*LETTERS["latin"][0]], draw(i, "letter"))))

            return F.array_join(F.transform(F.filter(F.split(long_, ""), lambda c: c != ""), one), "")

        cyrillic, greek, latin = low.rlike(r"^\p{IsCyrillic}"), low.rlike(r"^\p{IsGreek}"), low.rlike(r"^\p{IsLatin}")
        return F.when(latin, spoken("latin")).when(cyrillic, spoken("cyrillic")).when(greek, spoken("greek")).otherwise(lettered())

    return _cased_like(_let(F.sha2(F.concat_ws("|", F.lit(key), F.lit("name"), low, tried.cast("string")), 256), drawn), part)


def _person(e: Column, one) -> Column:
    """The entity with each part of the name replaced by one(part)."""
    title = F.regexp_extract(e, rf"^((?:{'|'.join(TITLES)})\.? )", 1)

    def run(bare: Column) -> Column:
        between, parts = F.split(bare, _RUN, -1), F.regexp_extract_all(bare, F.lit(_RUN), F.lit(0))
        return F.array_join(F.transform(between, lambda b, i: F.concat(b, F.coalesce(one(F.get(parts, i)), F.lit("")))), "")

    return F.concat(title, _let(F.substring(e, F.length(title) + 1, F.length(e)), run))


# all other types


def _alphabet(c: Column, hexadecimal: Column) -> Column:
    out = F.when(hexadecimal & F.lit(HEX).contains(c), F.lit(HEX))
    for a in ALPHABETS:
        out = out.when(F.lit(a).contains(c), F.lit(a))
    return out.otherwise(F.lit(""))


def _place(a: Column, c: Column) -> Column:
    return (F.position(c, a) - 1).cast("long")


def _moved(c: Column, draw: Column, hexadecimal: Column, never_zero: bool = False) -> Column:
    """The letter c moved in its alphabet by a draw (any long)."""

    def body(a: Column) -> Column:
        size = F.length(a).cast("long")
        step = F.pmod(draw, size - 1) + 1 if never_zero else F.pmod(draw, size)
        return F.when(size < 2, c).otherwise(F.substring(a, (F.pmod(_place(a, c) + step, size) + 1).cast("int"), F.lit(1)))

    return _let(_alphabet(c, hexadecimal), body)


def _hidden(e: Column, kind: Column) -> Column:
    """For each character whether it may change, as an array."""
    at, n = F.position(F.lit("@"), e), F.length(e)
    tail = F.length(F.regexp_extract(e, r"(\.?[^.@]+\.[^.@]+)$", 1))
    code = F.when(e.rlike(r"^\+\d{1,3}\D"), F.length(F.regexp_extract(e, r"^(\+\d{1,3})", 1))).when(e.startswith("+"), 2).otherwise(0)

    def free(c: Column, i: Column) -> Column:
        return (
            F.when(kind == "email", (i + 1 < at) | ((i + 1 > at) & (i < n - tail)))
            .when(kind == "phone", i >= code)
            .when(kind == "card", (i > 0) & (i < n - 1))
            .when(kind == "iban", i >= 4)
            .otherwise(F.lit(True))
        )

    return F.transform(F.split(e, ""), lambda c, i: free(c, i))


def _luhn(digits: Column, n: Column) -> Column:
    """The digit that completes a number whose first n - 1 digits are given by the characters of an array."""
    total = F.aggregate(
        F.transform(digits, lambda c, i: _let(c.cast("int") * F.when(F.pmod(n - 1 - i, F.lit(2)) == 1, 2).otherwise(1), lambda d: F.when(d > 9, d - 9).otherwise(d))),
        F.lit(0),
        lambda a, b: a + b,
    )
    return F.pmod(-total, F.lit(10))


def _account_check(e: Column) -> Column:
    """The two check digits, as a number from 2 to 98, that make a bank account valid; spaces don't count."""
    bare = F.upper(F.regexp_replace(e, " ", ""))
    turned = F.concat(F.substring(bare, F.lit(5), F.length(bare)), F.substring(bare, 1, 2), F.lit("00"))
    code = lambda c: F.when(c.rlike("[0-9]"), c.cast("int")).otherwise(F.ascii(c) - 55)
    rest = F.aggregate(F.split(turned, ""), F.lit(0), lambda a, c: F.when(c == "", a).otherwise(F.pmod(a * F.when(c.rlike("[0-9]"), 10).otherwise(100) + code(c), F.lit(97)).cast("int")))
    return F.lit(98) - rest


def _ip(e: Column, secret: Column) -> Column:
    parts = F.transform(F.split(e, r"\."), lambda x: x.cast("long"))

    def draw(value: Column, k: int) -> Column:
        return F.xxhash64(F.sha2(F.concat(secret, F.lit(f"|ip{k}|"), value.cast("string")), 256))

    def run(p: Column) -> Column:
        left, right = F.element_at(p, 1) * 256 + F.element_at(p, 2), F.element_at(p, 3) * 256 + F.element_at(p, 4)
        return _let(
            F.pmod(left + draw(right, 1), F.lit(65536)),
            lambda a: _let(
                F.pmod(right + draw(a, 2), F.lit(65536)),
                lambda b: _let(
                    F.pmod(a + draw(b, 3), F.lit(65536)),
                    lambda c: F.concat_ws(".", F.floor(c / 256), F.pmod(c, F.lit(256)), F.floor(b / 256), F.pmod(b, F.lit(256))),
                ),
            ),
        )

    return _let(parts, run)


def surrogate(e: Column, key: str, attempt: Column | int = 0) -> Column:
    """The surrogate of an entity other than a person."""
    tried = F.lit(attempt) if isinstance(attempt, int) else attempt

    def run(kind: Column) -> Column:
        secret = F.concat(F.lit(key + "|"), kind, F.lit("|"), tried.cast("string"))
        small = F.lower(e)
        hexadecimal = ((kind == "secret") & small.rlike("^[0-9a-f]+$")) | (kind == "ipv6")
        start = F.split(small, "")
        places = F.filter(
            F.transform(F.arrays_zip(start.alias("c"), _hidden(e, kind).alias("free")), lambda x, i: F.when(x["free"] & (F.length(_alphabet(x["c"], hexadecimal)) > 1), i).otherwise(-1)),
            lambda i: i >= 0,
        )

        def permuted(at: Column) -> Column:
            last = F.element_at(at, -1)

            def mixed(chars: Column, parity: int, k: int) -> Column:
                """The changeable places of one parity, but the last of all, moved by a hash of all others."""
                active = lambda i: F.array_contains(at, i) & (i != last) & (F.pmod(F.array_position(at, i), F.lit(2)) == parity)
                rest = F.array_join(F.filter(F.transform(chars, lambda c, i: F.when(active(i), "").otherwise(c)), lambda c: c.isNotNull()), "")
                digits = F.when(kind.isin("phone", "card", "ssn"), F.regexp_replace(rest, "[^0-9]", "")).when(kind == "iban", F.regexp_replace(rest, " ", "")).otherwise(rest)
                return _let(F.sha2(F.concat(secret, F.lit(f"|{k}|"), digits), 256), lambda h: F.transform(chars, lambda c, i: F.when(active(i), _moved(c, F.xxhash64(h, F.array_position(at, i)), hexadecimal)).otherwise(c)))

            def turned(chars: Column) -> Column:
                rest = F.array_join(F.transform(chars, lambda c, i: F.when(i == last, "").otherwise(c)), "")
                digits = F.when(kind.isin("phone", "card", "ssn"), F.regexp_replace(rest, "[^0-9]", "")).when(kind == "iban", F.regexp_replace(rest, " ", "")).otherwise(rest)
                h = F.xxhash64(F.sha2(F.concat(secret, F.lit("|last|"), digits), 256))
                return F.transform(chars, lambda c, i: F.when(i == last, _moved(c, h, hexadecimal, never_zero=True)).otherwise(c))

            four = _let(start, lambda s0: _let(mixed(s0, 0, 0), lambda s1: _let(mixed(s1, 1, 1), lambda s2: _let(mixed(s2, 0, 2), lambda s3: _let(mixed(s3, 1, 3), turned)))))
            return F.when(F.size(at) == 0, start).otherwise(four)

        def cased(chars: Column) -> Column:
            shouted = (F.upper(e) == e) & (small != e)
            by_place = F.array_join(F.transform(F.arrays_zip(chars.alias("n"), F.split(e, "").alias("o")), lambda x: F.when((F.upper(x["o"]) == x["o"]) & (F.lower(x["o"]) != x["o"]), F.upper(x["n"])).otherwise(x["n"])), "")
            return F.when(shouted, F.upper(F.array_join(chars, ""))).otherwise(by_place)

        def checked(s: Column) -> Column:
            """A card's last digit follows the new digits as the old one followed the old."""
            old, new = F.split(F.regexp_replace(e, "[^0-9]", ""), ""), F.split(F.regexp_replace(s, "[^0-9]", ""), "")

            def digit(o: Column, n: Column) -> Column:
                size = F.size(o)
                return F.pmod(_luhn(F.slice(n, F.lit(1), size - 1), size) + F.element_at(o, -1).cast("int") - _luhn(F.slice(o, F.lit(1), size - 1), size), F.lit(10))

            return F.concat(F.substring(s, F.lit(1), F.length(s) - 1), _let(old, lambda o: _let(new, lambda n: digit(o, n).cast("string"))))

        def balanced(s: Column) -> Column:
            """A bank account's check digits follow the new account as the old ones followed the old."""
            off = F.substring(e, 3, 2).cast("int") - _account_check(e)
            return F.concat(F.substring(s, 1, 2), F.lpad((F.pmod(_account_check(s) + off - 2, F.lit(97)) + 2).cast("string"), 2, "0"), F.substring(s, F.lit(5), F.length(s)))

        def widened(s: Column) -> Column:
            """Further letters in front of an address whose own are taken; letters instead of a name without case."""
            drawn = F.translate(F.sha2(F.concat(secret, F.lit("|wide|"), small), 256), "0123456789", "ghijklmnop")
            more = 4 * F.floor(tried / 8).cast("int")
            opaque = e.rlike(r"^[^@]*\p{Lo}") | (F.size(places) == 0)
            return F.when(opaque, F.concat(F.substring(drawn, F.lit(1), more + 8), F.substring(s, F.position(F.lit("@"), s), F.length(s)))).otherwise(F.concat(F.substring(drawn, F.lit(1), more), s))

        def finished(s: Column) -> Column:
            return F.when(kind == "card", checked(s)).when(kind == "iban", balanced(s)).when(kind == "email", widened(s)).otherwise(s)

        return F.when(kind == "ip", _ip(e, secret)).otherwise(_let(_let(_let(places, permuted), cased), finished))

    return _let(kind_of(e), run)


# texts


def pieces_of(text: Column) -> Column:
    """The text cut at its entities: those stand at the odd places."""
    marked = F.split(F.regexp_replace(text, f"({ANY})", f"{MARK}$1{MARK}"), MARK, -1)
    between, hits = F.split(text, ANY, -1), F.regexp_extract_all(text, F.lit(ANY), F.lit(0))  # for texts that hold the mark
    slow = F.flatten(F.transform(between, lambda b, i: F.when(i < F.size(hits), F.array(b, F.get(hits, i))).otherwise(F.array(b))))
    return F.when(text.contains(MARK), slow).otherwise(marked)


def hits_of(pieces: Column) -> Column:
    return F.filter(pieces, lambda _, i: F.pmod(i, F.lit(2)) == 1)


def found(text: Column) -> Column:
    """All entities of a text, in order."""
    return F.regexp_extract_all(text, F.lit(ANY), F.lit(0))


def _values(hits: Column) -> Column:
    """What surrogates are made for: parts of names, and other entities whole; in lower case."""
    return F.flatten(F.transform(hits, lambda e: F.when(kind_of(e) == "person", F.transform(name_parts(e), lambda x: F.struct(F.lower(x).alias("value"), F.lit(True).alias("name")))).otherwise(F.array(F.struct(F.lower(e).alias("value"), F.lit(False).alias("name"))))))


def entities(docs: DataFrame) -> DataFrame:
    """value, name (whether it is a part of a name) and n (occurrences) of all distinct values."""
    hits = docs.select(found(F.col("text")).alias("hits")).where(F.size("hits") > 0)
    return hits.select(F.explode(_values(F.col("hits"))).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("n")).select("v.value", "v.name", "n")


def _named(values: DataFrame, key: str, attempt: int) -> DataFrame:
    """value, name and surrogate (lower case)."""
    v = F.col("value")
    return values.select("value", "name", F.lower(F.when(F.col("name"), name_surrogate(v, key, attempt)).otherwise(surrogate(v, key, attempt))).alias("surrogate"))


def repairs(docs: DataFrame, key: str) -> DataFrame:
    """value and attempt of the values whose first surrogate is a real value or another value's surrogate; empty as a
    rule.  Every value is settled; a format without any room left raises an error."""
    known = kept(_named(entities(docs), key, 0))
    real = known.select(F.col("value").alias("surrogate"))
    first = known.groupBy("surrogate").agg(F.min("value").alias("value"))
    good = first.join(real, "surrogate", "left_anti")
    open_ = kept(known.join(good, "value", "left_anti").select("value", "name"))
    settled = None
    for k in range(1, MAX_ATTEMPTS):
        if open_.isEmpty():
            break
        tried = _named(open_, key, k)
        taken = known.join(open_, "value", "left_anti").select("surrogate")
        if settled is not None:
            taken = taken.unionByName(settled.select("surrogate"))
        good = kept(tried.groupBy("surrogate").agg(F.min("value").alias("value")).join(real, "surrogate", "left_anti").join(taken, "surrogate", "left_anti").withColumn("attempt", F.lit(k)))
        settled = good if settled is None else settled.unionByName(good)
        open_ = kept(open_.join(good, "value", "left_anti"))
    else:
        raise RuntimeError(f"no distinct surrogates for {open_.limit(5).collect()}")
    return known.select("value", F.lit(0).alias("attempt")).where("false") if settled is None else settled.select("value", "attempt")


def _replaced(pieces: Column, key: str, attempt_of) -> Column:
    def one(e: Column) -> Column:
        return F.when(kind_of(e) == "person", _person(e, lambda x: name_surrogate(x, key, attempt_of(F.lower(x))))).otherwise(surrogate(e, key, attempt_of(F.lower(e))))

    return F.array_join(F.transform(pieces, lambda p, i: F.when(F.pmod(i, F.lit(2)) == 0, p).otherwise(one(p))), "")


def _with_texts(docs: DataFrame, key: str, check: bool) -> DataFrame:
    """_doc (the row), _pieces and _text (replaced)."""
    fixes: list = []
    if check:
        table = repairs(docs, key)
        fixes = [(r["value"], r["attempt"]) for r in table.limit(MAX_REPAIRS + 1).collect()]
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_doc"), pieces_of(F.col("text")).alias("_pieces"))
    if len(fixes) > MAX_REPAIRS:  # each document's own repairs reach it as a map
        tagged = rows.withColumn("_row", F.xxhash64("_doc.text"))
        one = tagged.select("_row", F.explode(F.array_distinct(_values(hits_of(F.col("_pieces"))))["value"]).alias("value")).distinct()
        own = one.join(table, "value").groupBy("_row").agg(F.map_from_entries(F.collect_list(F.struct("value", "attempt"))).alias("_fix"))
        rows = tagged.join(own, "_row", "left")
        attempt_of = lambda v: F.coalesce(F.element_at("_fix", v), F.lit(0))
    elif fixes:
        lookup = F.create_map(*(F.lit(v) for pair in fixes for v in pair))
        attempt_of = lambda v: F.coalesce(F.element_at(lookup, v), F.lit(0))
    else:
        attempt_of = lambda v: F.lit(0)
    text = F.when(F.size("_pieces") > 1, _replaced(F.col("_pieces"), key, attempt_of)).otherwise(F.col("_doc.text"))
    return rows.select("_doc", "_pieces", text.alias("_text"))


def replace(docs: DataFrame, key: str, check: bool = True) -> DataFrame:
    """All rows and columns, with the entities in ``text`` replaced."""
    done = _with_texts(docs, key, check)
    return done.select(*(F.col("_text").alias("text") if c == "text" else F.col(f"_doc.`{c}`").alias(c) for c in docs.columns))


def counted(docs: DataFrame, key: str, check: bool = True) -> DataFrame:
    """doc_id, text (replaced), n_entities and one count for each type."""
    done = _with_texts(docs.select("doc_id", "text"), key, check)
    kinds = F.transform(F.coalesce(hits_of(F.col("_pieces")), F.array().cast("array<string>")), kind_of)
    rows = done.select("_doc.doc_id", F.col("_text").alias("text"), kinds.alias("_kinds"))
    count = lambda k: F.size(F.filter("_kinds", lambda x: x == k)).cast("long")
    return rows.select("doc_id", "text", F.size("_kinds").cast("long").alias("n_entities"), *(count(k).alias(f"n_{k}") for k in TYPES))
