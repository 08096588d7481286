"""Personal data: surrogates in place of detected entities, in DataFrame functions only.

One pattern finds all kinds of entities in a text. The part of a mention that
identifies (the unit: digits of a number, an address in lower case, a surname)
is replaced by a keyed surrogate of the same kind and shape: digits for digits
in the same places, addresses for addresses, letters of the same case, names
of the same gender and script. What makes a number valid stays: check digits of
cards, assigned ranges of social security numbers and telephone areas, public
and reserved blocks of network addresses. One unit has one surrogate in the
whole corpus, so mentions still refer to the same thing.

A given name is a unit of its own beside its surname and gender. Numbers are
permuted by keyed Feistel networks, other surrogates are drawn from a keyed
digest (given names from a list at first, then made of syllables). All of them
are checked over all units of the corpus: of units that meet in one surrogate,
or in a unit that really occurs, all but the first are drawn again, until none
meet. Reserved network addresses are permuted within their block of 65,536,
which a corpus may well use up: they are different by construction and not
compared with real ones. Units drawn again are few; up to EXCEPTIONS they are
looked up in the plan, more are joined by a shuffle of mentions.

Names are found by the title before them; a name without a title is left alone.

Defined cases: a null text stays null and has no entities; empty texts stay
empty; repeated rows and null ids give one row each; an empty table gives an
empty result; numbers in IPv4 form beyond 255 are left alone; all further
columns of the input keep their names and values.
"""

from __future__ import annotations


from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spreadmax.llm.common import fresh
from spreadmax.session import written

KEY = "surrogates-1"
EXCEPTIONS = 500
#: Attempts after which a surrogate may be a unit that occurs elsewhere; surrogates still differ from each other.
ATTEMPTS = 64
KINDS = ("email", "secret", "phone", "ssn", "ip", "card", "name")
_TITLES_F = ("Mrs", "Ms", "Miss", "Frau", "Madame", "Señora", "Госпожа", "Κυρία")
_TITLES_M = ("Mr", "Herr", "Monsieur", "Señor", "Господин", "Κύριος")
#: Patterns of kinds, in the order in which they are tried at a place of the text.
PATTERNS = {
    "email": r"(?<![\p{L}\p{N}_%+\-.])[\p{L}\p{N}_%+\-]++(?:\.[\p{L}\p{N}_%+\-]++)*+@[\p{L}\p{N}\-]++(?:\.[\p{L}\p{N}\-]++)++",
    "secret": r"\b(?=[a-fA-F]*[0-9])[0-9a-fA-F]{32,64}\b|\b(?:AKIA|ASIA)[0-9A-Z]{16}\b|\bgh[pousr]_[0-9A-Za-z]{36}\b|\bsk_(?:live|test)_[0-9A-Za-z]{16,64}\b|\bxox[abprs]-[0-9A-Za-z\-]{10,64}\b",
    "phone": r"(?:\+[0-9]{1,3}[ .\-]?)?\([0-9]{3}\) ?[0-9]{3}[ .\-][0-9]{4}(?![0-9])|\+[0-9]{1,3}[ .\-][0-9]{3}[ .\-][0-9]{3}[ .\-][0-9]{4}(?![0-9])|\b[0-9]{3}-[0-9]{3}-[0-9]{4}\b|(?<![0-9.])[0-9]{3}\.[0-9]{3}\.[0-9]{4}(?![0-9]|\.[0-9])",
    "ssn": r"\b[0-9]{3}-[0-9]{2}-[0-9]{4}\b",
    "ip": r"(?<![0-9.])(?:(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])\.){3}(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])(?![0-9]|\.[0-9])"
    r"|(?<![\p{L}\p{N}:.])(?:(?:[0-9a-fA-F]{1,4}:){7}[0-9a-fA-F]{1,4}|(?:[0-9a-fA-F]{1,4}:){2,6}(?::[0-9a-fA-F]{1,4}){1,5}|[23][0-9a-fA-F]{3}:(?::[0-9a-fA-F]{1,4}){1,6})(?![\p{L}\p{N}:])",
    "card": r"\b[0-9]{4}(?: [0-9]{4} [0-9]{4} |-[0-9]{4}-[0-9]{4}-|[0-9]{8})[0-9]{4}\b|\b3[47][0-9]{2}(?: [0-9]{6} |-[0-9]{6}-|[0-9]{6})[0-9]{5}\b",
    "name": rf"\b(?:{'|'.join((*_TITLES_F, *_TITLES_M))})\.? (?:\p{{Lu}}[\p{{Ll}}'\-]+ )?\p{{Lu}}[\p{{Ll}}'\-]+",
}
ANY = "|".join(f"(?:{p})" for p in PATTERNS.values())
#: The same for texts without "@", in which no address can be: much faster.
REST = "|".join(f"(?:{p})" for k, p in PATTERNS.items() if k != "email")
#: Given names by script and gender, and syllables of surnames and addresses.
GIVEN = {
    ("latin", "f"): ["Alba", "Berta", "Carla", "Dora", "Elena", "Flora", "Greta", "Hanna", "Irma", "Julia", "Klara", "Lena", "Maria", "Nora", "Olga", "Paula"],
    ("latin", "m"): ["Adam", "Boris", "Conrad", "Dirk", "Emil", "Felix", "Georg", "Hugo", "Ivan", "Jonas", "Konrad", "Leon", "Martin", "Nils", "Oskar", "Pavel"],
    ("cyrillic", "f"): ["Анна", "Вера", "Дарья", "Елена", "Ирина", "Мария", "Ольга", "Юлия"],
    ("cyrillic", "m"): ["Антон", "Борис", "Денис", "Егор", "Иван", "Максим", "Олег", "Юрий"],
    ("greek", "f"): ["Άννα", "Ελένη", "Ιωάννα", "Μαρία"],
    ("greek", "m"): ["Άρης", "Γιώργος", "Νίκος", "Πέτρος"],
}
_ONSETS = {"latin": "b d f g k l m n p r s t v z h j".split(), "cyrillic": "б в г д з к л м н п р с т ф х ш".split(), "greek": "β γ δ ζ κ λ μ ν π ρ σ τ φ χ θ ξ".split()}
#: Endings of given names made of syllables: of women, of men.
_ENDINGS = {"latin": ("na", "n"), "cyrillic": ("на", "н"), "greek": ("να", "ς")}
_VOWELS = {"latin": "a e i o".split(), "cyrillic": "а е и о".split(), "greek": "α ε ι ο".split()}


def _hash(*parts: Column) -> Column:
    """A keyed number below 2**48."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 12), 16, 10).cast("long")


def _let(value: Column, use) -> Column:
    """`use(value)` with the value computed once, however often `use` needs it."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def permuted(number: Column, low: int, high: int, key: Column, rounds: int = 6) -> Column:
    """A keyed permutation of 0 .. low * high - 1: a Feistel network over the two parts of the number."""
    b = F.pmod(number, F.lit(high).cast("long"))
    state = F.struct(F.floor((number - b) / high).cast("long").alias("a"), b.alias("b"))

    def turn(s: Column, r: Column) -> Column:
        left = F.pmod(s["a"] + _hash(key, r.cast("string"), s["b"].cast("string")), F.lit(low).cast("long"))
        right = F.pmod(s["b"] + _hash(key, (r + 100).cast("string"), left.cast("string")), F.lit(high).cast("long"))
        return F.struct(left.alias("a"), right.alias("b"))

    end = F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), state, turn)
    return end["a"] * high + end["b"]


def _digits(text: Column) -> Column:
    return F.regexp_replace(text, "[^0-9]", "")


def _part(digits: Column, begin: int, size: int) -> Column:
    return F.substring(digits, begin, size).cast("long")


def _padded(number: Column, size: int) -> Column:
    return F.lpad(number.cast("string"), size, "0")


def _refilled(mention: Column, digits: Column) -> Column:
    """The mention with its last digits replaced in order by `digits`."""
    skip = F.length(_digits(mention)) - F.length(digits)
    start = F.struct(F.lit(0).alias("n"), F.lit("").alias("out"))

    def put(acc: Column, ch: Column) -> Column:
        is_digit = ch.between("0", "9") & (F.length(ch) == 1)
        new = F.when(acc["n"] >= skip, F.substring(digits, acc["n"] - skip + 1, F.lit(1))).otherwise(ch)
        return F.struct((acc["n"] + is_digit.cast("int")).alias("n"), F.concat(acc["out"], F.when(is_digit, new).otherwise(ch)).alias("out"))

    return F.aggregate(F.split(mention, ""), start, put)["out"]


def _reshaped(text: Column, keep: Column, hexed: bool, seed: Column) -> Column:
    """The text with every character beyond the first `keep` replaced by a keyed one of its class."""

    def shaped(digest: Column) -> Column:
        def put(ch: Column, i: Column) -> Column:
            n = F.conv(F.substring(digest, 2 * F.pmod(i, F.lit(64)) + 1, F.lit(2)), 16, 10).cast("int")
            some = lambda letters: F.substring(F.lit(letters), F.pmod(n, F.lit(len(letters))) + 1, F.lit(1))
            if hexed:
                made = F.when(ch.rlike("^[0-9a-f]$"), some("0123456789abcdef"))
            else:
                lower = "abcdefghijklmnopqrstuvwxyz"
                made = F.when(ch.rlike("^[0-9]$"), some("0123456789")).when(ch.rlike("^[a-z]$"), some(lower)).when(ch.rlike("^[A-Z]$"), some(lower.upper()))
            return F.when(i < keep, ch).otherwise(made.otherwise(ch))

        return F.array_join(F.transform(F.split(text, ""), put), "")

    return _let(F.concat(F.sha2(seed, 256), F.sha2(F.concat(seed, F.lit("|more")), 256)), shaped)


def check_digit(payload: Column) -> Column:
    """The digit that makes a card number valid."""
    back = F.reverse(payload)

    def add(acc: Column, i: Column) -> Column:
        d = F.substring(back, i, F.lit(1)).cast("int") * F.when(F.pmod(i, F.lit(2)) == 1, 2).otherwise(1)
        return acc + F.when(d > 9, d - 9).otherwise(d)

    return F.pmod(-F.aggregate(F.sequence(F.lit(1), F.length(payload)), F.lit(0), add), F.lit(10))


def _card(digits: Column, key: Column) -> Column:
    """The issuer's digits stay; a valid number stays valid, an invalid one is as far off."""

    def of(size: int, keep: int) -> Column:
        free = size - 1 - keep
        half = 10 ** (free // 2)
        off = _part(digits, size, 1) - check_digit(F.substring(digits, 1, size - 1))
        new = F.concat(F.substring(digits, 1, keep), _padded(permuted(_part(digits, keep + 1, free), 10**free // half, half, key), free))
        return _let(new, lambda n: F.concat(n, F.pmod(check_digit(n) + off, F.lit(10)).cast("string")))

    return F.when(F.length(digits) == 15, of(15, 2)).otherwise(of(16, 1))


def _ssn(digits: Column, key: Column) -> Column:
    area, group, serial = _part(digits, 1, 3), _part(digits, 4, 2), _part(digits, 6, 4)
    valid = (area > 0) & (area < 900) & (area != 666) & (group > 0) & (serial > 0)
    areas, rest = 898, 99 * 9999
    number = (area - F.when(area > 666, 2).otherwise(1)) * rest + (group - 1) * 9999 + serial - 1

    def made(new: Column) -> Column:
        low = F.pmod(new, F.lit(rest).cast("long"))
        rank = F.floor(new / rest)
        return F.concat(
            _padded(rank + F.when(rank >= 665, 2).otherwise(1), 3), _padded(F.floor(low / 9999) + 1, 2), _padded(F.pmod(low, F.lit(9999).cast("long")) + 1, 4)
        )

    return F.when(valid, _let(permuted(number, areas, rest, key), made)).otherwise(_padded(permuted(digits.cast("long"), 10_000, 100_000, key), 9))


def _phone(digits: Column, key: Column) -> Column:
    """Ten digits; area and exchange that begin with 2 to 9 go on doing so."""
    area, rest, span = _part(digits, 1, 3), _part(digits, 4, 7), 8_000_000
    made = lambda new: F.concat(_padded(F.floor(new / span) + 200, 3), _padded(F.pmod(new, F.lit(span).cast("long")) + 2_000_000, 7))
    valid = (area >= 200) & (rest >= 2_000_000)
    new = permuted((area - 200) * span + rest - 2_000_000, 800, span, key)
    return F.when(valid, _let(new, made)).otherwise(_padded(permuted(digits.cast("long"), 100_000, 100_000, key), 10))


#: First parts of network addresses that hold public ones only.
_PUBLIC = [o for o in range(1, 224) if o not in (10, 100, 127, 169, 172, 192, 198, 203)]


def reserved_address(kind: Column, unit: Column) -> Column:
    """Addresses that are permuted within their block of 65,536."""
    first = F.split_part(unit, F.lit("."), F.lit(1))
    return (kind == "ip") & ~unit.contains(":") & ~first.isin(*map(str, _PUBLIC))


def _address(unit: Column, key: str, attempt: Column) -> Column:
    seed = lambda n: F.concat_ws("|", F.lit(key), F.lit("ip"), n.cast("string"))
    part = lambda n, k: F.pmod(F.shiftright(n, k), F.lit(256)).cast("string")

    def short(octets: Column) -> Column:
        at = lambda i: F.get(octets, F.lit(i))
        low = at(2) * 256 + at(3)
        rank = F.array_position(F.array(*[F.lit(o).cast("long") for o in _PUBLIC]), at(0)) - 1
        names = F.array(*[F.lit(str(o)) for o in _PUBLIC])
        moved = permuted((rank * 256 + at(1)) * 65536 + low, len(_PUBLIC) * 256, 65536, seed(attempt))
        public = _let(moved, lambda n: F.concat_ws(".", F.get(names, F.shiftright(n, 24).cast("int")), part(n, 16), part(n, 8), part(n, 0)))
        near = permuted(low, 256, 256, F.concat_ws("|", seed(F.lit(0)), at(0), at(1)))
        kept = _let(near, lambda n: F.concat_ws(".", at(0).cast("string"), at(1).cast("string"), part(n, 8), part(n, 0)))
        return F.when(at(0).isin(*_PUBLIC), public).otherwise(kept)

    long = _reshaped(unit, F.length(F.split_part(unit, F.lit(":"), F.lit(1))), True, F.concat_ws("|", seed(attempt), unit))
    return F.when(unit.contains(":"), long).otherwise(_let(F.transform(F.split(unit, r"\."), lambda x: x.try_cast("long")), short))


def _script(word: Column) -> Column:
    return F.when(word.rlike(r"\p{IsCyrillic}"), "cyrillic").when(word.rlike(r"\p{IsGreek}"), "greek").otherwise("latin")


def _word(seed: Column, syllables: int, script: str) -> Column:
    on, vo = F.array(*[F.lit(x) for x in _ONSETS[script]]), F.array(*[F.lit(x) for x in _VOWELS[script]])

    def made(n: Column) -> Column:
        part = lambda k: F.pmod(F.shiftright(n, 6 * k), F.lit(64)).cast("int")
        return F.concat(*[F.concat(F.get(on, F.pmod(part(k), F.lit(16))), F.get(vo, F.floor(part(k) / 16).cast("int"))) for k in range(syllables)])

    return _let(seed, made)


def _by_script(word: Column, make) -> Column:
    kind = _script(word)
    return F.when(kind == "cyrillic", make("cyrillic")).when(kind == "greek", make("greek")).otherwise(make("latin"))


def kind_of(mention: Column) -> Column:
    out = F.lit("name")
    for kind in reversed(KINDS[:-1]):
        out = F.when(mention.rlike(f"^(?:{PATTERNS[kind]})$"), kind).otherwise(out)
    return out


def unit_of(mention: Column, kind: Column) -> Column:
    """What identifies: equal units are the same entity."""
    surname = F.lower(F.element_at(F.split(mention, " "), -1))
    digits = _digits(mention)
    hexed = mention.rlike("^[0-9a-fA-F]+$")
    return (
        F.when(kind.isin("email", "ip") | ((kind == "secret") & hexed), F.lower(mention))
        .when(kind == "secret", mention)
        .when(kind == "name", surname)
        .when(kind == "phone", F.substring(digits, F.length(digits) - 9, F.lit(10)))
        .otherwise(digits)
    )


def given_of(mention: Column, kind: Column) -> Column:
    """The unit of a given name: surname, given name and gender; null where the mention has none."""
    words = F.split(mention, " ")
    title = F.regexp_replace(F.element_at(words, 1), r"\.$", "")
    gender = F.when(title.isin(*_TITLES_F), "f").otherwise("m")
    name = F.concat_ws("|", F.lower(F.element_at(words, -1)), F.lower(F.get(words, F.lit(1))), gender)
    return F.when((kind == "name") & (F.size(words) > 2), name)


def _given(unit: Column, attempt: Column, key: str) -> Column:
    """The surrogate of a given name, in lower case: of the list at first, then of syllables with an ending of its gender."""
    first = F.split_part(unit, F.lit("|"), F.lit(2))
    female = unit.endswith("|f")

    def by_script(script: str) -> Column:
        def pick(g: str) -> Column:
            names, n = F.array(*[F.lit(x.lower()) for x in GIVEN[script, g]]), len(GIVEN[script, g])
            at = F.pmod(_hash(F.lit(f"{key}|given"), first), F.lit(n)).cast("int")
            # never the name itself
            return F.when(F.get(names, at) == first, F.get(names, F.pmod(at + 1, F.lit(n)))).otherwise(F.get(names, at))

        made = _word(_hash(F.lit(f"{key}|given"), unit, attempt.cast("string")), 4, script)
        f, m = _ENDINGS[script]
        return F.when(attempt == 0, F.when(female, pick("f")).otherwise(pick("m"))).otherwise(F.concat(made, F.when(female, f).otherwise(m)))

    return _by_script(first, by_script)


def _drawn_email(unit: Column, attempt: Column, key: str) -> Column:
    seed = lambda *more: _hash(F.lit(key), F.lit("email"), unit, attempt.cast("string"), *more)
    local, host = F.split_part(unit, F.lit("@"), F.lit(1)), F.split_part(unit, F.lit("@"), F.lit(2))
    tail = F.regexp_extract(local, "([0-9]*)$", 1)
    word = _by_script(local, lambda s: _word(seed(), 7, s))

    def made(more: Column) -> Column:
        numbers = F.substring(F.lpad(more.cast("string"), 15, "7"), F.lit(1), F.length(tail))
        place = F.regexp_replace(host, "[0-9]+", F.pmod(more, F.lit(10)).cast("string"))
        return F.concat(word, F.when(local.contains("."), ".").otherwise(""), numbers, F.lit("@"), place)

    return _let(seed(F.lit("more")), made)


def _drawn_secret(unit: Column, attempt: Column, key: str) -> Column:
    text = F.concat_ws("|", F.lit(key), unit, attempt.cast("string"))
    prefix = F.length(F.regexp_extract(unit, r"^(AKIA|ASIA|gh[pousr]_|sk_live_|sk_test_|xox[abprs]-)", 1))
    return F.when(unit.rlike("^[0-9a-f]+$"), F.substring(F.sha2(text, 256), F.lit(1), F.length(unit))).otherwise(_reshaped(unit, prefix, False, text))


def drawn_given(unit: Column, attempt: Column, key: str) -> Column:
    """A given name has to differ from others of its surname and gender only."""
    return F.concat_ws("|", F.split_part(unit, F.lit("|"), F.lit(1)), _given(unit, attempt, key), F.split_part(unit, F.lit("|"), F.lit(3)))


def drawn(kind: Column, unit: Column, attempt: Column, key: str) -> Column:
    """Surrogates in the form of their units: digits of numbers, the rest in lower case (but for keys of services). Not of given names."""
    turn = F.concat_ws("|", F.lit(key), kind, attempt.cast("string"))
    surname = _by_script(unit, lambda s: _word(_hash(F.lit(key), F.lit("name"), unit, attempt.cast("string")), 5, s))
    return (
        F.when(kind == "email", _drawn_email(unit, attempt, key))
        .when(kind == "secret", _drawn_secret(unit, attempt, key))
        .when(kind == "phone", _phone(unit, turn))
        .when(kind == "ssn", _ssn(unit, turn))
        .when(kind == "card", _card(unit, turn))
        .when(kind == "ip", _address(unit, key, attempt))
        .otherwise(surname)
    )


def _cased(mention: Column, lower: Column) -> Column:
    loud = (F.upper(mention) == mention) & (F.lower(mention) != mention)
    return F.when(loud, F.upper(lower)).otherwise(lower)


def surrogate(mention: Column, kind: Column, low: Column, given: Column) -> Column:
    """The text that stands for a mention; `low` and `given` are the drawn surrogates of its unit and of its given name."""
    words = F.split(mention, " ")
    first = F.initcap(F.split_part(given, F.lit("|"), F.lit(2)))
    name = F.concat_ws(" ", F.element_at(words, 1), first, F.initcap(low))
    return (
        F.when(kind.isin("phone", "ssn", "card"), _refilled(mention, low))
        .when(kind == "name", name)
        .when((kind == "secret") & ~mention.rlike("^[0-9a-fA-F]+$"), low)
        .otherwise(_cased(mention, low))
    )


#: Texts without any of these have no entity but addresses.
_MIGHT = "|".join(("[0-9]", *_TITLES_F, *_TITLES_M, "gh[pousr]_", "sk_", "xox", "AKIA", "ASIA", "::"))


def _found(docs: DataFrame, into: str) -> DataFrame:
    """`docs` with the column `into`: an array of (mention, kind, unit, given) in the order of the text."""
    text = F.coalesce(F.col("text"), F.lit(""))
    every = lambda pattern: F.regexp_extract_all(text, F.lit(f"({pattern})"), F.lit(1))
    mentions = (
        F.when(text.contains("@"), every(ANY)).when(text.rlike(_MIGHT), every(REST)).otherwise(F.array().cast("array<string>"))
    )
    kinds = F.transform(F.col(into), lambda e: F.struct(e.alias("mention"), kind_of(e).alias("kind")))
    whole = F.transform(
        F.col(into), lambda x: F.struct(x["mention"], x["kind"], unit_of(x["mention"], x["kind"]).alias("unit"), given_of(x["mention"], x["kind"]).alias("given"))
    )
    return docs.withColumn(into, mentions).withColumn(into, kinds).withColumn(into, whole)


def repeated_draws(units: DataFrame, key: str = KEY) -> DataFrame:
    """Distinct (kind, unit) -> (kind, unit, attempt, low) of those whose first surrogate met another or a real unit; low is the last one."""
    def tried(df: DataFrame, attempt: int) -> DataFrame:
        unit, n = F.col("unit"), F.lit(attempt)
        low = F.when(F.col("kind") == "given", drawn_given(unit, n, key)).otherwise(drawn(F.col("kind"), unit, n, key))
        return df.select("kind", "unit", n.alias("attempt"), low.alias("low"))

    own = written(tried(units, 0), "units")
    real = own.select("kind", F.col("unit").alias("low")).withColumn("real", F.lit(True))
    settled, fresh, attempt = None, own, 0
    again = None
    while True:
        # The first unit of a surrogate keeps it; units settled before come first.
        firsts = fresh.groupBy("kind", "low").agg(F.min("unit").alias("first"))
        checked = fresh.join(firsts, ["kind", "low"]).join(real, ["kind", "low"], "left")
        if settled is not None:
            checked = checked.join(settled.select("kind", "low").withColumn("taken", F.lit(True)), ["kind", "low"], "left")
        else:
            checked = checked.withColumn("taken", F.lit(None).cast("boolean"))
        met = (F.col("unit") != F.col("first")) | F.col("taken").isNotNull()
        if attempt < ATTEMPTS:
            met = met | F.col("real").isNotNull()
        clash = met & ~reserved_address(F.col("kind"), F.col("unit"))
        checked = written(checked.withColumn("clash", clash).select("kind", "unit", "attempt", "low", "clash"), "checked")
        good = checked.filter("not clash").select("kind", "unit", "attempt", "low")
        settled = good if settled is None else settled.unionByName(good)
        if attempt:
            again = good if again is None else again.unionByName(good)
        bad = checked.filter("clash").select("kind", "unit")
        if not bad.limit(1).count():
            break
        attempt += 1
        fresh = tried(bad, attempt)
    if again is None:
        again = checked.filter("false").select("kind", "unit", "attempt", "low")
    return again.select("kind", "unit", "attempt", "low")


def replace_pii(docs: DataFrame, key: str = KEY, exceptions: int = EXCEPTIONS) -> DataFrame:
    """`docs` with text replaced, and entities: an array of (kind, mention, surrogate) in the order of the text.

    Where `docs` has a column of that name, it stays and the array is called entities_ (with one more underscore than is taken).
    """
    into, found_in, row, lows_in, pieces, text = fresh(docs.columns, "entities", "found", "row_number", "lows", "pieces", "new_text")
    found = _found(docs, found_in)
    units = F.concat(
        F.transform(found_in, lambda x: F.struct(x["kind"].alias("kind"), x["unit"].alias("unit"))),
        F.transform(F.filter(found_in, lambda x: x["given"].isNotNull()), lambda x: F.struct(F.lit("given").alias("kind"), x["given"].alias("unit"))),
    )
    mentions = found.select(F.explode(units).alias("m")).select("m.kind", "m.unit")
    again = written(repeated_draws(mentions.distinct(), key), "again")
    few = again.limit(exceptions + 1).count() <= exceptions
    if few:
        listed = {(r["kind"], r["unit"]): r["attempt"] for r in again.collect()}  # at most `exceptions`

        def attempt_of(kind: Column, unit: Column) -> Column:
            pairs = [F.lit(v) for (k, u), n in sorted(listed.items()) for v in (f"{k}|{u}", str(n))]
            return F.coalesce(F.try_element_at(F.create_map(*pairs), F.concat_ws("|", kind, unit)).cast("int"), F.lit(0)) if listed else F.lit(0)

        low = lambda x: _let(attempt_of(x["kind"], x["unit"]), lambda n: drawn(x["kind"], x["unit"], n, key))
        named = lambda x: _let(attempt_of(F.lit("given"), x["given"]), lambda n: drawn_given(x["given"], n, key))
        given = lambda x: F.when(x["given"].isNotNull(), named(x))
    else:
        rows = written(found.withColumn(row, F.monotonically_increasing_id()), "mentions")
        each = rows.select(F.col(row).alias("row"), F.posexplode(found_in).alias("at", "m")).select("row", "at", "m.kind", "m.unit", "m.given")
        # mentions without a given name have keys of their own, so no task gets them all
        each = each.withColumn("own", F.coalesce("given", F.concat_ws(":", "row", "at")))
        firsts = again.filter("kind = 'given'").select(F.col("unit").alias("own"), F.col("low").alias("first"))
        lows = (
            each.join(again, ["kind", "unit"], "left")
            .join(firsts, "own", "left")
            .withColumn("first", F.when(F.col("given").isNotNull(), F.coalesce("first", drawn_given(F.col("given"), F.lit(0), key))))
            .withColumn("low", F.coalesce("low", drawn(F.col("kind"), F.col("unit"), F.lit(0), key)))
            .groupBy(F.col("row").alias(row))
            .agg(F.array_sort(F.collect_list(F.struct("at", "low", "first"))).alias(lows_in))
        )
        found = rows.join(lows, row, "left").withColumn(
            found_in, F.transform(found_in, lambda x, i: F.struct(x["mention"], x["kind"], x["unit"], F.get(lows_in, i)["low"].alias("low"), F.get(lows_in, i)["first"].alias("first")))
        )
        low, given = lambda x: x["low"], lambda x: x["first"]
    shown = F.transform(
        found_in,
        lambda x: F.struct(x["kind"].alias("kind"), x["mention"].alias("mention"), _let(low(x), lambda n: surrogate(x["mention"], x["kind"], n, given(x))).alias("surrogate")),
    )
    done = found.withColumn(into, shown)
    between = F.when(F.col("text").contains("@"), F.split(F.col("text"), ANY, -1)).otherwise(F.split(F.col("text"), REST, -1))
    rebuilt = F.concat(
        F.get(F.col(pieces), F.lit(0)),
        F.array_join(F.transform(into, lambda e, i: F.concat(e["surrogate"], F.get(F.col(pieces), i + 1))), ""),
    )
    out = done.withColumn(pieces, F.when(F.size(into) > 0, between)).withColumn(
        text, F.when(F.size(into) > 0, rebuilt).otherwise(F.col("text"))
    )
    return out.select(*[F.col(text).alias(c) if c == "text" else F.col(f"`{c}`") for c in docs.columns], into)


def summary(docs: DataFrame, key: str = KEY) -> DataFrame:
    """doc_id, n_entities, the number of entities of each kind, mentions and surrogates in order, and the digest of the new text."""
    done = replace_pii(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), key)
    number = lambda kind: F.size(F.filter("entities", lambda e: e["kind"] == kind)).cast("long")
    counts = [number(kind).alias(f"n_{kind}") for kind in KINDS]
    return done.select(
        "doc_id", F.size("entities").cast("long").alias("n_entities"), *counts,
        F.array_join(F.transform("entities", lambda e: e["mention"]), "\t").alias("mentions"),
        F.array_join(F.transform("entities", lambda e: e["surrogate"]), "\t").alias("surrogates"),
        F.sha2(F.coalesce("text", F.lit("")), 256).alias("text_sha256"),
        F.octet_length(F.coalesce("text", F.lit(""))).cast("long").alias("n_bytes"),
    )
