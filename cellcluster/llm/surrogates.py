"""Personal data: detected entities receive keyed surrogates of the same kind and format.

Numbers (addresses of machines, cards, phones, social security numbers) go
through a keyed Feistel network over their digits: a permutation, so different
numbers of one format stay different, and one number always gets one surrogate.
Addresses of mail and bank accounts are replaced character by character within
their class, with right check digits for accounts. A name is found by its title
and replaced word by word: a surname always by one surname, a given name by one
of the same gender, both in the script they are written in, so ``Mr Smith`` and
``Mr John Smith`` stay one person. A full name that a title announces is looked
for in the same text without the title too.

A check over the distinct entities of the whole table, names by their words,
looks for surrogates that meet, or that are somebody else's entity, and gives
those another draw until none is left. Every step on the table is a DataFrame or
SQL expression.
"""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import durable, table

# Titles that announce a name, by gender, given names by gender and script, and what surnames are made of.
MALE_TITLES = ("Mr", "Herr", "Sr", "Señor", "Monsieur", "г-н", "κ", "Κύριος")
FEMALE_TITLES = ("Mrs", "Ms", "Miss", "Frau", "Sra", "Señora", "Mme", "Madame", "г-жа", "κα", "Κυρία")
ANY_TITLES = ("Dr", "Prof")
GIVEN = {
    ("m", "Latin"): ("James", "Peter", "Lucas", "Martin", "Hugo", "Oscar", "Pablo", "Bruno", "Felix", "Simon", "Adam", "Victor"),
    ("f", "Latin"): ("Alice", "Clara", "Emma", "Julia", "Laura", "Maria", "Nina", "Olivia", "Paula", "Sofia", "Teresa", "Vera"),
    ("m", "Cyrillic"): ("Иван", "Олег", "Павел", "Борис", "Артём", "Глеб", "Роман", "Юрий"),
    ("f", "Cyrillic"): ("Анна", "Вера", "Дарья", "Елена", "Ольга", "Мария", "Нина", "Юлия"),
    ("m", "Greek"): ("Γιώργος", "Πέτρος", "Παύλος", "Μάρκος", "Θωμάς", "Στέφανος", "Λουκάς", "Σπύρος"),
    ("f", "Greek"): ("Μαρία", "Ελένη", "Άννα", "Σοφία", "Ειρήνη", "Δήμητρα", "Βασιλική", "Ζωή"),
}
#: Endings of made-up given names, by gender.
ENDINGS = {"Latin": {"m": "us", "f": "a"}, "Cyrillic": {"m": "ан", "f": "а"}, "Greek": {"m": "ος", "f": "α"}}
SYLLABLES = {
    "Latin": ("ba", "den", "ro", "mil", "ta", "ven", "lo", "ker", "sa", "lin", "do", "mar", "fe", "nor", "gi", "wel"),
    "Cyrillic": ("ба", "ден", "ро", "мил", "та", "вен", "ло", "кор", "са", "лин", "до", "мар", "фе", "нор", "ги", "вел"),
    "Greek": ("βα", "δεν", "ρο", "μιλ", "τα", "νεν", "λο", "κορ", "σα", "λιν", "δο", "μαρ", "φε", "νορ", "γι", "πελ"),
    "Arabic": ("با", "دن", "رو", "ميل", "تا", "فن", "لو", "كر", "سا", "لين", "دو", "مار", "في", "نور", "جي", "ول"),
    "Hebrew": ("בא", "דן", "רו", "מיל", "תא", "בן", "לו", "קר", "סא", "לין", "דו", "מר", "פי", "נור", "גי", "ול"),
    "Devanagari": ("बा", "देन", "रो", "मिल", "ता", "वेन", "लो", "कर", "सा", "लिन", "दो", "मार", "फे", "नोर", "गी", "वेल"),
}
#: Scripts whose names keep their number of characters: what they begin with, and what follows.
CHARACTERS = {
    "Han": ("王李张刘陈杨赵黄周吴徐孙胡朱高林", "伟芳娜敏静丽强磊军洋勇艳杰娟涛明超兰霞平刚桂华建国文辉玉春海云"),
    "Hangul": ("김이박최정강조윤장임한오서신권황", "민서준하은지우현도연수진영주호성재원유경선희태윤아석기훈정미상혜"),
    "Hiragana": ("あいうえおかきくけこさしすせそた", "なにぬねのはひふへほまみむめもやゆよらりるれろわちつてとがぎぐげ"),
    "Katakana": ("アイウエオカキクケコサシスセソタ", "ナニヌネノハヒフヘホマミムメモヤユヨラリルレロワチツテトガギグゲ"),
}
PARTICLES = "van|von|de|der|den|la|di|da|bin|ibn|al"

_OCTET = r"(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
_TITLES = "|".join(sorted((*MALE_TITLES, *FEMALE_TITLES, *ANY_TITLES), key=lambda t: -len(t)))
#: A word of a name: a capital and more letters, or letters of a script without capitals.
_WORD = r"(?:\p{Lu}[\p{L}\p{M}'’-]++|\p{Lo}[\p{L}\p{M}'’-]*+)"
_TITLE = rf"(?:{_TITLES})\.? "
#: In order of precedence; each starts only where no run of its own characters goes on.
KINDS = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9_%+][A-Za-z0-9._%+-]*+@[A-Za-z0-9](?:[A-Za-z0-9-]{0,62}\.){1,8}[A-Za-z]{2,24}(?![A-Za-z0-9])",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])",
    "ip": rf"(?<![0-9.]){_OCTET}(?:\.{_OCTET}){{3}}(?!\.?[0-9])",
    "ssn": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    "phone": r"(?<![0-9+])\+[0-9]{1,3}(?:[ .-]?\([0-9]{1,4}\))?(?:[ .-]?[0-9]{2,4}){2,5}(?![0-9])|(?<![0-9])\([0-9]{3}\)[ -]?[0-9]{3}[ .-][0-9]{4}(?![0-9])|(?<![0-9.-])[0-9]{3}[.-][0-9]{3}[.-][0-9]{4}(?![0-9])",
    "card": r"(?<![0-9-])[0-9](?:[ -]?[0-9]){12,18}(?![0-9])",
    "name": rf"(?<![\p{{L}}\p{{N}}]){_TITLE}{_WORD}(?:(?: (?:{PARTICLES})(?= ))*+ {_WORD})?",
}
ANY = "|".join(f"(?:{p})" for p in KINDS.values())
#: No entity is without one of these; a text that lacks them is not searched further.
HINT = rf"[0-9@]|(?<!\p{{L}}){_TITLE}[\p{{Lu}}\p{{Lo}}]"
#: Overridden draws beyond which they travel by a join instead of inside the plan.
INLINE = 500


#: What marks words of names among the values that are drawn: a given name with its gender, a surname.
_GIVEN, _SURNAME = "\x01g", "\x01s"


def _rest(m: Column) -> Column:
    return F.regexp_replace(m, f"^{_TITLE}", "")


def _gender(m: Column) -> Column:
    male, female = (m.rlike("^(?:" + "|".join(t) + r")\.? ") for t in (MALE_TITLES, FEMALE_TITLES))
    return F.when(male, "m").when(female, "f").otherwise("a")


def with_entities(rows: DataFrame, text: str) -> DataFrame:
    """``rows`` with found, all entities of the text in order (null where there can be none), again, the pattern of the text, and genders of its full names.

    A name of several words under a title is found again without it.
    """
    body = F.col(text)
    rows = rows.withColumn("found", F.when(body.rlike(HINT), F.regexp_extract_all(body, F.lit(ANY), F.lit(0))))
    full = F.filter("found", lambda m: m.rlike(f"^{_TITLE}{_WORD} "))
    # a title that tells the gender counts before one that does not
    gender = lambda n: F.array_max(F.transform(F.filter(full, lambda m: _rest(m) == n), _gender))
    entries = F.transform(F.array_distinct(F.transform(full, _rest)), lambda n: F.struct(n.alias("name"), gender(n).alias("gender")))
    rows = rows.withColumn("genders", F.when(F.size(full) > 0, F.map_from_entries(entries)))
    names = F.array_join(F.map_keys("genders"), "|")
    rows = rows.withColumn("again", F.concat(F.lit(ANY + r"|(?<![\p{L}\p{N}])(?:"), names, F.lit(r")(?![\p{L}\p{N}])")))
    return rows.withColumn("found", F.when(F.col("again").isNull(), F.col("found")).otherwise(F.regexp_extract_all(body, F.col("again"), F.lit(0))))


def _is_name(m: Column) -> Column:
    """Of all entities only names have neither a digit nor an @."""
    return ~m.rlike("[0-9@]")


def kind_of(m: Column) -> Column:
    out = F.lit("name")
    for kind in reversed([k for k in KINDS if k != "name"]):
        out = F.when(m.rlike(f"^(?:{KINDS[kind]})$"), F.lit(kind)).otherwise(out)
    return out


def _draw(key: str, *parts: Column) -> Column:
    """A number below 2 ** 60 from a keyed digest."""
    return F.conv(F.substring(F.sha2(F.concat_ws("\x1f", F.lit(key), *parts), 256), 1, 15), 16, 10).cast("bigint")


def _feistel(high: Column, low: Column, high_mod: Column, low_mod: Column, key: str, salt: Column, rounds: int = 3) -> Column:
    """struct(high, low): both halves shifted in turn by a keyed function of the other; a permutation."""
    # the halves pass through an aggregate, so no expression is copied
    return F.aggregate(
        F.sequence(F.lit(1), F.lit(rounds)),
        F.struct(high.alias("h"), low.alias("l")),
        lambda acc, r: F.aggregate(
            F.array(F.pmod(acc["h"] + F.pmod(_draw(key, salt, F.lit("a"), r.cast("string"), acc["l"].cast("string")), high_mod), high_mod)),
            F.struct(F.lit(0).cast("bigint").alias("h"), F.lit(0).cast("bigint").alias("l")),
            lambda _, h: F.struct(h.alias("h"), F.pmod(acc["l"] + F.pmod(_draw(key, salt, F.lit("b"), r.cast("string"), h.cast("string")), low_mod), low_mod).alias("l")),
        ),
    )


def _digits_permuted(digits: Column, key: str, salt: Column) -> Column:
    """Digits of any length from 2 to 30, as many again."""
    n = F.length(digits)
    half = F.floor(n / 2).cast("int")
    tens = lambda k: F.rpad(F.lit("1"), k + 1, "0").cast("bigint")
    out = _feistel(F.substr(digits, F.lit(1), half).cast("bigint"), F.substr(digits, half + 1).cast("bigint"), tens(half), tens(n - half), key, F.concat_ws("|", salt, n.cast("string")))
    return F.aggregate(F.array(out), F.lit(""), lambda _, o: F.concat(F.lpad(o["h"].cast("string"), half, "0"), F.lpad(o["l"].cast("string"), n - half, "0")))


def _refill(shape: Column, digits: Column) -> Column:
    """``shape`` with its digits replaced in order."""
    return F.aggregate(
        F.split(shape, ""), F.struct(F.lit("").alias("s"), F.lit(1).alias("i")),
        lambda acc, c: F.when(c.rlike("^[0-9]$"), F.struct(F.concat(acc["s"], F.substr(digits, acc["i"], F.lit(1))).alias("s"), (acc["i"] + 1).alias("i"))).otherwise(F.struct(F.concat(acc["s"], c).alias("s"), acc["i"].alias("i"))),
        lambda acc: acc["s"],
    )


def _same_class(value: Column, key: str, salt: Column) -> Column:
    """Letters become letters, digits digits, the rest stays."""
    stream = F.concat(F.sha2(F.concat_ws("\x1f", F.lit(key), salt, value), 256), F.sha2(F.concat_ws("\x1f", F.lit(key), salt, value, F.lit("2")), 256))

    def one(c: Column, i: Column) -> Column:
        n = F.conv(F.substr(stream, F.pmod(i * 2, F.lit(128)) + 1, F.lit(2)), 16, 10).cast("int")
        pick = lambda letters: F.substr(F.lit(letters), F.pmod(n, F.lit(len(letters))) + 1, F.lit(1))
        return F.when(c.rlike("^[a-z]$"), pick("abcdefghijklmnopqrstuvwxyz")).when(c.rlike("^[A-Z]$"), pick("ABCDEFGHIJKLMNOPQRSTUVWXYZ")).when(c.rlike("^[0-9]$"), pick("0123456789")).otherwise(c)

    return F.concat_ws("", F.transform(F.split(value, ""), one))


def _luhn_sum(digits: Column, doubled_last: bool) -> Column:
    back = F.split(F.reverse(digits), "")
    worth = lambda c, i: F.when(F.pmod(i, F.lit(2)) == (0 if doubled_last else 1), F.pmod(c.cast("int") * 2, F.lit(10)) + F.floor(c.cast("int") / 5)).otherwise(c.cast("int")).cast("int")
    return F.aggregate(F.transform(F.filter(back, lambda c: c != ""), worth), F.lit(0), lambda a, x: a + x)


def _let(x: Column, use) -> Column:
    """``use`` of a value that is worked out once."""
    return F.element_at(F.transform(F.array(x), use), 1)


def _name_word(value: Column, key: str, attempt: Column) -> Column:
    """The surrogate of a word of a name, with the mark that the word has."""
    mark, word, gender = F.substring_index(value, ":", 1), F.regexp_replace(value, "^[^:]*:", ""), F.substring(value, 3, 1)
    salt, more = F.concat_ws("|", mark, attempt.cast("string")), F.greatest(attempt - 2, F.lit(0))
    script = F.lit("Latin")
    for name in (*[n for n in SYLLABLES if n != "Latin"], *CHARACTERS):
        script = F.when(word.rlike(rf"\p{{Is{name}}}"), name).otherwise(script)
    number = lambda part, size: F.pmod(_draw(key, salt, part, word), size).cast("int")

    def made(script: Column) -> Column:
        def own(options: dict[str, str]) -> Column:
            out = F.lit("")
            for name, text in options.items():
                out = F.when(script == name, text).otherwise(out)
            return out

        def of_gender(of) -> Column:
            return F.when(gender == "m", own(of("m"))).when(gender == "f", own(of("f"))).otherwise(own(of("a")))

        # later draws add syllables or characters: one alphabet has few short names
        parts = F.split(own({n: " ".join(v) for n, v in SYLLABLES.items()}), " ")
        spelt = lambda n: F.array_join(F.transform(F.sequence(F.lit(1), n + more), lambda i: F.get(parts, number(F.concat(F.lit("s"), i), F.size(parts)))), "")
        names = of_gender(lambda g: {n: " ".join(x for h in ("mf" if g == "a" else g) for x in GIVEN[h, n]) for n in ENDINGS})
        listed = _let(F.split(names, " "), lambda list_: F.get(list_, number(F.lit("g"), F.size(list_))))
        ending = of_gender(lambda g: {n: e.get(g, "") for n, e in ENDINGS.items()})
        given = F.when((attempt < 2) & (names != ""), listed).otherwise(F.initcap(F.concat(spelt(F.lit(2)), ending)))
        begin, rest = (own({n: v[k] for n, v in CHARACTERS.items()}) for k in (0, 1))
        one = lambda text, i: F.substr(text, number(i.cast("string"), F.length(text)) + 1, F.lit(1))
        characters = F.array_join(F.transform(F.sequence(F.lit(1), F.length(word) + more), lambda i: F.when(i == 1, one(begin, i)).otherwise(one(rest, i))), "")
        return F.when(begin != "", characters).when(mark == _SURNAME, F.initcap(spelt(F.lit(4)))).otherwise(given)

    return F.concat(mark, F.lit(":"), _let(script, made))


def _words(m: Column, genders: Column) -> Column:
    """The words of a name in order, as struct(value, word): the value is null for a particle."""
    rest = _rest(m)
    known = F.element_at(genders, rest)
    gender = F.when(known.isNotNull(), known).otherwise(_gender(m))
    words = F.split(rest, " ")
    mark = lambda i: F.when(i == F.size(words) - 1, F.lit(_SURNAME)).otherwise(F.concat(F.lit(_GIVEN), gender))
    return F.transform(words, lambda w, i: F.struct(F.when(~w.rlike(f"^(?:{PARTICLES})$"), F.concat(mark(i), F.lit(":"), F.lower(w))).alias("value"), w.alias("word")))


def values_of(m: Column, genders: Column) -> Column:
    """What is drawn for an entity: the words of a name, else itself."""
    words = F.filter(F.transform(_words(m, genders), lambda w: w["value"]), lambda v: v.isNotNull())
    return F.when(_is_name(m), words).otherwise(F.array(m))


def replacement(m: Column, genders: Column, key: str, draws: Column) -> Column:
    """The entity's surrogate at the draws that are settled."""
    attempt = lambda v: F.coalesce(F.element_at(draws, v), F.lit(0))

    def one(w: Column) -> Column:
        new = F.regexp_replace(_name_word(w["value"], key, attempt(w["value"])), "^[^:]*:", "")
        shout = (F.length(w["word"]) > 1) & (F.upper(w["word"]) == w["word"]) & (F.lower(w["word"]) != w["word"])
        return F.when(w["value"].isNull(), w["word"]).when(shout, F.upper(new)).otherwise(new)

    name = F.concat(F.regexp_extract(m, f"^{_TITLE}", 0), F.array_join(F.transform(_words(m, genders), one), " "))
    return F.when(_is_name(m), name).otherwise(surrogate(m, key, attempt(m)))


def _check_digits(country: Column, account: Column) -> Column:
    """Two digits that make the number 1 modulo 97, letters counting from 10."""
    worth = lambda c: F.when(c.rlike("^[0-9]$"), c.cast("int")).otherwise(F.ascii(c) - 55)
    step = lambda acc, c: F.pmod(acc * F.when(c.rlike("^[0-9]$"), 10).otherwise(100) + worth(c), F.lit(97))
    whole = F.filter(F.split(F.concat(account, country, F.lit("00")), ""), lambda c: c != "")
    return F.lpad((98 - F.aggregate(whole, F.lit(0), step)).cast("string"), 2, "0")


def surrogate(m: Column, key: str, attempt: Column) -> Column:
    """The replacement of an entity, or of a marked word of a name, at a draw; equal ones have equal replacements."""
    return _let(kind_of(m), lambda kind: _of_kind(m, kind, key, attempt))


def _of_kind(m: Column, kind: Column, key: str, attempt: Column) -> Column:
    salt = F.concat_ws("|", kind, attempt.cast("string"))
    digits = F.regexp_replace(m, "[^0-9]", "")
    octets = F.split(m, r"\.")
    words = _feistel(*[F.get(octets, F.lit(k)).cast("bigint") * 256 + F.get(octets, F.lit(k + 1)).cast("bigint") for k in (0, 2)], F.lit(65536).cast("bigint"), F.lit(65536).cast("bigint"), key, salt)
    ip = F.aggregate(F.array(words), F.lit(""), lambda _, o: F.concat_ws(".", F.floor(o["h"] / 256).cast("string"), F.pmod(o["h"], F.lit(256)).cast("string"), F.floor(o["l"] / 256).cast("string"), F.pmod(o["l"], F.lit(256)).cast("string")))
    # the issuer's first digit stays, and a right check digit becomes a right check digit
    body = F.substr(digits, F.lit(2), F.length(digits) - 2)
    with_check = F.aggregate(F.array(F.concat(F.substr(digits, F.lit(1), F.lit(1)), _digits_permuted(body, key, salt))), F.lit(""), lambda _, b: F.concat(b, F.pmod(F.lit(10) - F.pmod(_luhn_sum(b, True), F.lit(10)), F.lit(10)).cast("string")))
    plain = F.concat(F.substr(digits, F.lit(1), F.lit(1)), _digits_permuted(F.substr(digits, F.lit(2)), key, F.concat_ws("|", salt, F.lit("x"))))
    card = _refill(m, F.when(F.pmod(_luhn_sum(digits, False), F.lit(10)) == 0, with_check).otherwise(plain))
    country = F.regexp_extract(m, r"^\+[0-9]{1,3}(?=[ .(-])|^\+[0-9]", 0)
    rest = F.substr(m, F.length(country) + 1)
    phone = F.concat(country, _refill(rest, _digits_permuted(F.regexp_replace(rest, "[^0-9]", ""), key, F.concat_ws("|", salt, country))))
    user, host = F.substring_index(m, "@", 1), F.substring_index(m, "@", -1)
    zone = F.substring_index(host, ".", -1)
    more = F.when(attempt >= 3, F.substring(F.sha2(F.concat_ws("|", F.lit(key), m, salt), 256), 1, 6)).otherwise("")  # a short name has few draws
    email = F.concat(_same_class(user, key, F.concat_ws("|", salt, host)), more, F.lit("@"), _same_class(F.substr(host, F.lit(1), F.length(host) - F.length(zone)), key, F.lit("host")), zone)
    account = _same_class(F.substr(m, F.lit(5)), key, F.concat_ws("|", salt, F.substring(m, 1, 4)))
    iban = F.aggregate(F.array(account), F.lit(""), lambda _, a: F.concat(F.substring(m, 1, 2), _check_digits(F.substring(m, 1, 2), F.regexp_replace(a, " ", "")), a))
    ssn = _refill(m, _digits_permuted(digits, key, salt))
    return F.when(kind == "email", email).when(kind == "iban", iban).when(kind == "ip", ip).when(kind == "ssn", ssn).when(kind == "phone", phone).when(kind == "card", card).otherwise(_name_word(m, key, attempt))


def resolve(found: DataFrame, key: str, most: int = 12) -> DataFrame:
    """value and attempt (over 0) of the entities whose first draws met another's surrogate or entity.

    ``found`` has one row for each distinct value. Rounds go on until nothing
    meets; only ``most`` rounds in a row without fewer values that move are an error.
    """
    # few bytes, much work: as many tasks as there are shuffle partitions
    found = found.repartition(int(found.sparkSession.conf.get("spark.sql.shuffle.partitions")), "value")
    state = durable(found.select("value", F.lit(0).alias("attempt")).withColumn("s", surrogate(F.col("value"), key, F.col("attempt"))))
    least, idle = None, 0
    while idle < most:
        # the smallest value keeps its draw; a surrogate that somebody really has moves in any case
        first = state.groupBy("s").agg(F.min("value").alias("owner"), F.count(F.lit(1)).alias("n")).where("n > 1").select("s", "owner")
        real = state.select(F.col("value").alias("s")).withColumn("taken", F.lit(True))
        met = state.join(first, "s", "left").join(real, "s", "left").select("value", "attempt", "s", (F.coalesce("taken", F.lit(False)) | (F.col("owner") != F.col("value"))).alias("moves"))
        met = durable(met.withColumn("moves", F.coalesce("moves", F.lit(False))))
        n = met.where("moves").count()
        if not n:
            return state.where("attempt > 0").select("value", "attempt")
        least, idle = (n, 0) if least is None or n < least else (least, idle + 1)
        # a column of its own: inside a lambda a new column's name hides the old one of the same select
        met = met.withColumn("next", F.col("attempt") + F.col("moves").cast("int"))
        state = durable(met.select("value", F.col("next").alias("attempt"), F.when(F.col("moves"), surrogate(F.col("value"), key, F.col("next"))).otherwise(F.col("s")).alias("s")))
    raise RuntimeError("surrogates keep meeting; the formats leave too few draws")


def pseudonymise(docs: DataFrame, key: str, text: str = "text") -> DataFrame:
    """``docs`` with the text rewritten and n_entities, n_distinct.

    Null stays null with no entity. Equal entities are replaced alike in all
    rows, different ones differently, and no surrogate is an entity of the
    table; names are compared word by word, without regard to case. Names in
    scripts that have no list here get Latin ones. Texts of any length are read
    whole, an empty table gives no row. Columns with the names of the results
    are replaced, others kept.
    """
    kept = [c for c in docs.columns if c not in ("n_entities", "n_distinct")]
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in kept]).alias("row"), F.col(f"`{text}`").cast("string").alias("body"))
    values = lambda found, genders: F.flatten(F.transform(found, lambda m: values_of(m, genders)))
    # the outer form keeps the search from being done once more as a filter
    each = with_entities(rows.select("body"), "body").select("found", F.explode_outer(values(F.col("found"), F.col("genders"))).alias("value")).where("value IS NOT NULL")
    moved = durable(resolve(each.select("value").distinct(), key))
    rows = with_entities(rows, "body")
    if moved.limit(INLINE + 1).count() <= INLINE:
        out = _put(rows, key, F.from_json(F.lit(json.dumps({r.value: r.attempt for r in moved.collect()})), "map<string,int>"))
    else:
        # texts without an entity take no part in the join
        own = each.join(moved, "value").groupBy(F.col("found").alias("own")).agg(F.map_from_entries(F.collect_set(F.struct("value", "attempt"))).alias("draws"))
        some = rows.where(F.size("found") > 0).join(own, F.col("found") == F.col("own"), "left")
        out = _put(some, key, F.coalesce("draws", F.create_map().cast("map<string,int>"))).unionByName(_put(rows.where(F.coalesce(F.size("found"), F.lit(0)) <= 0), key, F.create_map().cast("map<string,int>")))
    return out.select(*[F.col("body").alias(c) if c == text else F.col(f"row.`{c}`").alias(c) for c in kept], "n_entities", "n_distinct")


def _put(rows: DataFrame, key: str, draws: Column) -> DataFrame:
    """row, the text with its surrogates as body, and the counts."""
    body, found = F.col("body"), F.col("found")
    gaps = F.when(F.col("again").isNull(), F.split(body, ANY, -1)).otherwise(F.split(body, F.col("again"), -1))
    new = F.transform(found, lambda m: replacement(m, F.col("genders"), key, draws))
    put = F.concat_ws("", F.flatten(F.zip_with(gaps, new, lambda g, s: F.array(g, F.coalesce(s, F.lit(""))))))
    size = lambda x: F.greatest(F.coalesce(F.size(x), F.lit(0)), F.lit(0)).cast("bigint")
    return rows.select("row", F.when(F.size(found) > 0, put).otherwise(body).alias("body"), size(found).alias("n_entities"), size(F.array_distinct(found)).alias("n_distinct"))


#: The key of the registered query; a user gives their own and keeps it secret.
DEMO_KEY = "rotate-this-key"


def op6_keyed_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return pseudonymise(docs, DEMO_KEY).select("doc_id", "text", "n_entities", "n_distinct")
