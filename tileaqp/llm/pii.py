"""Personal data: found entities get keyed surrogates of the same kind and format.

One regular expression finds e-mail addresses, secrets, bank accounts, phone numbers,
social security numbers, card numbers, network addresses and titled names. Mentions are
brought to a canonical form (case and separators removed); a surrogate is derived
from a keyed digest of kind and canonical form, so the same entity gets the same
surrogate in every document, and is then written in the format of each mention: its
separators, letter case and script. Card numbers keep their network digit and whether
their check digit is right.

A name is a surname and maybe a given name, each an entity of its own, without its
title: whoever shares a surname in the text shares its surrogate, with any title and in any case. A
given name's gender is that of the titles it is seen with, else of a short list; the
surrogate has the same. Surnames of Cyrillic and Greek script end by the mention's gender.
Names without a title aren't found.

Surrogates of all distinct entities are compared: if two entities got the same one,
or one that is itself an entity of the input, all but the smallest draw again with
the next attempt, until all differ. Names get a syllable more with every attempt,
and from ``LONGER`` attempts on all kinds a digit more, so that no format runs out. Only distinct
entities are shuffled for this. Texts are scanned once for their mentions, which are kept
in a durable table by the text's digest; texts without a hint of an entity are not scanned further.

Null and empty texts stay. Texts count whole. Repeated rows and copies are replaced
alike; other columns, whatever their names, stay. An empty table gives an empty
result. Only DataFrame expressions are used.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from ..runtime import durable

#: Titles that show a gender, and those that don't, and the letters they start with.
MALE = "Mr|Mister|Sir|Herr|Señor|Monsieur|Господин|Κύριος"
FEMALE = "Mrs|Ms|Miss|Madam|Frau|Señora|Señorita|Madame|Mme|Mlle|Госпожа|Κυρία"
NEUTRAL = "Dr|Prof"
INITIALS = "MSHFDPГΚ"
#: Given names whose gender is known without a title, lower case.
MALE_NAMES = "adam alexander andreas anton boris carlos daniel david dimitri erik felix georg hans henry igor ivan jack james jan jean john jose juan karl lars lucas luis marco mark martin max michael miguel nikos oscar otto paul pedro peter pierre robert stefan thomas victor walter william".split()
FEMALE_NAMES = "ada alice amelia anna barbara carla carmen clara claire elena eleni elisabeth emily emma eva helen ines ingrid irene isabel jane johanna julia karin katarina laura linda lucia maria marie marta mary nina olga paula petra rosa sara sofia sophie susan teresa ursula vera".split()

_WORD = r"\p{Lu}(?:\p{L}++|(?=['’-]))(?:['’-]\p{Lu}\p{L}++)*+"
_TITLE = rf"(?=[{INITIALS}])(?:{MALE}|{FEMALE}|{NEUTRAL})\.? "
#: Kinds and how their mentions look. The first that matches at a place wins.
KINDS = {
    "email": r"(?<![\p{L}\p{N}._%+-])[\p{L}\p{N}._%+-]{1,64}+@[\p{L}\p{N}-]{1,63}(?:\.[\p{L}\p{N}-]{1,63})+",
    "secret": r"(?<![0-9A-Za-z])(?:(?=[a-fA-F]*[0-9])[0-9a-fA-F]{32,}|(?:AKIA|ASIA)[0-9A-Z]{16}|(?:sk|pk|ghp|gho)[-_][0-9A-Za-z]{16,})(?![0-9A-Za-z])",
    "iban": r"(?<![0-9A-Za-z])[A-Z]{2}[0-9]{2}(?: ?[0-9A-Z]{4}){3,7}(?: ?[0-9A-Z]{1,3})?(?![0-9A-Za-z])",
    "phone": r"\+[0-9]{1,3}[ .-]?\(?[0-9]{2,4}\)?(?:[ .-]?[0-9]{2,4}){2,4}(?![0-9]|\.[0-9])|\([0-9]{3}\) ?[0-9]{3}-[0-9]{4}(?![0-9])|(?<![0-9-])[0-9]{3}-[0-9]{3}-[0-9]{4}(?![0-9])",
    "ssn": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9])",
    "card": r"(?<![0-9])[0-9](?:[ -]?[0-9]){14,15}(?![0-9])",
    "ip": r"(?<![0-9A-Za-z])(?<![0-9]\.)(?:(?:25[0-5]|2[0-4][0-9]|[01]?[0-9]?[0-9])\.){3}(?:25[0-5]|2[0-4][0-9]|[01]?[0-9]?[0-9])(?!\.?[0-9])",
    "ip6": r"(?<![0-9A-Za-z:.])(?:(?:[0-9a-fA-F]{1,4}:){7}[0-9a-fA-F]{1,4}|(?:[0-9a-fA-F]{1,4}:){1,6}(?::[0-9a-fA-F]{1,4}){1,6})(?![0-9A-Za-z:])",
    "name": rf"(?<!\p{{L}}){_TITLE}{_WORD}(?: (?!{_TITLE}){_WORD})?",
}
ANY = "|".join(f"(?:{p})" for p in KINDS.values())
#: A text without these has no entity; cheap to look for.
HINT = rf"[0-9@]|(?=[spgA{INITIALS}])(?:(?:sk|pk|ghp|gho)[-_]|AKIA|ASIA|(?:{MALE}|{FEMALE}|{NEUTRAL})\.? \p{{Lu}})"
#: Attempts after which a surrogate may be longer than what it stands for.
LONGER = 8

#: Fixed consonants and vowels of made-up names, by script; 16 and 4, chosen by six bits.
SYLLABLES = {
    "latin": ("b d f g h j k l m n p r s t v w".split(), "a e i o".split()),
    "cyrillic": ("б д ф г х ж к л м н п р с т в з".split(), "а е и о".split()),
    "greek": ("β δ φ γ χ ζ κ λ μ ν π ρ σ τ θ ψ".split(), "α ε ι ο".split()),
}


def kind_of(mention: Column) -> Column:
    out = F.lit("name")
    for name, pattern in reversed(list(KINDS.items())[:-1]):
        out = F.when(mention.rlike(f"^(?:{pattern})$"), F.lit(name)).otherwise(out)
    return out


def script_of(value: Column) -> Column:
    return F.when(value.rlike(r"\p{IsCyrillic}"), "cyrillic").when(value.rlike(r"\p{IsGreek}"), "greek").otherwise("latin")


def canonical(kind: Column, mention: Column) -> Column:
    """The entity of a mention; of a name its surname's stem."""
    digits = F.regexp_replace(mention, "[^0-9]", "")
    surname = F.translate(F.lower(F.regexp_extract(mention, r"([^ ]+)$", 1)), "άέήίόύώ", "αεηιουω")
    stem = F.regexp_replace(F.regexp_replace(surname, "(ов|ев|ин)а$", "$1"), "(ος|ου)$", "")
    return (
        F.when(kind.isin("phone", "ssn", "card"), digits)
        .when(kind == "iban", F.replace(mention, F.lit(" "), F.lit("")))
        .when(kind == "name", stem)
        .when((kind == "secret") & ~mention.rlike("^[0-9a-fA-F]+$"), mention)
        .otherwise(F.lower(mention))
    )


def given_name(mention: Column) -> Column:
    """The given name of a name's mention in lower case; null without one."""
    return F.nullif(F.lower(F.regexp_extract(mention, rf"^{_TITLE}({_WORD}) ", 1)), F.lit(""))


def gender(mention: Column) -> Column:
    """The gender that a title shows: m, f or n."""
    return F.when(mention.rlike(rf"^(?:{MALE})\.? "), F.lit("m")).when(mention.rlike(rf"^(?:{FEMALE})\.? "), F.lit("f")).otherwise(F.lit("n"))


def genders_of_names(mentions: DataFrame) -> DataFrame:
    """(given, sex): of each given name in (given, shown)."""
    seen = mentions.filter("given is not null").groupBy("given").agg(F.bool_or(F.col("shown") == "m").alias("m"), F.bool_or(F.col("shown") == "f").alias("f"))
    listed = F.when(F.col("given").isin(MALE_NAMES), "m").when(F.col("given").isin(FEMALE_NAMES), "f").otherwise("n")
    return seen.select("given", F.when(F.col("m") & ~F.col("f"), "m").when(F.col("f") & ~F.col("m"), "f").otherwise(listed).alias("sex"))


def _syllables(digest: Column, script: Column, first: int, n: Column) -> Column:
    """``n`` syllables from the hexadecimal digits from ``first`` on, two digits each."""

    def pick(i: Column) -> Column:
        byte = F.conv(digest.substr(2 * i + first, F.lit(2)), 16, 10).cast("int")
        out = F.lit(None).cast("string")
        for name, (consonants, vowels) in SYLLABLES.items():
            out = F.when(script == name, F.concat(F.array(*map(F.lit, consonants))[byte.bitwiseAND(F.lit(15))], F.array(*map(F.lit, vowels))[F.shiftright(byte, 4).bitwiseAND(F.lit(3))])).otherwise(out)
        return out

    return F.array_join(F.transform(F.sequence(F.lit(0), n - 1), pick), "")


def _luhn(digits: Column) -> Column:
    """Sum of the check over all digits, the last one not doubled."""
    n = F.length(digits)

    def part(i: Column) -> Column:
        d = digits.substr(n - i, F.lit(1)).cast("int")
        twice = d * 2
        return F.when(i % 2 == 0, d).otherwise(F.when(twice > 9, twice - 9).otherwise(twice))

    return F.aggregate(F.transform(F.sequence(F.lit(0), n - 1), part), F.lit(0), lambda a, x: a + x) % 10


def surrogate(kind: Column, value: Column, attempt: Column, key: str) -> Column:
    """The canonical surrogate of a canonical entity; ``key`` is the secret that makes it hard to guess."""
    digest = F.sha2(F.concat_ws("|", F.lit(key), kind, value, attempt.cast("string")), 256)
    more = F.concat(digest, F.sha2(F.concat(digest, F.lit("+")), 256))
    number = F.translate(more, "abcdef", "173905")
    n = F.length(value)
    drawn = F.concat(F.when(kind == "ssn", F.lit("9")).otherwise(value.substr(F.lit(1), F.lit(1))), number.substr(F.lit(1), n - 1))
    body = drawn.substr(F.lit(1), n - 1)
    right = ((10 - _luhn(F.concat(body, F.lit("0")))) % 10).cast("string")
    card = F.concat(body, F.when(_luhn(value) == 0, right).when(F.substring(number, 40, 1) == right, ((right.cast("int") + 1) % 10).cast("string")).otherwise(F.substring(number, 40, 1)))
    octet = lambda i: F.conv(F.substring(digest, i, 2), 16, 10)
    address = F.concat_ws(".", (F.conv(F.substring(digest, 1, 2), 16, 10).cast("int") % 99 + 100).cast("string"), octet(3), octet(5), octet(7))
    places = F.length(F.replace(value, F.lit(":"), F.lit("")))
    address6 = F.concat(F.lit("2"), more.substr(F.lit(1), places - 1))
    domain = F.sha2(F.concat_ws("|", F.lit(key), F.lit("domain"), F.regexp_extract(value, "@(.*)$", 1)), 256)
    latin = F.lit("latin")
    mail = F.concat(_syllables(digest, latin, 1, F.lit(3)), F.lit("."), F.substring(number, 20, 4), F.lit("@"), _syllables(domain, latin, 1, F.lit(3)), F.substring(domain, 9, 2), F.lit(".example."), F.regexp_extract(value, r"([^.]*)$", 1))
    long_hex = F.repeat(more, F.greatest(F.lit(1), F.ceil(n / 128).cast("int"))).substr(F.lit(1), n)
    prefix = F.regexp_extract(value, r"^(AKIA|ASIA|(?:sk|pk|ghp|gho)[-_])", 1)
    hexadecimal = value.rlike("^[0-9a-f]+$")
    secret = F.when(hexadecimal, long_hex).otherwise(F.concat(prefix, F.when(prefix.rlike("^A"), F.upper(long_hex)).otherwise(long_hex).substr(F.lit(1), n - F.length(prefix))))
    script = script_of(value)
    surname = _syllables(digest, script, 1, F.least(attempt + 4, F.lit(30)))
    sex = F.substring(value, -1, 1)
    ending = F.when(script == "cyrillic", F.when(sex == "f", "на").otherwise("н")).when(script == "greek", F.when(sex == "f", "να").otherwise("νος")).otherwise(F.when(sex == "f", "na").when(sex == "m", "n").otherwise("l"))
    given = F.concat(_syllables(digest, script, 1, F.least(attempt + 3, F.lit(30))), ending)
    made = (
        F.when(kind.isin("phone", "ssn"), drawn).when(kind == "card", card).when(kind == "ip", address).when(kind == "ip6", address6).when(kind == "email", mail).when(kind == "secret", secret)
        .when(kind == "iban", F.concat(F.substring(value, 1, 2), number.substr(F.lit(1), n - 2))).when(kind == "given", given).otherwise(surname)
    )
    return F.when(attempt >= LONGER, F.concat(made, number.substr(F.lit(60), attempt - (LONGER - 1)))).otherwise(made)


def _cased(mention: Column, made: Column) -> Column:
    """A name in the letter case of what it replaces."""
    return F.when((mention == F.upper(mention)) & (F.length(mention) > 1), F.upper(made)).otherwise(F.initcap(made))


def render(kind: Column, mention: Column, made: Column, given: Column | None = None, sex: Column | None = None) -> Column:
    """``made`` in the format of ``mention``: separators of digits, upper case, the title before a name, the gender's ending after it."""

    def character(c: Column, i: Column) -> Column:
        before = F.length(F.regexp_replace(mention.substr(F.lit(1), i), "[ .()+:-]", ""))
        return F.when(c.rlike(r"^[ .()+:-]$"), c).otherwise(made.substr(before + 1, F.lit(1)))

    digits = F.length(F.regexp_replace(mention, "[ .()+:-]", ""))
    spaced = F.concat(F.array_join(F.transform(F.split(mention, ""), character), ""), made.substr(digits + 1, F.lit(99)))
    shout = mention == F.upper(mention)
    title = F.regexp_extract(mention, rf"^({_TITLE})", 1)
    first, last = F.regexp_extract(mention, rf"^{_TITLE}({_WORD}) ", 1), F.regexp_extract(mention, r"([^ ]+)$", 1)
    lower, script = F.lower(last), script_of(last)
    shown = gender(mention)
    known = F.when(shown != "n", shown).when(sex.isin("m", "f"), sex) if sex is not None else F.when(shown != "n", shown)
    female = F.coalesce(known == "f", lower.rlike("(ова|ева|ина|ου)$"))
    ending = F.when(script == "cyrillic", F.when(female, "ова").otherwise("ов")).when(script == "greek", F.when(female, "ου").otherwise("ος")).otherwise("")
    person = F.concat(title, F.when(first != "", F.concat(_cased(first, given), F.lit(" "))).otherwise("") if given is not None else F.lit(""), _cased(last, F.concat(made, ending)))
    return (
        F.when(kind.isin("phone", "ssn", "card", "iban", "ip6"), F.when((kind == "ip6") & shout, F.upper(spaced)).otherwise(spaced))
        .when(kind == "name", person)
        .when(kind.isin("email", "secret") & shout, F.upper(made))
        .otherwise(made)
    )


def distinct_surrogates(entities: DataFrame, key: str) -> DataFrame:
    """(kind, value, made) for distinct (kind, value): no two alike within a kind, none an entity itself."""
    entities = durable(entities.select("kind", "value").distinct(), "entities")
    drawn = entities.withColumn("attempt", F.lit(0))
    while True:
        drawn = durable(drawn.withColumn("made", surrogate(F.col("kind"), F.col("value"), F.col("attempt"), key)), "drawn")
        clash = drawn.groupBy("kind", "made").agg(F.min("value").alias("first"), F.count("*").alias("n")).filter("n > 1").drop("n")
        real = drawn.select("kind", "made").distinct().join(entities.select("kind", F.regexp_replace("value", "/[mfn]$", "").alias("made")), ["kind", "made"], "left_semi")
        again = clash.join(real.withColumn("real", F.lit(True)), ["kind", "made"], "full").select("kind", "made", "first", "real")
        again = durable(again, "again")
        if again.isEmpty():
            return drawn.select("kind", "value", "made")
        # where the surrogate is an entity everyone draws again, else all but the first
        stays = F.col("value").eqNullSafe(F.col("first")) & F.col("real").isNull()
        drawn = drawn.join(again.withColumn("hit", F.lit(True)), ["kind", "made"], "left").select(
            "kind", "value", (F.col("attempt") + F.when(F.col("hit") & ~stays, 1).otherwise(0)).alias("attempt")
        )


def surrogates(mentions: DataFrame, key: str) -> DataFrame:
    """(mention, new) for the distinct ``mention`` of the input: what each is replaced by."""
    mention, kind = F.col("mention"), F.col("kind")
    named = kind == "name"
    mentions = mentions.withColumn("kind", kind_of(mention)).withColumn("value", canonical(kind, mention))
    mentions = durable(mentions.withColumn("given", F.when(named, given_name(mention))).withColumn("shown", F.when(named, gender(mention))), "mentions")
    sexes = genders_of_names(mentions)
    mentions = mentions.join(sexes, "given", "left").withColumn("given", F.concat("given", F.lit("/"), "sex"))
    mentions = durable(mentions, "mentions")
    givens = mentions.filter("given is not null").select(F.lit("given").alias("kind"), F.col("given").alias("value"))
    made = distinct_surrogates(mentions.select("kind", "value").unionByName(givens), key)
    first = made.filter("kind = 'given'").select(F.col("value").alias("given"), F.col("made").alias("made_given"))
    full = mentions.join(made, ["kind", "value"]).join(first, "given", "left")
    return full.select("mention", render(kind, mention, F.col("made"), F.col("made_given"), F.col("sex")).alias("new"))


def replace(docs: DataFrame, key: str, text: str = "text", count: str | None = "n_entities") -> DataFrame:
    """``docs`` with every entity in ``text`` replaced; ``count`` names a column for how many there were."""
    own = "_pii_"
    while any(c.startswith(own) for c in docs.columns):
        own += "_"
    body = F.col(f"`{text}`").cast("string")
    found = F.regexp_extract_all(body, F.lit(f"({ANY})"), F.lit(1))
    hint = F.coalesce(body.rlike(HINT), F.lit(False))
    of = F.sha2(body, 256)
    each = durable(docs.filter(hint).select(of.alias("of"), F.array_distinct(found).alias("found")).filter(F.size("found") > 0).dropDuplicates(["of"]), "found")
    each = each.select("of", F.explode("found").alias("mention"))
    shown = durable(surrogates(each.select("mention").distinct(), key), "surrogates")
    maps = each.join(shown, "mention").groupBy(F.col("of").alias(own)).agg(F.map_from_entries(F.collect_list(F.struct("mention", "new"))).alias(own + "map"))
    clean = docs.filter(~hint | (F.size(found) == 0))
    hit = docs.filter(hint).withColumn(own + "n", F.size(found).cast("long")).filter(F.col(own + "n") > 0)
    # control characters mark the mentions; those of the text itself are written as two first
    plain = body
    for a, b in (("\x01", "\x01a"), ("\x02", "\x01b"), ("\x03", "\x01c")):
        plain = F.replace(plain, F.lit(a), F.lit(b))
    plain = F.when(body.rlike("[\x01-\x03]"), plain).otherwise(body)
    parts = F.split(F.regexp_replace(plain, f"({ANY})", "\x02$1\x03"), "\x02")
    pair = F.transform(F.slice(parts, 2, F.greatest(F.size(parts) - 1, F.lit(0))), lambda p: F.split(p, "\x03", 2))
    back = lambda m: F.when(m.contains("\x01"), m).otherwise(F.coalesce(F.col(own + "map")[m], m))
    done = F.concat(parts[0], F.array_join(F.transform(pair, lambda p: F.concat(back(p[0]), p[1])), ""))
    for a, b in (("\x03", "\x01c"), ("\x02", "\x01b"), ("\x01", "\x01a")):
        done = F.when(body.rlike("[\x01-\x03]"), F.replace(done, F.lit(b), F.lit(a))).otherwise(done)
    replaced = hit.withColumn(own, of).join(maps, own)
    names = [c for c in docs.columns if c != count]
    out = replaced.select(*[done.alias(c) if c == text else F.col(f"`{c}`") for c in names], F.col(own + "n"))
    out = clean.select(*(F.col(f"`{c}`") for c in names), F.lit(0).cast("long").alias(own + "n")).unionByName(out)
    return out.withColumnRenamed(own + "n", count) if count else out.drop(own + "n")
