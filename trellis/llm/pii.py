"""Surrogates for personal data [native]: keyed, type-consistent, distinct, coreferent.

Entities are found by one regular expression over the whole text; each is replaced, in the same
row, by a surrogate that a keyed function makes of its normal form. Equal entities thus get equal
surrogates everywhere (coreference) without a join, and formats are kept: digits stay digits in
their places, card numbers and IBANs keep valid check digits, hexadecimal secrets their length,
addresses their domain's identity, and titled names gender and script.

Digits are permuted by a keyed Feistel network, so distinct numbers of one format can't collide.
The other kinds are hashed; a check over all distinct entities, in every form a mention can take,
finds surrogates given twice, or equal to a real entity, and moves these to the function's next
attempt until none is left. Only
entities are shuffled for this, pre-aggregated; texts stay where they are unless one of theirs
had to be moved.

Nulls: a null text stays null and has no entities. Empty tables stay empty; repeated rows are
treated alike; texts have any length. Of entities with one surrogate (a tie) the least keeps it.
All other columns are passed on by `surrogates`.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import checkpointed, let_go, spread_join, written

#: Key of the registered query; real uses pass a secret of their own.
DEMO_KEY = "replace-this-key"
ROUNDS = 8
#: Attempts for an entity before it is an error.
MOST_ATTEMPTS = 50
#: Letters of an e-mail surrogate's local part and domain.
LOCAL, DOMAIN = 12, 10

# Titles that show a gender, given names by gender and script, and syllables of surnames.
TITLES = {
    "m": ("Mr", "Herr", "Monsieur", "M", "Señor", "Sr", "Don", "господин", "г-н", "κύριος", "κ"),
    "f": ("Mrs", "Ms", "Miss", "Frau", "Madame", "Mme", "Mlle", "Señora", "Sra", "Doña", "госпожа", "г-жа", "κυρία", "κα"),
}
GIVEN = {
    ("m", "latin"): ("Adam", "Bruno", "Carl", "David", "Emil", "Felix", "Georg", "Hugo", "Ivan", "Jonas", "Karim", "Leon", "Marco", "Noel", "Oscar", "Paul"),
    ("f", "latin"): ("Alma", "Bella", "Clara", "Dora", "Elena", "Flora", "Greta", "Helen", "Irma", "Julia", "Karin", "Laura", "Maria", "Nora", "Olga", "Paula"),
    ("m", "cyrillic"): ("Антон", "Борис", "Вадим", "Глеб", "Денис", "Егор", "Иван", "Кирилл", "Лев", "Марк", "Олег", "Павел", "Роман", "Семён", "Тимур", "Юрий"),
    ("f", "cyrillic"): ("Анна", "Вера", "Галина", "Дарья", "Ева", "Жанна", "Зоя", "Ирина", "Клара", "Лидия", "Мария", "Нина", "Ольга", "Полина", "Раиса", "Софья"),
    ("m", "greek"): ("Άρης", "Βασίλης", "Γιώργος", "Δήμος", "Ηλίας", "Θωμάς", "Κώστας", "Λουκάς", "Μάριος", "Νίκος", "Ορέστης", "Πέτρος", "Σπύρος", "Τάσος", "Φώτης", "Χάρης"),
    ("f", "greek"): ("Άννα", "Βάσω", "Γιάννα", "Δάφνη", "Ελένη", "Ζωή", "Ηρώ", "Θάλεια", "Ιωάννα", "Κλειώ", "Λένα", "Μαρία", "Νίκη", "Όλγα", "Ρένα", "Σοφία"),
}
SYLLABLES = {
    "latin": ("ba", "de", "fi", "go", "hu", "ka", "le", "mi", "no", "pu", "ra", "se", "ti", "vo", "wu", "za"),
    "cyrillic": ("ба", "де", "фи", "го", "ху", "ка", "ле", "ми", "но", "пу", "ра", "се", "ти", "во", "жу", "за"),
    "greek": ("βα", "δε", "φι", "γο", "χου", "κα", "λε", "μι", "νο", "που", "ρα", "σε", "τι", "βο", "ψυ", "ζα"),
}
SURNAME_END = {"latin": "n", "cyrillic": "ко", "greek": "κης"}

# --- what is found ----------------------------------------------------------------------------------

OCTET = "(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
WORDS = r"\p{Lu}[\p{L}'’\-]*+(?: \p{Lu}[\p{L}'’\-]*+){0,2}"
PATTERNS = {
    # a name of 253 characters has 127 labels at most: the bound keeps the engine's stack small on any text
    "email": r"(?<![A-Za-z0-9._%+\-])[A-Za-z0-9._%+\-]++@[A-Za-z0-9\-]++(?:\.[A-Za-z0-9\-]++){0,126}\.[A-Za-z]{2,}",
    "access_key": r"(?<![A-Za-z0-9])(?:AKIA|ASIA)[A-Z0-9]{16}(?![A-Za-z0-9])",
    "secret": r"(?<![A-Za-z])(?i:password|passwd|pwd|secret|token|api[_\-]?key)\s{0,3}[=:]\s{0,3}[\"']?[A-Za-z0-9+/_\-]{8,}+",
    "ip": rf"(?<![0-9.])(?:{OCTET}\.){{3}}{OCTET}(?![0-9]|\.[0-9])",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])",
    "phone": r"(?<![0-9A-Za-z+])(?:\+[0-9]{1,3}(?:[ .\-]?\(?[0-9]{1,4}\)?){2,6}|(?:\([0-9]{3}\) ?|[0-9]{3}[ .\-])[0-9]{3}[ .\-][0-9]{4})(?![0-9A-Za-z])",
    "ssn": r"(?<![0-9\-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9\-])",
    "card": r"(?<![0-9.\-])[0-9](?:[ \-]?[0-9]){12,18}(?![0-9])",
    "name": rf"(?<!\p{{L}})(?:{'|'.join(t for g in TITLES.values() for t in sorted(g, key=len, reverse=True))})\.? {WORDS}",
}
#: One expression for all kinds; earlier kinds win where several begin at one place. None begins between two letters of a word.
ANY = f"(?<!(?=[A-Za-z]{{2}})[A-Za-z])(?:{'|'.join(f'(?:{p})' for p in PATTERNS.values())})"


def let(value: Column, use: Callable[[Column], Column]) -> Column:
    """Bind a value within an expression, so that it is computed once."""
    return F.transform(F.array(value), use)[0]


def number(hex_digits: Column) -> Column:
    return F.conv(F.substring(hex_digits, 1, 15), 16, 10).cast("long")


def keyed(key: str, *parts) -> Column:
    return F.sha2(F.concat_ws("|", F.lit(key), *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts]), 256)


def permuted(digits: Column, kind, key: str, attempt) -> Column:
    """A keyed permutation of the digit strings of each length up to 18: alternating Feistel rounds over two halves."""
    attempt = attempt if isinstance(attempt, Column) else F.lit(attempt)

    def of(d: Column) -> Column:
        n = F.length(d)
        left = F.floor(n / 2).cast("int")
        ten = lambda k: F.pow(F.lit(10.0), k).cast("long")
        start = F.struct(F.concat(F.lit("0"), F.substring(d, F.lit(1), left)).cast("long").alias("a"), F.concat(F.lit("0"), F.substring(d, left + 1, n)).cast("long").alias("b"))

        def turn(at: Column, r: Column) -> Column:
            odd = r % 2 == 1
            shift = number(keyed(key, kind, attempt, n, r, F.when(odd, at["b"]).otherwise(at["a"])))
            return F.struct(F.when(odd, (at["a"] + shift % ten(left)) % ten(left)).otherwise(at["a"]).alias("a"), F.when(odd, at["b"]).otherwise((at["b"] + shift % ten(n - left)) % ten(n - left)).alias("b"))

        end = F.aggregate(F.sequence(F.lit(1), F.lit(ROUNDS)), start, turn)
        return let(end, lambda x: F.concat(F.lpad(x["a"].cast("string"), left, "0"), F.lpad(x["b"].cast("string"), n - left, "0")))

    return let(digits, of)


def only_digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def refill(shape: Column, digits: Column) -> Column:
    """The shape with its digits replaced, one by one, by others."""
    return F.array_join(F.zip_with(F.split(shape, "[0-9]", -1), F.split(F.concat(digits, F.lit("")), ""), lambda gap, d: F.concat(gap, F.coalesce(d, F.lit("")))), "")


def luhn_sum(digits: Column) -> Column:
    """Sum of the digits, every second from the right doubled."""
    return F.aggregate(
        F.transform(F.split(F.reverse(digits), ""), lambda d, i: let(F.when(i % 2 == 1, d.cast("int") * 2).otherwise(d.cast("int")), lambda x: F.when(x > 9, x - 9).otherwise(x))),
        F.lit(0), lambda a, x: a + x,
    )


def mod97(text: Column) -> Column:
    """Remainder of an account number, its letters read as 10 to 35."""
    return F.aggregate(F.split(text, ""), F.lit(0), lambda a, c: F.when(c.rlike("[0-9]"), (a * 10 + F.ascii(c) - 48) % 97).otherwise((a * 100 + F.ascii(c) - 55) % 97))


def iban_parts(x: Column) -> Column:
    return F.replace(x, F.lit(" "), F.lit(""))


def kind_of(m: Column) -> Column:
    """The kind of a match; null where its check digits show that it isn't one."""
    whole = lambda k: m.rlike(rf"\A(?:{PATTERNS[k]})\z")
    out = F.lit(None).cast("string")
    valid = {
        "iban": mod97(F.concat(F.substring(iban_parts(m), F.lit(5), F.length(m)), F.substring(iban_parts(m), 1, 4))) == 1,
        "card": luhn_sum(only_digits(m)) % 10 == 0,
        "phone": F.length(only_digits(m)).between(7, 15),
    }
    for k in reversed(PATTERNS):
        fits = whole(k)
        out = F.when(fits & valid[k] if k in valid else fits, F.lit(k)).otherwise(out)
    return out


def script_of(x: Column) -> Column:
    return F.when(x.rlike(r"\p{IsCyrillic}"), "cyrillic").when(x.rlike(r"\p{IsGreek}"), "greek").otherwise("latin")


def bare_name(m: Column) -> Column:
    """A name without its title."""
    return F.regexp_replace(m, r"\A\S+ ", "")


def entity_of(m: Column, kind: Column) -> Column:
    """The normal form that coreferent mentions share."""
    return (
        F.when(kind == "email", F.lower(m))
        .when(kind.isin("card", "ssn", "phone"), F.concat(F.regexp_extract(m, r"\A(\+?)", 1), only_digits(m)))
        .when(kind == "iban", iban_parts(m))
        .when(kind == "secret", F.regexp_extract(m, r"([A-Za-z0-9+/_\-]+)\z", 1))
        .when(kind == "name", bare_name(m))
        .otherwise(m)
    )


# --- what replaces it -------------------------------------------------------------------------------


def letters(h: Column, n: int) -> Column:
    return F.translate(F.substring(h, 1, n), "0123456789abcdef", "abcdefghijklmnop")


def spelled(shape: Column, h: Column) -> Column:
    """Characters of the shape's kinds (lower, upper, digit), as many, chosen by repeated hashing."""
    stream = F.concat(*[F.sha2(F.concat(h, F.lit(str(k))), 256) for k in range(4)])
    hex_only = ~shape.rlike("[^0-9a-f]")

    def letter(c: Column, i: Column) -> Column:
        v = F.conv(F.substring(stream, (i * 2) % 255 + 1, F.lit(2)), 16, 10).cast("int")
        pick = lambda alphabet: F.substring(F.lit(alphabet), (v % len(alphabet)) + 1, F.lit(1))
        return F.when(hex_only, pick("0123456789abcdef")).when(c.rlike("[0-9]"), pick("0123456789")).when(c.rlike("[A-Z]"), pick("ABCDEFGHIJKLMNOPQRSTUVWXYZ")).when(c.rlike("[a-z]"), pick("abcdefghijklmnopqrstuvwxyz")).otherwise(c)

    return F.array_join(F.transform(F.split(shape, ""), letter), "")


def _choice(options: Column, n: Column) -> Column:
    return F.element_at(options, (n % F.size(options) + 1).cast("int"))


def person(m: Column, key: str, attempt: Column) -> Column:
    """Title kept; each given name by gender and script, the last word (the surname) by script.

    The place in the list of given names doesn't depend on the gender, so that names which are
    distinct under one title are distinct under every other.
    """
    title = F.regexp_extract(m, r"\A(\S+) ", 1)

    def of(x: Column) -> Column:
        def word(w: Column, i: Column) -> Column:
            def surname(h: Column) -> Column:
                # later attempts have longer surnames, so that there are enough of them
                syllables = F.when(attempt > 2, 10).when(attempt > 0, 6).otherwise(3)
                said = F.transform(F.sequence(F.lit(0), syllables - 1), lambda k: _choice(x["syllables"], F.conv(F.substring(h, 16 + 2 * k, F.lit(2)), 16, 10).cast("int")))
                return F.concat(F.initcap(F.array_join(said, "")), x["end"])

            def given(h: Column) -> Column:
                return _choice(x["given"], F.conv(F.substring(h, 1, 4), 16, 10).cast("int"))

            last = i == F.size(F.split(x["bare"], " ")) - 1
            return let(keyed(key, F.when(last, "surname").otherwise("given"), attempt, F.lower(w)), lambda h: F.when(last, surname(h)).otherwise(given(h)))

        return F.array_join(F.transform(F.split(x["bare"], " "), word), " ")

    def by(value: Column, options: dict) -> Column:
        out = F.lit(None)
        for k, v in options.items():
            out = F.when(value == k, F.array(*map(F.lit, v)) if isinstance(v, tuple) else F.lit(v)).otherwise(out)
        return out

    # what depends on gender and script is looked up once a name: expressions stay small, which the driver holds and analyses
    gender = F.when(F.regexp_replace(title, r"\.\z", "").isin(*TITLES["f"]), "f").otherwise("m")
    told = let(bare_name(m), lambda bare: let(script_of(bare), lambda script: let(
        F.struct(bare.alias("bare"), by(F.concat(gender, F.lit(" "), script), {" ".join(k): v for k, v in GIVEN.items()}).alias("given"), by(script, SYLLABLES).alias("syllables"), by(script, SURNAME_END).alias("end")), of)))
    return F.concat_ws(" ", title, told)


def surrogate(m: Column, kind: Column, key: str, attempt: Column | int = 0, local: int = LOCAL) -> Column:
    """The surrogate of a match of a kind, in the match's own format."""
    attempt = attempt if isinstance(attempt, Column) else F.lit(attempt)
    d = only_digits(m)
    card = F.concat(F.substring(d, 1, 1), permuted(F.substring(d, F.lit(2), F.length(d) - 2), "card", key, attempt))
    # the country stays: one digit of zones 1 and 7, else the first two, however the number is spaced
    lead = F.when(~F.startswith(m, F.lit("+")), 0).when(F.substring(d, 1, 1).isin("1", "7"), 1).otherwise(2)
    octets = F.transform(F.split(m, r"\."), lambda x: F.lpad(F.conv(x, 10, 16), 2, "0"))
    half = lambda a: F.conv(F.array_join(F.slice(octets, a, 2), ""), 16, 10).cast("long")
    mixed = F.aggregate(F.sequence(F.lit(1), F.lit(ROUNDS)), F.struct(half(1).alias("a"), half(3).alias("b")), lambda at, r: F.struct(at["b"].alias("a"), ((at["a"] + number(keyed(key, "ip", attempt, r, at["b"]))) % 65536).alias("b")))
    address = let(mixed, lambda x: F.concat_ws(".", *[(p % 256).cast("string") for p in (F.floor(x["a"] / 256), x["a"], F.floor(x["b"] / 256), x["b"])]))
    low = F.lower(m)
    domain = F.regexp_extract(low, r"@(.+)\z", 1)
    top = F.regexp_extract(domain, r"\.([a-z]+)\z", 1)
    email = F.concat(letters(keyed(key, "email", attempt, low), local), F.lit("@"), letters(keyed(key, "domain", domain), DOMAIN), F.when(top.isin("com", "net", "org"), F.concat(F.lit(".example."), top)).otherwise(F.lit(".example")))
    value = F.regexp_extract(m, r"([A-Za-z0-9+/_\-]+)\z", 1)
    secret = F.concat(F.substring(m, F.lit(1), F.length(m) - F.length(value)), spelled(value, keyed(key, "secret", attempt, value)))
    access = F.concat(F.substring(m, 1, 4), spelled(F.substring(m, 5, 16), keyed(key, "access_key", attempt, m)))
    plain = iban_parts(m)
    body = let(F.substring(plain, F.lit(5), F.length(plain)), lambda b: refill(b, _long_permuted(only_digits(b), key, attempt)))
    account = let(body, lambda b: F.concat(F.substring(plain, 1, 2), F.lpad((98 - mod97(F.concat(b, F.substring(plain, 1, 2), F.lit("00")))).cast("string"), 2, "0"), b))
    grouped = let(account, lambda a: F.when(m.contains(" "), F.trim(F.regexp_replace(a, "(.{4})", "$1 "))).otherwise(a))
    return (
        F.when(kind == "email", email)
        .when(kind == "access_key", access)
        .when(kind == "secret", secret)
        .when(kind == "ip", address)
        .when(kind == "iban", grouped)
        .when(kind == "phone", refill(m, F.concat(F.substring(d, F.lit(1), lead), permuted(F.substring(d, lead + 1, F.length(d)), "phone", key, attempt))))
        .when(kind == "ssn", refill(m, permuted(d, "ssn", key, attempt)))
        .when(kind == "card", refill(m, F.concat(card, ((10 - luhn_sum(F.concat(card, F.lit("0"))) % 10) % 10).cast("string"))))
        .when(kind == "name", person(m, key, attempt))
    )


def _long_permuted(d: Column, key: str, attempt: Column) -> Column:
    """Digit strings beyond 18: the first 18 permuted, then the rest, so distinct ones stay distinct."""
    return F.concat(permuted(F.substring(d, 1, 18), "iban", key, attempt), F.when(F.length(d) > 18, permuted(F.substring(d, F.lit(19), F.length(d)), "iban2", key, attempt)).otherwise(F.lit("")))


# --- the operator -----------------------------------------------------------------------------------


def matched(docs: DataFrame, text: str = "text") -> DataFrame:
    """Docs with `__found`: the (match, kind, entity) of every match, in order; kind is null for what isn't one."""
    found = F.transform(F.regexp_extract_all(F.col(text), F.lit(ANY), F.lit(0)), lambda m: let(kind_of(m), lambda k: F.struct(m.alias("m"), k.alias("kind"), entity_of(m, k).alias("entity"))))
    return docs.withColumn("__found", found)


def forms(m: Column, kind: Column, entity: Column, key: str, attempt: Column, local: int) -> Column:
    """Normal forms of all surrogates that an entity may get: a name's depends on its title's gender."""
    titled = F.transform(F.array(*[F.lit(f"{t[0]} ") for t in TITLES.values()]), lambda t: bare_name(person(F.concat(t, entity), key, attempt)))
    made = let(surrogate(m, kind, key, attempt, local), lambda s: entity_of(s, kind))
    return F.when(kind == "name", titled).otherwise(F.array(made))


def moved(found: DataFrame, key: str, local: int = LOCAL) -> DataFrame | None:
    """(kind, entity, attempt) of the entities that must leave their first surrogate; None if there are none.

    Every distinct entity is checked against all others, in all forms its surrogate can take: of
    those with one surrogate the least stays, and no surrogate may be a real entity of its kind.
    """
    every = found.select(F.explode("__found").alias("x")).where("x.kind is not null").groupBy("x.kind", "x.entity").agg(F.min("x.m").alias("m"))
    now = checkpointed(every.withColumn("attempt", F.lit(0)))
    made = F.explode(F.array_distinct(forms(F.col("m"), F.col("kind"), F.col("entity"), key, F.col("attempt"), local)))
    for k in range(MOST_ATTEMPTS):
        given = checkpointed(now.select("*", made.alias("made")))  # a long expression, analysed once a round
        turn = F.dense_rank().over(Window.partitionBy("kind", "made").orderBy("attempt", "entity"))
        real = now.select("kind", F.col("entity").alias("made"), F.lit(True).alias("real"))
        judged = given.withColumn("turn", turn).join(real, ["kind", "made"], "left").withColumn("again", (F.col("turn") > 1) | F.col("real").isNotNull())
        judged = checkpointed(judged.groupBy("kind", "entity", "m", "attempt").agg(F.max("again").alias("again")))
        if judged.where("again").isEmpty():
            return now.where("attempt > 0").select("kind", "entity", "attempt") if k else None
        now = checkpointed(judged.select("kind", "entity", "m", (F.col("attempt") + F.col("again").cast("int")).alias("attempt")))
    raise ValueError("surrogates still collide: widen their format")


#: Parts into which rows of one text are dealt when they meet its moved entities.
SALTS = 32


def surrogates(docs: DataFrame, key: str = DEMO_KEY, text: str = "text", local: int = LOCAL) -> DataFrame:
    """Docs with the text's entities replaced, and `__kinds`: the kinds of what was replaced, in order.

    Texts are searched once: docs and what is found go to a table in the shared folder.
    """
    let_go(docs.sparkSession)
    found = written(matched(docs, text))
    exceptions = moved(found, key, local)
    let_go(docs.sparkSession)
    at: Callable[[Column], Column] = lambda x: F.lit(0)
    if exceptions is not None:  # texts that hold a moved entity get their attempts by a join on the text's digest
        found = found.withColumn("__digest", F.sha2(text, 256))
        held = found.select("__digest", F.explode("__found").alias("x")).select("__digest", F.struct("x.kind", "x.entity").alias("__e")).distinct()
        held = spread_join(held, exceptions.select(F.struct("kind", "entity").alias("__e"), "attempt"), "__e")
        by = held.groupBy("__digest").agg(F.map_from_entries(F.collect_list(F.struct(F.concat_ws("|", "__e.kind", "__e.entity"), "attempt"))).alias("__moved"))
        # copies of a text differ in other columns, by which they are dealt out
        by = by.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        salt = F.pmod(F.xxhash64(F.lit("salt"), *[F.col(f"`{c}`") for c in docs.columns if c != text]), F.lit(SALTS)).cast("int")
        found = found.withColumn("__salt", salt).join(by, ["__digest", "__salt"], "left")
        at = lambda x: F.coalesce(F.col("__moved")[F.concat_ws("|", x["kind"], x["entity"])], F.lit(0))
    new = F.transform("__found", lambda x: let(at(x), lambda attempt: F.coalesce(surrogate(x["m"], x["kind"], key, attempt, local), x["m"])))
    pieces = F.zip_with(F.split(F.col(text), ANY, -1), new, lambda gap, s: F.concat(gap, F.coalesce(s, F.lit(""))))
    out = found.withColumn("__kinds", F.filter(F.transform("__found", lambda x: x["kind"]), lambda k: k.isNotNull()))
    out = out.withColumn(text, F.when(F.size("__kinds") > 0, F.array_join(pieces, "")).otherwise(F.col(text)))
    return out.select(*[F.col(f"`{c}`") for c in docs.columns], "__kinds")


def surrogate_documents(docs: DataFrame, key: str = DEMO_KEY) -> DataFrame:
    """doc_id, n_entities, kinds (each with its number) and the text with surrogates, for every row."""
    out = surrogates(docs.select("doc_id", "text"), key)
    kinds = F.array_join(F.transform(F.array_sort(F.array_distinct(F.col("__kinds"))), lambda k: F.concat_ws(":", k, F.size(F.filter(F.col("__kinds"), lambda x: x == k)).cast("string"))), ",")
    return out.select("doc_id", F.greatest(F.lit(0), F.size("__kinds")).alias("n_entities"), F.coalesce(kinds, F.lit("")).alias("kinds"), "text")
