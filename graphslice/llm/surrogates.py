"""PII surrogates with built-in functions only: keyed, type-consistent, format-preserving and distinct replacements."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Durable, maybe_in, settle, without

OCTET = r"(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
MALE, FEMALE, NEUTRAL = r"Mr|Herr|Sr|Señor|Monsieur|Г-н", r"Mrs|Ms|Miss|Frau|Sra|Señora|Mme|Madame|Г-жа", r"Dr|Prof"
PATTERNS = {
    "email": r"(?<![\p{L}\p{N}._%+-])[\p{L}\p{N}._%+-]++@[\p{L}\p{N}-]+(?:\.[\p{L}\p{N}-]+)*\.\p{L}{2,}",
    "token": r"(?<![\p{L}\p{N}])(?:[0-9a-f]{32,64}|[0-9A-F]{32,64})(?![\p{L}\p{N}])",
    "phone": r"(?<![\p{L}\p{N}+])\+[0-9]{1,3}[ .-]?(?:\([0-9]{1,4}\)|[0-9]{1,4})(?:[ .-]?[0-9]{2,4}){2,4}(?![0-9])",
    "ip": rf"(?<![\p{{L}}\p{{N}}.]){OCTET}(?:\.{OCTET}){{3}}(?![0-9]|\.[0-9])",
    "card": r"(?<![\p{L}\p{N}])[0-9]{4}(?:[ -]?[0-9]{4}){2}[ -]?[0-9]{1,7}(?![\p{L}\p{N}])",
    "ssn": r"(?<![\p{L}\p{N}-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![\p{L}\p{N}-])",
    "name": rf"(?<![\p{{L}}\p{{N}}])(?:{FEMALE}|{MALE}|{NEUTRAL})\.? \p{{Lu}}\p{{Ll}}+(?: \p{{Lu}}\p{{Ll}}+)?(?![\p{{L}}\p{{N}}])",
}
ANY = "|".join(PATTERNS.values())
HINT = rf"[0-9@]|(?:{FEMALE}|{MALE}|{NEUTRAL})\.? \p{{Lu}}"

# alphabets within which characters are shifted: a letter stays a vowel or consonant of its script, a digit a digit
PLAIN = ("0123456789", "aeiou", "bcdfghjklmnpqrstvwxyz", "áéíóúàèìòùâêîôûäëïöü", "аеиоуыэюя", "бвгджзйклмнпрстфхцчшщ")
HEX = ("0123456789abcdef",)
DIGITS = ("0123456789",)
# pools of given names by gender and script
GIVEN = {
    ("m", "latin"): "Adam Bruno Carl Denis Emil Felix Georg Hugo Ivan Jonas Karel Leon Marco Nils Oskar Paul".split(),
    ("f", "latin"): "Anna Berta Clara Diana Elena Frida Greta Helga Irene Julia Katrin Laura Maria Nora Olga Paula".split(),
    ("n", "latin"): "Alex Robin Kim Sascha Dominique Andrea Noa Charlie Jean Sam Toni Lou Mika Luca Jules Kai".split(),
    ("m", "cyrillic"): "Антон Борис Вадим Глеб Денис Егор Захар Игорь Кирилл Лев Марк Олег Павел Роман Семён Тимур".split(),
    ("f", "cyrillic"): "Анна Вера Галина Дарья Елена Жанна Зоя Ирина Лидия Мария Нина Ольга Полина Раиса Софья Тамара".split(),
    ("n", "cyrillic"): "Саша Женя Валя Слава Паша Шура Тоня Миша Ася Вася Лёня Сима Тося Яша Рома Надя".split(),
}


def kind(e: Column) -> Column:
    """Type of a match."""
    out = F.when(F.contains(e, F.lit("@")), "email").when(F.startswith(e, F.lit("+")), "phone")
    for name in ("ip", "token", "ssn", "card"):
        out = out.when(e.rlike(f"^(?:{PATTERNS[name]})$"), name)
    return out.otherwise("name")


def _digest(key: str, tag: str, *parts: Column) -> Column:
    return F.sha2(F.concat_ws("|", F.lit(key), F.lit(tag), *parts), 512)


def _byte(digest: Column, i: Column | int) -> Column:
    """Two hex digits of the digest, as a number; the 128 digits are used in turn."""
    at = (F.pmod(F.lit(2) * i, F.lit(126)) + 1).cast("int") if isinstance(i, Column) else F.lit(2 * i + 1)
    return F.conv(F.substring(digest, at, F.lit(2)), 16, 10).cast("int")


def _shift(s: Column, digest: Column, alphabets: tuple[str, ...]) -> Column:
    """Each character moved on within its alphabet by a byte of the digest; others stay."""

    def one(c: Column, i: Column) -> Column:
        out = None
        for a in alphabets:
            place = F.call_function("locate", c, F.lit(a))
            moved = F.substring(F.lit(a), (F.pmod(place - 1 + _byte(digest, i), F.lit(len(a))) + 1).cast("int"), F.lit(1))
            out = F.when(place > 0, moved) if out is None else out.when(place > 0, moved)
        return out.otherwise(c)

    return F.array_join(F.transform(F.filter(F.split(s, ""), lambda c: c != ""), one), "")


def let(value: Column, body) -> Column:
    """body(value) with the value computed once, however often the body uses it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def feistel(s: Column, key: str, tag: str, tweak: Column, alphabets: tuple[str, ...]) -> Column:
    """A keyed bijection on the strings of one format: halves shift each other in three rounds, each of which can be
    undone, and no character leaves its alphabet. So two strings never get one image."""

    def turned(half: Column, other: Column, round_: str, then) -> Column:
        return let(_digest(key, tag + round_, tweak, other), lambda d: let(_shift(half, d, alphabets), then))

    def rounds(x: Column) -> Column:
        half = F.floor(F.length(x) / 2).cast("int")
        left, right = F.substring(x, F.lit(1), half), F.substring(x, (half + 1).cast("int"), F.length(x))
        return let(right, lambda r: turned(left, r, "1", lambda a: turned(r, a, "2", lambda b: turned(a, b, "3", lambda c: F.concat(c, b)))))

    return let(s, rounds)


def _luhn(digits: Column) -> Column:
    """Check digit of a digit string."""
    n = F.length(digits)
    parts = F.transform(F.sequence(F.lit(1), n), lambda i: F.substring(digits, i, F.lit(1)).cast("int") * F.when((n - i) % 2 == 0, 2).otherwise(1))
    total = F.aggregate(parts, F.lit(0), lambda t, x: t + F.when(x > 9, x - 9).otherwise(x))
    return F.pmod(F.lit(10) - total % 10, F.lit(10))


def _only_digits(s: Column) -> Column:
    return F.regexp_replace(s, "[^0-9]", "")


def surrogate(e: Column, key: str, attempt: Column) -> Column:
    """The replacement of a match: same type, separators, length, script, letter case (all upper or as lower-cased),
    validity of check digits and, for names, gender. Equal entities get equal replacements whatever their case."""
    t = attempt.cast("string")
    low = F.lower(e)

    def email(x: Column) -> Column:
        def with_host(host: Column) -> Column:
            top = F.regexp_extract(host, r"(\.\p{L}+)$", 1)
            domain = F.concat(feistel(F.substring(host, F.lit(1), F.length(host) - F.length(top)), key, "host", F.lit("0"), PLAIN), top)
            return F.concat(feistel(F.regexp_extract(x, "^([^@]*)@", 1), key, "local", F.concat_ws("|", t, host), PLAIN), F.lit("@"), domain)

        return let(F.regexp_extract(x, "@(.*)$", 1), with_host)

    code = F.regexp_extract(e, r"^(\+[0-9]{1,3})", 1)
    phone = F.concat(code, feistel(F.substring(e, F.length(code) + 1, F.length(e)), key, "phone", t, DIGITS))

    def card(body: Column) -> Column:
        last = F.substring(e, F.length(e), F.lit(1)).cast("int")
        inner = F.concat(F.substring(body, F.lit(1), F.lit(1)), feistel(F.substring(body, F.lit(2), F.length(body)), key, "card", t, DIGITS))
        # a valid number stays valid, and a number that fails the check fails it by as much
        return let(inner, lambda i: F.concat(i, F.pmod(_luhn(_only_digits(i)) + last - _luhn(_only_digits(body)), F.lit(10)).cast("string")))

    def turned(x: Column, by: Column, tag: str, then) -> Column:
        d = _digest(key, tag, t, F.concat_ws(".", F.transform(by, lambda v: v.cast("string"))))
        return let(d, lambda d: let(F.transform(x, lambda v, i: F.pmod(v + _byte(d, i), F.lit(256))), then))

    def ip(octets: Column) -> Column:
        left, right = F.slice(octets, 1, 2), F.slice(octets, 3, 2)
        return turned(left, right, "ip1", lambda a: turned(right, a, "ip2", lambda b: turned(a, b, "ip3", lambda c: F.concat_ws(".", F.transform(F.concat(c, b), lambda v: v.cast("string"))))))

    title = F.regexp_extract(e, rf"^((?:{FEMALE}|{MALE}|{NEUTRAL})\.?) ", 1)

    def named(names: Column) -> Column:
        two = F.contains(names, F.lit(" "))
        first, family = F.when(two, F.substring_index(names, " ", 1)), F.substring_index(names, " ", -1)
        gender = F.when(title.rlike(rf"^(?:{FEMALE})\.?$"), "f").when(title.rlike(rf"^(?:{MALE})\.?$"), "m").otherwise("n")
        script = F.when(names.rlike(r"\p{IsCyrillic}"), "cyrillic").otherwise("latin")
        pools = F.create_map(*[x for (g, sc), pool in GIVEN.items() for x in (F.lit(g + sc), F.array(*[F.lit(n) for n in pool]))])
        place = let(_digest(key, "given", t, F.lower(F.coalesce(first, F.lit("")))), lambda d: _byte(d, 0) % 16 + 1)
        # a given name tried again gets an ending of its own, so that one title and family name take any number of given names
        ending = F.when(attempt > 0, feistel(F.lower(first), key, "ending", t, PLAIN)).otherwise("")
        pick = F.concat(F.element_at(F.element_at(pools, F.concat(gender, script)), place), ending)
        # the family name's image does not depend on the title or the given name, so it is the same wherever it stands
        kin = F.initcap(feistel(F.lower(family), key, "family", F.when(two, F.lit("0")).otherwise(t), PLAIN))
        return F.concat_ws(" ", title, F.when(two, pick), kin)

    by_kind = lambda k: (
        F.when(k == "email", let(low, email)).when(k == "phone", phone)
        .when(k == "ip", let(F.transform(F.split(e, r"\."), lambda x: x.cast("int")), ip))
        .when(k == "token", feistel(low, key, "token", t, HEX)).when(k == "ssn", feistel(e, key, "ssn", t, DIGITS))
        .when(k == "card", let(F.substring(e, F.lit(1), F.length(e) - 1), card))
        .otherwise(let(F.substring(e, F.length(title) + 2, F.length(e)), named))
    )
    return let(let(kind(e), by_kind), lambda out: F.when((e == F.upper(e)) & (F.lower(e) != F.upper(e)), F.upper(out)).otherwise(out))


def _matches(text: Column) -> Column:
    return F.when(text.rlike(HINT), F.regexp_extract_all(text, F.lit(ANY), F.lit(0))).otherwise(F.array().cast("array<string>"))


def clashes(entities: DataFrame, key: str, keep: Durable, most_rounds: int = 12) -> DataFrame:
    """(norm, attempt) of the entities whose first replacement is another entity's replacement or is itself an entity.

    The least entity of a clash keeps its replacement; the others try again, until none is left. Raises if some are
    left after `most_rounds`.
    """
    current = keep(entities.withColumn("attempt", F.lit(0)), "attempt0")
    for i in range(1, most_rounds + 1):
        made = current.withColumn("made", F.lower(surrogate(F.col("entity"), key, F.col("attempt"))))
        owner = made.groupBy("made").agg(F.min("norm").alias("owner"), F.count("*").alias("n")).filter("n > 1")
        taken = made.join(current.select(F.col("norm").alias("real")), F.col("made") == F.col("real")).select("norm")
        lost = made.join(owner, "made").filter("norm <> owner").select("norm").union(taken).distinct()
        lost = keep(lost.withColumnRenamed("norm", "lost"), f"lost{i}")
        if lost.isEmpty():
            return current.filter("attempt > 0").select("norm", "attempt")
        current = keep(current.join(lost, F.col("norm") == F.col("lost"), "left").select("norm", "entity", (F.col("attempt") + F.col("lost").isNotNull().cast("int")).alias("attempt")), f"attempt{i}")
    raise ValueError(f"replacements still clash after {most_rounds} rounds")


def session_key(spark) -> str:
    """The session's secret, spark.graphslice.surrogates.key. Without one, a fixed key that is public: good for tests and for
    comparing runs, not for releasing texts."""
    return spark.conf.get("spark.graphslice.surrogates.key", "public test key")


def replace_entities(docs: DataFrame, key: str) -> DataFrame:
    """The documents with every detected entity replaced in `text`, and `n_entities` (0 for null and empty texts).

    Replacement is a keyed function of the entity, so it is the same in all documents and texts are not joined with a
    table of entities. The distinct entities are checked for clashes apart from the texts; only documents with an
    entity that had to be tried again are joined, by doc_id, with the attempts. Other columns stay; a column named
    n_entities is replaced. Repeated rows are replaced alike.
    """
    spark = docs.sparkSession
    keep = Durable(spark)
    docs = docs.drop("n_entities")
    found = docs.select(F.explode(_matches(F.col("text"))).alias("entity")).select("entity", F.lower("entity").alias("norm"))
    entities = keep(found.groupBy("norm").agg(F.min("entity").alias("entity")), "entities")
    again = clashes(entities, key, keep)
    settle(spark)

    def swapped(df: DataFrame, attempt) -> DataFrame:
        text = F.col("text")
        parts = F.split(text, ANY, -1)
        whole = F.array_join(F.zip_with(parts, F.transform("_m", lambda e: surrogate(e, key, attempt(e))), lambda g, s: F.concat(g, F.coalesce(s, F.lit("")))), "")
        return df.withColumn("_m", _matches(text)).withColumn("text", F.when(F.size("_m") > 0, whole).otherwise(text)).withColumn("n_entities", F.greatest(F.size("_m"), F.lit(0)).cast("long")).drop("_m")

    none = lambda e: F.lit(0)
    if again.isEmpty():
        return swapped(docs, none)
    spread = docs.select("doc_id", F.explode(F.array_distinct(F.transform(_matches(F.col("text")), F.lower))).alias("norm")).join(again, "norm")
    by_doc = keep(spread.groupBy("doc_id").agg(F.map_from_entries(F.collect_set(F.struct("norm", "attempt"))).alias("_again")).withColumnRenamed("doc_id", "_d"), "again")
    plain = swapped(without(docs, "doc_id", by_doc, "_d"), none)
    rest = maybe_in(docs, "doc_id", by_doc, "_d").join(by_doc, F.col("doc_id") == F.col("_d")).drop("_d")
    retried = swapped(rest, lambda e: F.coalesce(F.element_at(F.col("_again"), F.lower(e)), F.lit(0))).drop("_again")
    return plain.unionByName(retried)


def redacted(docs: DataFrame, key: str) -> DataFrame:
    """Columns of the documents, with replaced text and, where it was set, its length in n_chars."""
    out = replace_entities(docs, key)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("n_chars").isNotNull() & (F.col("n_entities") > 0), F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)
