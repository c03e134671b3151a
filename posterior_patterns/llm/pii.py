"""Personal data replaced by keyed surrogates of the same type, gender, script and format.

Detected: e-mail addresses, IPv4 addresses, international and grouped phone numbers, 16-digit card
numbers, grouped national ids, names after a title, and the same given name and surname without a title in a
text that has them with one.  Surrogates belong to entities, not to spellings: an address in any case, the digits
of a phone or card number in any grouping, a given name of a gender, a surname.  So "Mr Karl Braun", "Mr
Braun" and "Karl Braun" of a text stay one person, and a number in two formats stays one number.

A surrogate maps every letter and digit with a keyed digest of (key, type, entity, attempt), keeping script,
length, the top-level domain, the country code, the octet range, and the card's issuer digit and Luhn validity;
a given name becomes one of the title's gender in the entity's script, or mapped letters once these are taken.
A mention gets its entity's surrogate in its own case and grouping.

Distinctness: surrogates are computed once for every distinct entity of the corpus; one that equals a
detected entity or another's surrogate (the least entity keeps it) is computed again with the next attempt
until none collides; from attempt GROW on names and addresses may be longer.

Everything is DataFrame functions.  Distinct (text digest, mention) rows meet the surrogates, so copies
and hot mentions collapse before the join and are spread in it, and only texts that hold a mention are shuffled.

Defined cases: null texts stay null and have no entities; texts without entities stay as they are;
copies and repeated rows are rewritten alike; a surname alone without a title, and a national number without
its country code beside one with it, are not recognised as the same; an empty table gives an empty result; other
columns, whatever their names, are kept, but for one named n_entities, which is replaced by the number of mentions
that the patterns find.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.durable import Durable
from .text import digest, with_class

# Entity patterns, in order of precedence.
EMAIL = r"(?<![\w.%+-])[\w.%+-]{1,64}+@(?:[A-Za-z0-9-]{1,63}\.){1,6}[A-Za-z]{2,24}(?![\w])"
IPV4 = r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?![\d]|\.\d)"
CARD = r"(?<![\d-])(?:\d{16}|\d{4}([ -])\d{4}\1\d{4}\1\d{4})(?![\d-])"
PHONE = r"(?<![\w+])\+\d{1,3}[ .-]?(?:\(\d{1,4}\)|\d{1,4})(?:[ .-]?\d{2,4}){2,4}(?![\d])|(?<![\w(])\(\d{3}\) ?\d{3}[ .-]\d{4}(?![\d])"
NATIONAL = r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])"
TITLES = {"m": ["Mr", "Herr", "Monsieur", "Señor", "Sr", "Господин"], "f": ["Mrs", "Ms", "Miss", "Frau", "Madame", "Mme", "Señora", "Sra", "Госпожа"]}
NAME = r"(?<![\p{L}])(?:" + "|".join(t for x in TITLES.values() for t in sorted(x, key=len, reverse=True)) + r")\.? \p{Lu}[\p{Ll}'-]+(?: \p{Lu}[\p{Ll}'-]+)?"
GIVEN = {
    ("m", "latin"): ["Adam", "Bruno", "Carl", "David", "Emil", "Felix", "Georg", "Hugo", "Ivan", "Jonas", "Karim", "Leon", "Marco", "Nils", "Oscar", "Paul"],
    ("f", "latin"): ["Anna", "Berta", "Clara", "Diana", "Elena", "Flora", "Greta", "Helen", "Irene", "Julia", "Klara", "Laura", "Maria", "Nora", "Olivia", "Paula"],
    ("m", "cyrillic"): ["Андрей", "Борис", "Виктор", "Глеб", "Денис", "Егор", "Иван", "Кирилл"],
    ("f", "cyrillic"): ["Анна", "Вера", "Галина", "Дарья", "Елена", "Ирина", "Мария", "Ольга"],
}
PATTERN = "|".join((EMAIL, IPV4, CARD, PHONE, NATIONAL, NAME))
#: A text without any of these characters or titles holds no entity.
_HINT = r"[@0-9]|" + "|".join(t for x in TITLES.values() for t in x)
_ATTEMPTS, GROW = 40, 8
#: Country codes of one or two digits; all others have three.
_COUNTRY = r"^\+(?:1|7|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|\d{3})"


def mentions(text: Column) -> Column:
    """All mentions of a text in order, repeats included."""
    none = F.expr("cast(array() as array<string>)")
    return F.when(text.rlike(_HINT), F.regexp_extract_all(text, F.lit(PATTERN), F.lit(0))).otherwise(none)


def kind_of(mention: Column) -> Column:
    return (
        F.when(mention.contains("@"), "email").when(mention.rlike(r"^\d+\.\d+\.\d+\.\d+$"), "ip").when(mention.rlike(r"^\d{3}-\d{2}-\d{4}$"), "national")
        .when(mention.rlike(r"^\d[\d -]+$"), "card").when(mention.rlike(r"^[+(]"), "phone").otherwise("name")
    )


def _title(mention: Column) -> Column:
    return F.regexp_extract(mention, r"^\S+ ", 0)


def _names(mention: Column) -> Column:
    return F.split(F.substring(mention, F.length(_title(mention)) + 1, F.length(mention)), " ")


def entities_of(mention: Column) -> Column:
    """The entities that a mention names, as (kind, entity): two for a full name."""
    one = lambda kind, entity: F.struct(kind.alias("kind"), entity.alias("entity"))
    kind, digits, rest = kind_of(mention), F.regexp_replace(mention, r"\D", ""), _names(mention)
    women = F.regexp_replace(_title(mention), r"\.? $", "").isin(TITLES["f"])
    surname = one(F.lit("surname"), F.element_at(rest, -1))
    given = one(F.when(women, "given f").otherwise("given m"), F.get(rest, F.lit(0)))
    return (
        F.when(kind == "name", F.when(F.size(rest) > 1, F.array(given, surname)).otherwise(F.array(surname)))
        .when(kind == "email", F.array(one(kind, F.lower(mention))))
        .when(kind == "phone", F.array(one(kind, F.concat(F.when(mention.startswith("+"), "+").otherwise(""), digits))))
        .when(kind == "card", F.array(one(kind, digits))).otherwise(F.array(one(kind, mention)))
    )


def _byte(stream: Column, i: Column) -> Column:
    """Number i of a keyed stream of 64 bytes in hex, used cyclically."""
    return F.conv(F.substring(stream, F.pmod(i, F.lit(64)) * 2 + 1, F.lit(2)), 16, 10).cast("int")


def _luhn(digits: Column) -> Column:
    """Luhn sum of an array of 16 digit characters modulo 10."""
    return F.aggregate(F.sequence(F.lit(0), F.lit(15)), F.lit(0), lambda a, i: a + F.when(i % 2 == 1, F.get(digits, i).cast("int")).otherwise(F.floor(F.get(digits, i).cast("int") * 2 / 10).cast("int") + (F.get(digits, i).cast("int") * 2) % 10)) % 10


_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_CYR_UP, _CYR_LOW = "АБВГДЕЖЗИКЛМНОПРСТУФХЦЧШЭЮЯ", "абвгдежзиклмнопрстуфхцчшэюя"


def _mapped(c: Column, b: Column) -> Column:
    """A character of the same class, chosen by a byte."""
    pick = lambda letters: F.substring(F.lit(letters), b % len(letters) + 1, F.lit(1))
    return (
        F.when(c.between("0", "9"), (b % 10).cast("string")).when(c.between("a", "z"), pick(_LOWER)).when(c.between("A", "Z"), pick(_UPPER))
        .when(c.between("а", "я"), pick(_CYR_LOW)).when(c.between("А", "Я"), pick(_CYR_UP))
        .when(c.rlike(r"\p{Ll}"), pick(_LOWER)).when(c.rlike(r"\p{Lu}"), pick(_UPPER)).otherwise(c)
    )


def surrogate(kind: Column, entity: Column, attempt: Column, key: str) -> Column:
    """The surrogate of an entity at an attempt; any two attempts differ in their keyed stream."""
    stream = F.sha2(F.concat_ws("|", F.lit(key), kind, entity, attempt.cast("string")), 512)
    all_mapped = lambda t, shift=0: F.array_join(F.transform(F.split(t, ""), lambda c, i: _mapped(c, _byte(stream, i + shift))), "")
    longer = F.when(attempt >= GROW, F.array_join(F.transform(F.sequence(F.lit(40), F.lit(41) + (attempt / GROW).cast("int")), lambda i: _mapped(F.right(entity, F.lit(1)), _byte(stream, i))), "")).otherwise("")
    cut = F.length(entity) - F.instr(F.reverse(entity), ".") + 1  # of the top-level domain's dot
    extra = F.when(attempt >= GROW, F.concat(F.substring(stream, F.lit(97), F.lit(2)), attempt.cast("string"))).otherwise("")
    email = F.concat(extra, all_mapped(F.substring(entity, F.lit(1), cut - 1)), F.substring(entity, cut, F.length(entity)))
    ip = F.array_join(F.transform(F.split(entity, r"\."), lambda o, i: (F.when((i == 0) | (i == 3), _byte(stream, i) % 223 + 1).otherwise(_byte(stream, i))).cast("string")), ".")
    lead = F.length(F.regexp_extract(entity, _COUNTRY, 0))
    phone = F.concat(F.substring(entity, F.lit(1), lead), all_mapped(F.substring(entity, lead + 1, F.length(entity))))
    digits = F.split(entity, "")
    new = F.transform(digits, lambda c, i: F.when(i == 0, c).otherwise((_byte(stream, i) % 10).cast("string")))
    head = F.slice(new, 1, 15)
    check = ((10 - _luhn(F.concat(head, F.array(F.lit("0"))))) % 10).cast("string")
    card = F.array_join(F.concat(head, F.array(F.when(_luhn(digits) == 0, check).otherwise(F.get(new, F.lit(15))))), "")
    mapped = F.concat(all_mapped(entity, 7), longer)
    given = lambda sex: F.when(entity.rlike(r"\p{IsCyrillic}"), _choice(GIVEN[sex, "cyrillic"], stream)).otherwise(_choice(GIVEN[sex, "latin"], stream))
    first = lambda sex: F.when(attempt < 4, given(sex)).otherwise(mapped)
    return (
        F.when(kind == "email", email).when(kind == "ip", ip).when(kind == "phone", phone).when(kind == "card", card)
        .when(kind == "given f", first("f")).when(kind == "given m", first("m")).when(kind == "surname", mapped).otherwise(all_mapped(entity))
    )


def _like(mention: Column, found: Column) -> Column:
    """A mention rewritten with its entities' surrogates, in its own case and grouping."""
    kind, one = kind_of(mention), F.element_at(found, 1)
    before = lambda i: F.length(F.regexp_replace(F.substring(mention, F.lit(1), i), r"\D", ""))
    digits = F.regexp_replace(one, r"\D", "")
    grouped = F.array_join(F.transform(F.split(mention, ""), lambda c, i: F.when(c.between("0", "9"), F.substring(digits, before(i) + 1, F.lit(1))).otherwise(c)), "")
    more = F.length(one) - F.length(mention)  # letters that a later attempt put before
    capital = lambda i: F.substring(mention, i - more + 1, F.lit(1)).rlike(r"\p{Lu}") & (i >= more)
    cased = F.array_join(F.transform(F.split(one, ""), lambda c, i: F.when(capital(i), F.upper(c)).otherwise(c)), "")
    name = F.concat(_title(mention), F.array_join(found, " "))
    return F.when(kind == "email", cased).when(kind.isin("phone", "card"), grouped).when(kind == "name", name).otherwise(one)


def _choice(words: list[str], stream: Column) -> Column:
    return F.element_at(F.array(*map(F.lit, words)), _byte(stream, F.lit(60)) % len(words) + 1)


def surrogate_table(found: DataFrame, store: Durable, key: str) -> DataFrame:
    """found(kind, entity), distinct and stored -> (kind, entity, surrogate): distinct, and no surrogate is itself an entity found."""
    spark, taken = found.sparkSession, None
    tasks, todo = int(spark.conf.get("spark.sql.shuffle.partitions")), found
    originals = found.select("kind", F.col("entity").alias("surrogate"))
    for attempt in range(_ATTEMPTS):
        spread = todo.select("kind", "entity").repartition(tasks, "kind", "entity")  # mapping is the costly part
        made = store.save(spread.withColumn("surrogate", surrogate(F.col("kind"), F.col("entity"), F.lit(attempt), key)), f"made{attempt}")
        first = made.groupBy("kind", "surrogate").agg(F.min("entity").alias("entity"))
        held = first.join(originals, ["kind", "surrogate"], "left_anti")
        if taken is not None:
            held = held.join(taken.select("kind", "surrogate"), ["kind", "surrogate"], "left_anti")
        held = store.save(held.select("kind", "entity", "surrogate"), f"held{attempt}")
        taken = held if taken is None else taken.unionByName(held)
        todo = store.save(made.join(held.select("kind", "entity"), ["kind", "entity"], "left_anti").select("kind", "entity"), f"todo{attempt}")
        if todo.isEmpty():
            return taken
    raise RuntimeError("a type of entities has no room for distinct surrogates")


def mention_table(found: DataFrame, store: Durable, key: str) -> DataFrame:
    """found(mention, n), distinct and stored -> (mention, n, new): every spelling with its replacement."""
    parts = found.select("mention", "n", F.posexplode(entities_of(F.col("mention"))).alias("place", "e")).select("mention", "n", "place", "e.kind", "e.entity")
    parts = store.save(parts, "parts")
    known = surrogate_table(store.save(parts.select("kind", "entity").distinct(), "entities"), store, key)
    named = parts.join(known, ["kind", "entity"]).groupBy("mention", "n").agg(F.sort_array(F.collect_list(F.struct("place", "surrogate"))).alias("s"))  # one or two
    tasks = int(found.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return named.repartition(tasks, "mention").select("mention", "n", _like(F.col("mention"), F.col("s.surrogate")).alias("new"))


def pseudonymise(docs: DataFrame, key: str, text_col: str = "text") -> DataFrame:
    """docs with the text rewritten, and n_entities."""
    store, text = Durable(docs.sparkSession, "pii"), F.col(text_col)
    listed = docs.select(digest(text).alias("d"), F.explode(F.array_distinct(mentions(text))).alias("mention"))
    pairs = store.save(listed.groupBy("d", "mention").agg(F.count("*").alias("copies")), "pairs")
    names = store.save(mention_table(store.save(pairs.groupBy("mention").agg(F.count("*").alias("n")), "mentions"), store, key), "names")
    met = with_class(pairs, names, "mention", "n", "d").select("d", "copies", "mention", F.col("class.new").alias("new"))
    # a person's name without the title, in a text that has it with one
    full = (kind_of(F.col("mention")) == "name") & (F.size(_names(F.col("mention"))) > 1)
    plain = lambda c: F.array_join(_names(F.col(c)), " ")
    met = met.withColumn("person", F.when(full, F.struct(F.concat(F.lit(r"(?<!\p{L})"), plain("mention"), F.lit(r"(?!\p{L})")).alias("old"), plain("new").alias("new"))))
    maps = met.groupBy("d").agg(F.max("copies").alias("copies"), F.map_from_entries(F.collect_list(F.struct("mention", "new"))).alias("map"), F.array_sort(F.collect_set("person")).alias("people"))  # of one text
    maps = store.save(maps, "maps")
    keep = [c for c in docs.columns if c != "n_entities"]
    whole = F.struct(*(F.col(f"`{c}`") for c in keep)).alias("caller")
    rows = docs.select(whole, text.alias("text"), mentions(text).alias("found")).withColumn("found", F.coalesce("found", F.expr("cast(array() as array<string>)")))
    back = lambda new: [new.alias(c) if c == text_col else F.col(f"caller.`{c}`") for c in keep]
    clean = rows.filter(F.size("found") == 0).select(*back(F.col("text")), F.lit(0).cast("long").alias("n_entities"))
    held = rows.filter(F.size("found") > 0).withColumn("d", digest(F.col("text"))).withColumn("row", F.monotonically_increasing_id())
    held = with_class(held, maps, "d", "copies", "row")
    gaps = F.split(F.col("text"), PATTERN, -1)
    new = F.array_join(F.zip_with(gaps, "found", lambda g, e: F.concat(g, F.coalesce(F.element_at("class.map", e), F.lit("")))), "")
    new = F.when(F.size("class.people") > 0, F.aggregate("class.people", new, lambda t, p: F.regexp_replace(t, p.old, p.new))).otherwise(new)
    return clean.unionByName(held.select(*back(new), F.size("found").cast("long").alias("n_entities")))
