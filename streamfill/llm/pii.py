"""Surrogates for personal data; DataFrame functions only.

Mentions of e-mail and network addresses, telephone, card, account and social numbers, names after an honorific, and
the same names without it in the same text are cut out and replaced by made-up ones of the same type and form: digits
stay digits, with their signs between them, a card number that checks out still does, a name keeps its script and the
gender of its honorifics. A surrogate comes from a keyed hash of what the mention denotes, so all mentions of one
entity, whatever their spelling, get the same one everywhere. A name is one entity whatever its honorifics, unless the
corpus has it with those of both genders. Surrogates of all entities are compared over the whole corpus: an entity
whose surrogate is another's, or is a real entity, draws again. Not found: names that never follow an honorific, and
parts of a name by themselves.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import SALTS, salt_of, settle

# What mentions look like, and names to draw from.
EMAIL = r"(?:(?<![\p{L}\p{N}._%+-])|\G)[\p{L}\p{N}._%+-]++@[A-Za-z0-9](?:[A-Za-z0-9.-]*[A-Za-z0-9])?\.[A-Za-z]{2,}"
IP = r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?![\d]|\.\d)"
IBAN = r"(?=[A-Z]{2}\d)\b[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?\b"
SSN = r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])"
CARD = r"(?<!\d)\d(?:[ -]?\d){12,18}(?![ -]?\d)"
PHONE = r"(?<![\d+])(?:\+\d{1,3}[ .-]?)?(?:\(\d{2,4}\)[ .-]?|\d{2,4}[ .-])\d{3,4}[ .-]\d{3,4}(?!\d)|(?<![\d+])\+\d(?:[ .()-]{0,2}\d){6,14}(?!\d)"
MALE_TITLE = r"(?:Mr|Herr|Monsieur|Señor|Sr|Sir|Господин|Г-н|Κύριος|Κος)"
FEMALE_TITLE = r"(?:Mrs|Ms|Miss|Frau|Madame|Mme|Mlle|Señora|Sra|Госпожа|Г-жа|Κυρία|Κα)"
TITLE = r"(?:" + MALE_TITLE + "|" + FEMALE_TITLE + r"|Dr|Prof)"
NAME = r"(?=[DFHMPSГΚ])(?<!\p{L})" + TITLE + r"\.? +\p{Lu}[\p{Ll}\p{M}'’-]+(?: +\p{Lu}[\p{Ll}\p{M}'’-]+){0,2}"
FIRST_NAMES = {
    ("latin", "m"): ["Adam", "Bruno", "Carl", "David", "Emil", "Felix", "Hugo", "Ivan", "Jonas", "Leon", "Marco", "Noah", "Oscar", "Paul", "Simon", "Victor"],
    ("latin", "f"): ["Alice", "Bella", "Clara", "Diana", "Elena", "Flora", "Greta", "Hanna", "Irene", "Julia", "Laura", "Maria", "Nora", "Olga", "Sara", "Vera"],
    ("cyrillic", "m"): ["Антон", "Борис", "Виктор", "Глеб", "Денис", "Егор", "Иван", "Кирилл", "Лев", "Максим", "Никита", "Олег", "Павел", "Роман", "Семён", "Тимур"],
    ("cyrillic", "f"): ["Алина", "Вера", "Галина", "Дарья", "Елена", "Жанна", "Инна", "Кира", "Лидия", "Мария", "Нина", "Ольга", "Полина", "Рита", "София", "Юлия"],
    ("greek", "m"): ["Αλέξης", "Βασίλης", "Γιώργος", "Δημήτρης", "Θανάσης", "Ηλίας", "Κώστας", "Λευτέρης", "Μάριος", "Νίκος", "Ορέστης", "Πέτρος", "Σπύρος", "Στέλιος", "Τάσος", "Φώτης"],
    ("greek", "f"): ["Άννα", "Βάσω", "Γεωργία", "Δήμητρα", "Ελένη", "Ζωή", "Ηρώ", "Θάλεια", "Ιωάννα", "Κατερίνα", "Λένα", "Μαρία", "Νεφέλη", "Ξένια", "Σοφία", "Χαρά"],
}
SYLLABLES = {
    "latin": ["ba", "bel", "cor", "da", "del", "fen", "gar", "hol", "ka", "lan", "mer", "nor", "pol", "ren", "sol", "ter"],
    "cyrillic": ["ба", "бел", "вор", "га", "дин", "жен", "зар", "кол", "ла", "лин", "мер", "нор", "пол", "рен", "сол", "тер"],
    "greek": ["βα", "βελ", "γορ", "δα", "δελ", "ζεν", "θαρ", "κολ", "λα", "λιν", "μερ", "νορ", "πολ", "ρεν", "σολ", "τερ"],
}
TYPES = (("email", EMAIL), ("iban", IBAN), ("ip", IP), ("ssn", SSN), ("card", CARD), ("phone", PHONE), ("name", NAME))
#: All of them in that order; a look at the next character spares most places the patterns of numbers.
MENTION = f"(?:{EMAIL})|(?:{IBAN})|(?=[\\d+(])(?:" + "|".join(f"(?:{p})" for p in (IP, SSN, CARD, PHONE)) + f")|(?:{NAME})"
#: Draws after which a kind of number counts as used up.
MOST_DRAWS = 100


def type_of(mention: Column) -> Column:
    return reduce(lambda rest, x: F.when(mention.rlike(f"^(?:{x[1]})$"), x[0]).otherwise(rest), reversed(TYPES[:-1]), F.lit("name"))


def digits_of(s: Column) -> Column:
    return F.regexp_replace(s, r"[^0-9]", "")


def entity_of(kind: Column, mention: Column) -> Column:
    """What a mention denotes, the same for all its spellings. A bare ten-digit number is the one with +1 before it."""
    number = digits_of(mention)
    return (
        F.when(kind == "email", F.lower(mention)).when(kind == "ip", mention).when(kind == "iban", F.regexp_replace(mention, " ", ""))
        .when(kind == "phone", F.when((F.length(number) == 10) & ~mention.startswith("+"), F.concat(F.lit("1"), number)).otherwise(number))
        .when(kind == "name", F.lower(bare_name(mention))).otherwise(number)
    )


def bare_name(mention: Column) -> Column:
    return F.regexp_replace(F.regexp_replace(mention, "^" + TITLE + r"\.? +", ""), r"\s+", " ")


def gender_of(kind: Column, mention: Column) -> Column:
    """m or f by the honorific of a name, else u."""
    name = kind == "name"
    return F.when(name & mention.rlike("^" + FEMALE_TITLE + r"\.? "), "f").when(name & mention.rlike("^" + MALE_TITLE + r"\.? "), "m").otherwise("u")


def _pick(digest: Column, at: int, values: list[str]) -> Column:
    return F.element_at(F.array(*map(F.lit, values)), F.conv(F.substring(digest, at, 2), 16, 10).cast("int") % len(values) + 1)


def _luhn(number: Column) -> Column:
    """The check sum of a string of digits; 0 for a number that checks out."""
    n = F.length(number)
    digit = lambda i: F.substring(number, n - i, F.lit(1)).cast("int")
    doubled = lambda i: F.when(i % 2 == 1, F.when(digit(i) > 4, digit(i) * 2 - 9).otherwise(digit(i) * 2)).otherwise(digit(i))
    return F.aggregate(F.transform(F.sequence(F.lit(0), n - 1), doubled), F.lit(0), lambda a, b: a + b) % 10


def surrogate(kind: Column, entity: Column, attempt: Column, key: str) -> Column:
    """The surrogate's essence: the digits or letters that fill a mention's form."""
    digest = F.sha2(F.concat_ws("|", F.lit(key), kind, entity, attempt.cast("string")), 256)
    stream = F.concat(*(F.lpad(F.pmod(F.conv(F.substring(digest, 1 + 12 * k, 12), 16, 10).cast("long"), F.lit(10**12)).cast("string"), 12, "0") for k in range(5)))
    local = F.translate(F.substring(digest, 1, 14), "0123456789", "ghijklmnop")
    email = F.concat(local, F.lit("@mail"), F.conv(F.substring(digest, 15, 1), 16, 10), F.lit(".example.net"))
    ip = F.concat_ws(".", *(F.pmod(F.conv(F.substring(digest, 1 + 4 * k, 4), 16, 10).cast("int"), F.lit(254 if k in (0, 3) else 256)) + (1 if k in (0, 3) else 0) for k in range(4)))
    number = F.substring(stream, F.lit(1), F.length(entity))
    same_country = F.concat(F.substring(entity, 1, 1), F.substring(stream, F.lit(2), F.length(entity) - 1))
    all_but_last = F.substring(number, F.lit(1), F.length(entity) - 1)
    check = (10 - _luhn(F.concat(all_but_last, F.lit("0")))) % 10
    card = F.when(_luhn(entity) == 0, F.concat(all_but_last, check.cast("string"))).otherwise(number)
    iban = F.concat(
        F.substring(entity, 1, 2),
        F.array_join(F.transform(F.sequence(F.lit(3), F.length(entity)), lambda i: F.when(F.substring(entity, i, F.lit(1)).rlike("[0-9]"), F.substring(stream, i, F.lit(1))).otherwise(F.translate(F.substring(stream, i, F.lit(1)), "0123456789", "BCDFGHJKLM"))), ""),
    )
    script = F.when(entity.rlike(r"\p{IsCyrillic}"), "cyrillic").when(entity.rlike(r"\p{IsGreek}"), "greek").otherwise("latin")
    male = F.when(entity.startswith("m:"), True).when(entity.startswith("f:"), False).otherwise(F.substring(digest, 1, 1) < "8")
    first, last = F.lit(None).cast("string"), F.lit(None).cast("string")
    for s, syllables in SYLLABLES.items():
        drawn = F.when(male, _pick(digest, 3, FIRST_NAMES[s, "m"])).otherwise(_pick(digest, 3, FIRST_NAMES[s, "f"]))
        first = F.when(script == s, drawn).otherwise(first)
        # a longer one at every draw, so that there is always room
        made = F.concat(*(_pick(digest, at, syllables) for at in (5, 7, 9, 11, 13)), *(F.when(attempt > k, _pick(digest, 15 + 2 * k, syllables)).otherwise("") for k in range(24)))
        last = F.when(script == s, F.initcap(made)).otherwise(last)
    words = F.size(F.split(entity, " "))
    name = F.when(words == 1, last).when(words == 2, F.concat_ws(" ", first, last)).otherwise(F.concat_ws(" ", first, F.initcap(F.substring(last, 4, 4)), last))
    return (
        F.when(kind == "email", email).when(kind == "ip", ip).when(kind == "iban", iban).when(kind == "card", card)
        .when(kind == "phone", same_country).when(kind == "name", name).otherwise(number)
    )


def rendered(kind: Column, mention: Column, core: Column) -> Column:
    """The surrogate in the form of the mention: its signs and spaces, or its honorific, kept."""
    number = digits_of(mention)
    fill = F.when((kind == "phone") & (F.length(core) > F.length(number)), F.substring(core, F.lit(2), F.length(number))).otherwise(core)
    signs = F.split(mention, "")
    before = lambda i, what: F.length(F.regexp_replace(F.substring(mention, F.lit(1), i + 1), what, ""))
    digits = F.array_join(F.transform(signs, lambda c, i: F.when(c.rlike("[0-9]"), F.substring(fill, before(i, "[^0-9]"), F.lit(1))).otherwise(c)), "")
    letters = F.array_join(F.transform(signs, lambda c, i: F.when(c == " ", c).otherwise(F.substring(fill, before(i, " "), F.lit(1)))), "")
    title = F.regexp_extract(mention, "^" + TITLE + r"\.? +", 0)
    return F.when(kind.isin("email", "ip"), core).when(kind == "name", F.concat(title, core)).when(kind == "iban", letters).otherwise(digits)


def draw(entities: DataFrame, key: str) -> DataFrame:
    """Rows (kind, entity, core) for the distinct (kind, entity): cores differ within a kind and are no entity of it,
    names without regard to case. Every round settles what it has found and goes on with the rest only. Numbers keep
    their length, so a kind whose forms are used up raises an error after MOST_DRAWS rounds."""
    same = lambda c: F.when(F.col("kind") == "name", F.lower(c)).otherwise(F.col(c))
    entities = settle(entities.select("kind", "entity"))
    taken = entities.select("kind", F.when(F.col("kind") == "name", F.regexp_replace("entity", "^[mfu]:", "")).otherwise(F.col("entity")).alias("same"))
    found, left = [], entities
    for attempt in range(MOST_DRAWS):
        drawn = left.withColumn("core", surrogate(F.col("kind"), F.col("entity"), F.lit(attempt), key)).withColumn("same", same("core"))
        drawn = drawn.withColumn("turn", F.row_number().over(Window.partitionBy("kind", "same").orderBy("entity")))
        tested = settle(drawn.join(taken.withColumn("real", F.lit(True)), ["kind", "same"], "left").withColumn("again", (F.col("turn") > 1) | F.col("real").isNotNull()))
        found.append(tested.where("not again"))
        if not tested.where("again").limit(1).count():
            return reduce(DataFrame.unionByName, found).select("kind", "entity", "core")
        taken, left = taken.union(found[-1].select("kind", "same")), tested.where("again").select("kind", "entity")
    raise ValueError(f"after {MOST_DRAWS} draws some entities have no surrogate: their kind has too few of their length")


def replace_private(docs: DataFrame, key: str, *, carry: tuple[str, ...] = (), id_col: str = "doc_id", text_col: str = "text", salts: int = SALTS) -> DataFrame:
    """Rows (doc_id, carry..., text, n_replaced), one for each row of docs, with every mention replaced.

    A null text stays null, with none replaced. Repeated rows get the same text; an empty table gives an empty
    result; other columns are ignored but for those in `carry`. The key must be kept secret: who has it can test
    guesses, but nothing can be read back from a surrogate alone.
    """
    rows = docs.select(F.col(id_col).alias("q_id"), F.col(text_col).alias("q_text"), *(F.col(c).alias(f"c_{c}") for c in carry))
    none = F.array().cast("array<string>")
    found = F.coalesce(F.col("q_text").rlike(MENTION), F.lit(False))
    hit = rows.where(found).withColumn("q_said", F.coalesce(F.regexp_extract_all("q_text", F.lit(MENTION), F.lit(0)), none))
    names = F.array_distinct(F.transform(F.filter("q_said", lambda m: m.rlike("^" + TITLE + r"\.? ") & (type_of(m) == "name")), bare_name))
    longest = F.transform(F.array_sort(F.transform(names, lambda n: F.struct((-F.length(n)).alias("l"), n.alias("n")))), lambda x: F.regexp_replace(x["n"], " ", " +"))
    hit = hit.withColumn("q_names", F.array_join(longest, "|"))
    hit = hit.withColumn("q_pattern", F.when(F.col("q_names") != "", F.concat(F.lit(MENTION + r"|(?<!\p{L})(?:"), "q_names", F.lit(r")(?!\p{L})"))).otherwise(F.lit(MENTION)))
    hit = hit.withColumn("q_said", F.when(F.col("q_names") != "", F.coalesce(F.regexp_extract_all("q_text", F.col("q_pattern"), F.lit(0)), none)).otherwise(F.col("q_said")))
    hit = settle(hit.drop("q_names").withColumn("q_row", F.monotonically_increasing_id()))

    said = hit.select("q_row", F.posexplode("q_said").alias("at", "mention"))
    said = said.withColumn("kind", type_of(F.col("mention")))
    said = said.withColumns({"entity": entity_of(F.col("kind"), F.col("mention")), "gender": gender_of(F.col("kind"), F.col("mention")), "part": salt_of(F.col("q_row"), salts=salts)})
    cells = settle(said.groupBy("kind", "entity", "gender", "part").agg(F.count("*").alias("n")).drop("n"))
    # a name's gender over the corpus; one of both genders stands for several people
    known = cells.groupBy("kind", "entity").agg(F.max(F.when(F.col("gender") != "u", F.col("gender"))).alias("most"), F.min(F.when(F.col("gender") != "u", F.col("gender"))).alias("least"))
    both = F.col("most") != F.col("least")
    who = F.when(F.col("kind") == "name", F.concat(F.when(F.coalesce(both, F.lit(False)), F.col("gender")).otherwise(F.coalesce("most", F.lit("u"))), F.lit(":"), F.col("entity"))).otherwise(F.col("entity"))
    cells = cells.join(known, ["kind", "entity"]).withColumn("who", who).select("kind", "entity", "gender", "part", "who")
    drawn = draw(cells.select("kind", F.col("who").alias("entity")).distinct(), key).withColumnRenamed("entity", "who")
    cores = cells.join(drawn, ["kind", "who"]).drop("who")
    new = said.join(cores, ["kind", "entity", "gender", "part"]).select("q_row", "at", rendered(F.col("kind"), F.col("mention"), F.col("core")).alias("new"))
    new = new.groupBy("q_row").agg(F.array_sort(F.collect_list(F.struct("at", "new"))).alias("new"))
    gaps = F.split("q_text", F.col("q_pattern"), -1)
    text = F.array_join(F.transform(F.arrays_zip(gaps.alias("gap"), F.col("new.new").alias("new")), lambda x: F.concat(x["gap"], F.coalesce(x["new"], F.lit("")))), "")
    own = [F.col(f"c_{c}").alias(c) for c in carry]
    replaced = hit.join(new, "q_row").select(F.col("q_id").alias(id_col), *own, text.alias("text"), F.size("new").cast("long").alias("n_replaced"))
    return rows.where(~found).select(F.col("q_id").alias(id_col), *own, F.col("q_text").alias("text"), F.lit(0).cast("long").alias("n_replaced")).union(replaced)
