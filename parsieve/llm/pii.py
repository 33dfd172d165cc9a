"""PII surrogates with DataFrame operations only.

Entities found by one pattern get keyed replacements of their own kind: digits for digits
and letters for letters in the same format (an address stays one, a card number keeps its
check digit's validity), given names by gender and script of the title and name. The
replacement is a function of key, entity and attempt; over the table of distinct entities
attempts go up until replacements are distinct and none is itself an entity, so equal
entities stay equal and different ones different across the corpus. What still clashes after
ATTEMPTS, or has nothing to replace, leaves the exact format: it gets a keyed token
besides, which grows with every further attempt, so no corpus runs out of replacements.
A person is a title, given names and a family name, of which the names are entities of
their own: "Mr John Smith" and "Mr Smith" get one family name, as do two titles of it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from parsieve.llm.common import Cuts

# Titles by gender, and names to draw from by script and gender.
MALE_TITLES = "Mr Mister Herr Señor Sr Monsieur Don Господин Г-н".split()
FEMALE_TITLES = "Mrs Ms Miss Frau Señora Sra Madame Mme Mlle Doña Госпожа Г-жа".split()
NAMES = {
    ("latin", "m"): "Aldo Boris Carl David Emil Felix Georg Hugo Ivan Jonas Karl Leon Marco Nils Otto Paul Quentin Rolf Simon Theo".split(),
    ("latin", "f"): "Anna Berta Clara Diana Elena Flora Greta Helga Irene Julia Klara Laura Maria Nora Olga Petra Rosa Sofia Tina Vera".split(),
    ("cyrillic", "m"): "Антон Борис Виктор Глеб Денис Егор Иван Кирилл Лев Максим".split(),
    ("cyrillic", "f"): "Анна Вера Галина Дарья Елена Инна Ирина Ксения Лидия Мария".split(),
    ("latin", "s"): "Abel Brandt Castel Dorn Engel Falk Grau Holm Iversen Jansen Keller Lund Moreau Nolan Ortega Prado Quist Romero Stark Thal".split(),
    ("cyrillic", "s"): "Абрамов Белов Волков Громов Дроздов Ершов Жуков Зимин Котов Лебедев".split(),
}
_TITLES = "|".join(MALE_TITLES + FEMALE_TITLES)
_WORD = r"\p{Lu}\p{Ll}+(?:[-’']\p{Lu}\p{Ll}+)*"
_NAME = rf"{_WORD}(?: {_WORD}){{0,2}}"
EMAIL = r"(?<![\p{L}\p{N}._%+-])[\p{L}\p{N}._%+-]++@[\p{L}\p{N}-]++(?:\.[\p{L}\p{N}-]++)+"
PHONE = r"(?<![\p{L}\p{N}+])\+?\d{1,3}[ .-]?\(?\d{2,4}\)?[ .-]\d{3,4}[ .-]\d{3,4}(?![\p{L}\p{N}])"
_OCTET = r"(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)"
ADDRESS = rf"(?<![\p{{L}}\p{{N}}.]){_OCTET}(?:\.{_OCTET}){{3}}(?!\.?[\p{{L}}\p{{N}}])"
CARD = r"(?<![\p{L}\p{N}])(?:\d{13,19}|\d{4}(?:[ -]\d{4}){3})(?![\p{L}\p{N}])"
NUMBER = r"(?<![\p{L}\p{N}-])\d{3}-\d{2}-\d{4}(?![\p{L}\p{N}-])"
PERSON = rf"(?<![\p{{L}}\p{{N}}])(?:{_TITLES})\.? {_NAME}"
ANY = "|".join((EMAIL, ADDRESS, CARD, NUMBER, PHONE, PERSON))
HINT = rf"@|\d[\d.() -]{{5}}|(?:{_TITLES})\.? \p{{Lu}}"
ATTEMPTS = 64  # in the entity's own format
TOKEN, TOKEN_STEP = 8, 2  # digits of the token, and more of them for each attempt with it


def kind_of(entity: Column) -> Column:
    whole = lambda p: entity.rlike(f"^(?:{p})$")
    return (
        F.when(entity.contains("@"), "email")
        .when(entity.rlike(r"^\d{1,3}(?:\.\d{1,3}){3}$"), "address")
        .when(whole(NUMBER), "number")
        .when(entity.rlike(r"^(?:\d{13,19}|\d{4}(?:[ -]\d{4}){3})$"), "card")
        .when(entity.rlike(r"^\p{L}"), "person")
        .otherwise("phone")
    )


def _luhn(digits: Column) -> Column:
    """Check sum modulo 10 of an array of digits, the last one with weight one."""
    doubled = F.transform(F.reverse(digits), lambda d, i: F.when(i % 2 == 0, d).otherwise(2 * d - F.when(2 * d > 9, 9).otherwise(0)))
    return F.aggregate(doubled, F.lit(0), lambda a, d: a + d) % 10


def _digits(text: Column) -> Column:
    return F.transform(F.filter(F.split(text, ""), lambda c: c.rlike("^[0-9]$")), lambda c: c.cast("int"))


def _filled(entity: Column, seed: Column) -> Column:
    """Every ASCII digit and letter replaced by a keyed one of its class; other letters by
    keyed ones of the same script and case; all else stays."""
    stream = F.concat(*(F.sha2(F.concat(seed, F.lit(f"/{i}")), 256) for i in range(2)))

    def one(c: Column, i: Column) -> Column:
        # A long entity draws on the stream again, shifted.
        at = (i * 2) % 124 + 1
        n = F.conv(F.substring(stream, at, F.lit(3)), 16, 10).cast("int") + F.floor(i / 62).cast("int")
        pick = lambda first, size: F.char(F.lit(first) + n % size)
        cyr = lambda first: F.substring(F.lit(first), n % 32 + 1, F.lit(1))
        return (
            F.when(c.rlike("^[0-9]$"), (n % 10).cast("string"))
            .when(c.rlike("^[a-z]$"), pick(97, 26))
            .when(c.rlike("^[A-Z]$"), pick(65, 26))
            .when(c.rlike(r"^\p{IsCyrillic}$"), F.when(c == F.lower(c), cyr("абвгдежзийклмнопрстуфхцчшщъыьэюя")).otherwise(cyr("АБВГДЕЖЗИЙКЛМНОПРСТУФХЦЧШЩЪЫЬЭЮЯ")))
            .when(c.rlike(r"^\p{L}$"), F.when(c == F.lower(c), pick(97, 26)).otherwise(pick(65, 26)))
            .otherwise(c)
        )

    return F.array_join(F.transform(F.split(entity, ""), one), "")


def _picked(names: list[str], seed: Column, salt: str) -> Column:
    n = F.pmod(F.xxhash64(seed, F.lit(salt)), F.lit(len(names))).cast("int")
    return F.element_at(F.array(*map(F.lit, names)), n + 1)


def surrogate(entity: Column, kind: Column, key: str, attempt: Column) -> Column:
    seed = F.sha2(F.concat_ws("\x00", F.lit(key), kind, F.lower(entity), attempt.cast("string")), 256)
    octet = lambda i: (F.conv(F.substring(seed, 1 + 4 * i, 4), 16, 10).cast("int") % 254 + 1).cast("string")
    address = F.concat_ws(".", *(octet(i) for i in range(4)))
    # The last label of a mail address, its top domain, stays.
    top = F.regexp_extract(entity, r"\.([\p{L}\p{N}-]+)$", 1)
    email = F.concat(_filled(F.expr("left(entity, length(entity) - length(regexp_extract(entity, '[.]([^.]+)$', 1)))"), seed), top)
    card = _filled(entity, seed)
    off = F.when(_luhn(_digits(entity)) == 0, _luhn(_digits(card))).otherwise(0)
    card = F.concat(F.expr("left(entity, 0)"), F.regexp_replace(card, r".$", ""), ((F.right(card, F.lit(1)).cast("int") + 10 - off) % 10).cast("string"))

    def name(part: str) -> Column:
        """A name of the list, later ones of two to four by hyphens."""
        def of(script: str) -> Column:
            each = [_picked(NAMES[script, part], F.concat(seed, F.lit(str(i))), "name") for i in range(4)]
            return F.concat(each[0], *(F.when(attempt > 2 * (i - 1), F.concat(F.lit("-"), each[i])).otherwise("") for i in range(1, 4)))

        return F.when(entity.rlike(r"\p{IsCyrillic}"), of("cyrillic")).otherwise(of("latin"))

    plain = F.when(kind == "email", email).when(kind == "address", address).when(kind == "card", card)
    return plain.when(kind == "family", name("s")).when(kind == "given_f", name("f")).when(kind == "given_m", name("m")).otherwise(_filled(entity, seed))


def _fixed(entity: Column, kind: Column) -> Column:
    """Whether a mail address has nothing before its last label that could be replaced."""
    return (kind == "email") & ~F.regexp_replace(entity, r"[^.]+$", "").rlike(r"[0-9\p{L}\p{IsCyrillic}]")


def _longer(entity: Column, kind: Column, plain: Column, key: str, attempt: Column, extra: Column) -> Column:
    """The surrogate `plain` with a keyed token: letters at the end of the local part or of
    the name, else a group of digits at the end. Tokens tell case variants apart."""
    seed = F.sha2(F.concat_ws("\x00", F.lit(key), F.lit("token"), kind, entity, attempt.cast("string")), 512)
    hexed = F.substring(seed, F.lit(1), (F.lit(TOKEN) + TOKEN_STEP * extra).cast("int"))
    spelt = lambda letters: F.translate(hexed, "0123456789abcdef", letters)
    latin, cyrillic = spelt("abcdefghijklmnop"), spelt("абвгдежзиклмнопр")
    at = F.instr(plain, "@")
    email = F.concat(F.substring(plain, F.lit(1), at - 1), latin, F.substring(plain, at, F.length(plain)))
    name = F.concat(plain, F.when(plain.rlike(r"\p{IsCyrillic}$"), cyrillic).otherwise(latin))
    return F.when(kind == "email", email).when(kind.isin("family", "given_f", "given_m"), name).otherwise(F.concat(plain, F.lit("-"), spelt("0123456789012345")))


def _tried(rows: DataFrame, key: str) -> DataFrame:
    """entity, kind, attempt with the surrogate of that attempt."""
    entity, kind, attempt = F.col("entity"), F.col("kind"), F.col("attempt")
    extra = attempt - F.when(_fixed(entity, kind), 0).otherwise(ATTEMPTS)
    plain = rows.select("entity", "kind", "attempt", extra.alias("extra"), surrogate(entity, kind, key, attempt).alias("plain"))
    chosen = F.when(F.col("extra") < 0, F.col("plain")).otherwise(_longer(entity, kind, F.col("plain"), key, attempt, F.col("extra")))
    return plain.select("entity", "kind", "attempt", chosen.alias("surrogate"))


def _parts(persons: DataFrame) -> DataFrame:
    """entity, title, given ('' if there is none), family, given_kind of persons(entity)."""
    entity = F.col("entity")
    title = F.regexp_extract(entity, rf"^((?:{_TITLES})\.? )", 1)
    named = F.regexp_replace(entity, rf"^(?:{_TITLES})\.? ", "")
    female = title.rlike(f"^(?:{'|'.join(FEMALE_TITLES)})\\b")
    return persons.select("entity", title.alias("title"), F.regexp_extract(named, "^(.*) ", 1).alias("given"), F.regexp_extract(named, "([^ ]+)$", 1).alias("family"), F.when(female, "given_f").otherwise("given_m").alias("given_kind"))


def surrogates(spark: SparkSession, entities: DataFrame, key: str) -> DataFrame:
    """(entity, kind, surrogate), distinct and disjoint from the entities, from a table
    of distinct entities. Of those that meet the smallest keeps its attempt. After
    ATTEMPTS rounds each further one draws from a space 256 times (digits: 100 times) the last."""
    cuts = Cuts(spark)
    kinds = cuts.cut(entities.select("entity", kind_of(F.col("entity")).alias("kind")), "kinds")
    persons = _parts(kinds.where("kind = 'person'"))
    names = persons.select(F.explode(F.array(F.struct(F.col("family").alias("entity"), F.lit("family").alias("kind")), F.struct(F.col("given").alias("entity"), F.col("given_kind").alias("kind")))).alias("n")).select("n.*")
    real = kinds.where("kind <> 'person'").union(names.where("entity <> ''").distinct()).withColumn("attempt", F.lit(0))
    real = cuts.cut(real, "entities")
    now = cuts.cut(_tried(real, key), "surrogates")
    while True:
        who = F.concat_ws("\x00", "entity", "kind")
        many = now.groupBy("surrogate").agg(F.count(F.lit(1)).alias("c"), F.min(who).alias("keeper"))
        taken = real.select(F.col("entity").alias("surrogate"), F.lit(True).alias("real")).distinct()
        clash = cuts.cut(many.join(taken, "surrogate", "left").where("c > 1 or real").select("surrogate", "keeper", "real"), "clash")
        if clash.isEmpty():
            break
        moved = now.join(clash, "surrogate", "left")
        again = F.coalesce(F.col("real"), F.col("keeper") != who, F.lit(False))
        step = moved.select("entity", "kind", (F.col("attempt") + again.cast("int")).alias("attempt"))
        after = cuts.cut(_tried(step, key), "surrogates")
        cuts.drop(now, clash)
        now = after
    family = now.where("kind = 'family'").select(F.col("entity").alias("family"), F.col("surrogate").alias("new_family"))
    given = now.where("kind like 'given%'").select(F.col("entity").alias("given"), F.col("kind").alias("given_kind"), F.col("surrogate").alias("new_given"))
    whole = persons.join(family, "family").join(given, ["given", "given_kind"], "left")
    new = F.concat("title", F.coalesce(F.concat("new_given", F.lit(" ")), F.lit("")), "new_family")
    return now.where("kind <> 'family' and kind not like 'given%'").select("entity", "kind", "surrogate").union(whole.select("entity", F.lit("person"), new))


def pseudonymised(spark: SparkSession, docs: DataFrame, key: str = "parsieve") -> DataFrame:
    """doc_id, n_entities, text with surrogates; a row per input row.

    Null texts stay null, texts without an entity as they are and where they are: only rows
    with an entity are written and joined, each under a number of its own, so repeated and
    null doc_ids are rows like any other. The key should be secret and kept: the same key
    gives the same surrogates.
    """
    rows = docs.select("doc_id", "text")
    hinted = F.coalesce(F.col("text").rlike(HINT), F.lit(False))
    found = F.when(hinted, F.regexp_extract_all("text", F.lit(ANY), F.lit(0)))
    cuts = Cuts(spark)
    hit = rows.withColumn("found", found).where(F.size("found") > 0)
    hit = cuts.cut(hit.select(F.monotonically_increasing_id().alias("row"), "doc_id", "text", "found"), "hit")
    mentions = cuts.cut(hit.select("row", F.explode(F.array_distinct("found")).alias("entity")), "mentions")
    table = cuts.cut(surrogates(spark, mentions.select("entity").distinct(), key), "table")
    named = mentions.join(table.hint("merge"), "entity").groupBy("row").agg(F.map_from_entries(F.collect_list(F.struct("entity", "surrogate"))).alias("names"))
    joined = hit.join(named.hint("merge"), "row")
    new = F.transform(F.concat("found", F.array(F.lit(""))), lambda m: F.when(m == "", "").otherwise(F.element_at("names", m)))
    text = F.array_join(F.flatten(F.zip_with(F.split("text", ANY, -1), new, lambda a, b: F.array(a, b))), "")
    plain = rows.where(~hinted | ~F.col("text").rlike(ANY)).select("doc_id", F.lit(0).cast("long").alias("n_entities"), "text")
    return joined.select("doc_id", F.size("found").cast("long").alias("n_entities"), text.alias("text")).union(plain)
