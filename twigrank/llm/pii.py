"""Surrogates for personal data, in DataFrame functions only.

Entities (e-mail and IP addresses, phone, card, social security and account numbers, secret keys, titled names) are found
by one pattern and replaced by keyed surrogates of their type; the name of a person who has a title somewhere in a document is
replaced in the rest of the document too. A surrogate is a function of the key, the type and the
entity's canonical form, so all mentions of an entity get the same one in whatever format they are written; it keeps the
format of the mention: punctuation, length, case, country, check digits, script, and the gender that a name's title tells. Names get
theirs word by word, so that names that share a word stay alike. A table of all distinct entities and words checks that no
two share a surrogate and that none is one of the corpus; those that do get another attempt, and what still collides then
gets the free values of its format by rank, or a longer one where its format is full.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from twigrank.llm.common import mark_in, materialize

# Titles by gender and script, and syllables of invented names.
MALE = ["Mr", "Mister", "Sir", "Herr", "Monsieur", "Señor", "Sr", "Signor", "Господин"]
FEMALE = ["Mrs", "Ms", "Miss", "Madam", "Frau", "Madame", "Mme", "Señora", "Sra", "Signora", "Госпожа"]
LATIN = "ba be bi bo da de di do fa fe fi ga go ka ke ki la le li lo ma me mi mo na ne ni no pa pe ra re ri ro sa se si so ta te ti to va ve vi".split()
CYRILLIC = "ба бе би бо да де ди до ка ке ки ла ле ли ло ма ме ми мо на не ни но па пе ра ре ри ро са се си со та те ти то ва ве ви".split()

EMAIL = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}"
SECRET = r"(?<![A-Za-z0-9])(?:[0-9a-f]{32,}|[0-9A-F]{32,})(?![A-Za-z0-9])"
ACCOUNT = r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])"
ADDRESS = r"(?<![0-9.])(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])(?:\.(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])){3}(?![0-9]|\.[0-9])"
ADDRESS6 = r"(?<![0-9A-Za-z:.])(?:(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}|(?=[0-9A-Fa-f:]*[0-9])(?:[0-9A-Fa-f]{1,4}:){1,6}(?::[0-9A-Fa-f]{1,4}){1,6})(?![0-9A-Za-z:])"
SOCIAL = r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])"
CARD = r"(?<![0-9.+])[0-9](?:[ -]?[0-9]){12,18}(?![0-9])"
PHONE = r"(?<![0-9+])(?:\+?[0-9]{1,3}[ .-]?)?\([0-9]{2,4}\)[ .-]?[0-9]{3,4}[ .-]?[0-9]{3,4}(?![0-9])|\+[0-9]{1,3}(?:[ .-]?[0-9]{2,4}){2,4}(?![0-9])|(?<![0-9-])[0-9]{3}[ .-][0-9]{3}[ .-][0-9]{4}(?![0-9-])"
TITLE = r"(?<!\p{L})(?:" + "|".join(sorted([*MALE, *FEMALE], key=len, reverse=True)) + r")\.? "
NAME = TITLE + r"\p{Lu}\p{L}+(?: \p{Lu}\p{L}+)?"
ANY = "|".join(f"(?:{p})" for p in (EMAIL, SECRET, ACCOUNT, ADDRESS6, ADDRESS, SOCIAL, CARD, PHONE, NAME))
#: What a text must have to hold any entity; most texts stop here.
HINT = r"[0-9@]|" + TITLE
#: Types of the words of names: family names, and given names by gender.
WORDS = ("family", "given_m", "given_f")
TYPES = [("email", EMAIL), ("secret", SECRET), ("account", ACCOUNT), ("address6", ADDRESS6), ("address", ADDRESS), ("social", SOCIAL), ("card", CARD), ("phone", PHONE)]
MAX_ATTEMPTS = 16


def kind(mention: Column) -> Column:
    out = F.when(mention.contains("@"), "email")
    for name, pattern in TYPES[1:]:
        out = out.when(mention.rlike(rf"^(?:{pattern})$"), name)
    return out.otherwise("name")


def canonical(mention: Column, type_: Column) -> Column:
    """The same for all mentions of an entity."""
    digits = F.regexp_replace(mention, "[^0-9]", "")
    gender = F.when(mention.rlike("^(?:" + "|".join(FEMALE) + r")\.? "), "f").otherwise("m")
    return (
        F.when(type_.isin("email", "address6"), F.lower(mention))
        .when(type_.isin("phone", "card", "social"), digits)
        .when(type_ == "account", F.replace(mention, F.lit(" "), F.lit("")))
        .when(type_ == "name", F.concat(gender, F.lit(":"), F.lower(F.regexp_replace(mention, "^" + TITLE, ""))))
        .otherwise(mention)
    )


def units(type_: Column, entity: Column) -> Column:
    """What gets a surrogate of its own: the words of a name, else the entity itself; type and entity of each."""
    words = F.split(F.substring(entity, 3, 1000), " ")
    # the last word is a family name, whatever the gender; words before it are given names of the gender
    of_name = F.transform(words, lambda w, i: F.struct(F.when(i == F.size(words) - 1, "family").otherwise(F.concat(F.lit("given_"), F.substring(entity, 1, 1))).alias("type"), w.alias("entity")))
    return F.when(type_ == "name", of_name).otherwise(F.array(F.struct(type_.alias("type"), entity.alias("entity"))))


def folded(type_: Column, core: Column) -> Column:
    """A surrogate as entities are written: words of names in lower case."""
    return F.when(type_.isin(*WORDS), F.lower(core)).otherwise(core)


def stream(seed: Column, size: Column) -> Column:
    """Hexadecimal digits that only the seed decides, two for each of `size` characters at least."""
    return F.array_join(F.transform(F.sequence(F.lit(0), F.floor(size / 32).cast("int")), lambda b: F.sha2(F.concat_ws("|", seed, b.cast("string")), 256)), "")


def number(hexes: Column, i: Column, below: int) -> Column:
    """The i-th pair of digits (from 0) as a number under `below`."""
    return (F.conv(F.substring(hexes, i * 2 + 1, F.lit(2)), 16, 10).cast("int") % below).cast("int")


def pick(from_: str, k: Column) -> Column:
    return F.substring(F.lit(from_), k + 1, F.lit(1))


def like(text: Column, seed: Column) -> Column:
    """text with each digit and letter exchanged for another of its class; the rest stays."""
    hexes = stream(seed, F.length(text))
    change = lambda c, i: (
        F.when(c.rlike("[0-9]"), pick("0123456789", number(hexes, i, 10)))
        .when(c.rlike("[a-z]"), pick("abcdefghijklmnopqrstuvwxyz", number(hexes, i, 26)))
        .when(c.rlike("[A-Z]"), pick("ABCDEFGHIJKLMNOPQRSTUVWXYZ", number(hexes, i, 26)))
        .otherwise(c)
    )
    return F.array_join(F.transform(F.split(text, ""), change), "")


def luhn(digits: Column) -> Column:
    """The sum that is a multiple of ten for valid card numbers."""
    twice = lambda d: d * 2 - F.when(d > 4, 9).otherwise(0)
    each = F.transform(F.reverse(F.filter(F.split(digits, ""), lambda c: c != "")), lambda c, i: F.when(i % 2 == 1, twice(c.cast("int"))).otherwise(c.cast("int")))
    return F.aggregate(each, F.lit(0), lambda a, x: a + x) % 10


def mod97(text: Column) -> Column:
    """The number of which the check digits of an account make 1; letters count as 10 to 35."""
    step = lambda a, c: F.when(c.rlike("[0-9]"), a * 10 + F.ascii(c) - 48).otherwise(a * 100 + F.ascii(c) - 55) % 97
    return F.aggregate(F.filter(F.split(text, ""), lambda c: c != ""), F.lit(0), step)


def is_valid_account(entity: Column) -> Column:
    return mod97(F.concat(F.substring(entity, 5, 1000), F.substring(entity, 1, 4))) == 1


def account_of(entity: Column, body: Column) -> Column:
    """An account number of the entity's country with another body; valid if the entity is, else with its check digits."""
    country = F.substring(entity, 1, 2)
    check = F.lpad((98 - mod97(F.concat(body, country, F.lit("00")))).cast("string"), 2, "0")
    return F.concat(country, F.when(is_valid_account(entity), check).otherwise(F.substring(entity, 3, 2)), body)


def n_syllables(word: Column) -> Column:
    return F.least(F.lit(4), F.greatest(F.lit(2), F.floor(F.length(word) / 2).cast("int")))


def ending(type_: Column, word: Column) -> Column:
    """Given names end as those of their gender do."""
    cyrillic = word.rlike(r"\p{IsCyrillic}")
    return F.when(type_ == "given_f", F.when(cyrillic, "а").otherwise("a")).when(type_ == "given_m", F.when(cyrillic, "н").otherwise("n")).otherwise("")


def syllables(word: Column, seed: Column, ending: Column) -> Column:
    """An invented word in the script of `word`, with as many syllables as a word of its length has."""
    hexes = stream(seed, F.lit(8))
    n = n_syllables(word)
    of = lambda table: F.array_join(F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.element_at(F.array(*map(F.lit, table)), number(hexes, i, len(table)) + 1)), "")
    return F.initcap(F.concat(F.when(word.rlike(r"\p{IsCyrillic}"), of(CYRILLIC)).otherwise(of(LATIN)), ending))


def new_domain(key: str, address: Column) -> Column:
    """@ and the domain in an e-mail address's surrogate; one domain has one, with the same top level."""
    domain = F.substring_index(address, "@", -1)
    name_of, top = F.regexp_extract(domain, r"^(.*)\.[^.]*$", 1), F.regexp_extract(domain, r"(\.[^.]*)$", 1)
    return F.concat(F.lit("@"), like(name_of, F.concat_ws("|", F.lit(key), F.lit("domain"), domain)), top)


def surrogate(key: str, type_: Column, entity: Column, attempt: Column) -> Column:
    """The canonical surrogate of a unit."""
    seed = F.concat_ws("|", F.lit(key), type_, entity, attempt.cast("string"))
    shuffled = like(entity, seed)
    digits = F.concat(F.substring(entity, 1, 1), F.expr("''"), F.substring(shuffled, 2, 1000))  # the first digit tells country or issuer
    # of a valid card number, the last digit is set to make the surrogate valid
    zero = F.concat(F.substring(digits, F.lit(1), F.length(digits) - 1), F.lit("0"))
    valid = F.concat(F.substring(digits, F.lit(1), F.length(digits) - 1), ((10 - luhn(zero)) % 10).cast("int").cast("string"))
    email = F.concat(like(F.substring_index(entity, "@", 1), seed), new_domain(key, entity))
    hexes = stream(seed, F.length(entity))
    secret = F.array_join(F.transform(F.split(entity, ""), lambda c, i: F.when(c == "", "").when(c.rlike("[A-F]") | (entity == F.upper(entity)), pick("0123456789ABCDEF", number(hexes, i, 16))).otherwise(pick("0123456789abcdef", number(hexes, i, 16)))), "")
    address = F.array_join(F.transform(F.sequence(F.lit(0), F.lit(3)), lambda i: (number(hexes, i, 254) + 1).cast("string")), ".")
    address6 = F.array_join(F.transform(F.split(entity, ""), lambda c, i: F.when(c.rlike("[0-9a-f]"), pick("0123456789abcdef", number(hexes, i, 16))).otherwise(c)), "")
    word = syllables(entity, F.concat_ws("|", F.lit(key), F.lit("word"), entity, attempt.cast("string")), ending(type_, entity))
    return (
        F.when(type_ == "email", email)
        .when(type_ == "secret", secret)
        .when(type_ == "address", address)
        .when(type_ == "address6", address6)
        .when(type_ == "account", account_of(entity, F.substring(shuffled, 5, 1000)))
        .when(type_ == "card", F.when(luhn(entity) == 0, valid).otherwise(digits))
        .when(type_ == "phone", digits)
        .when(type_.isin(*WORDS), word)
        .otherwise(shuffled)
    )


def spelled(places: Column, step, v: Column) -> Column:
    """The number v written into the places, last place first; null if they are too few. step(place, rest) gives the
    characters of a place and how many choices it has."""

    def put(a: Column, place: Column) -> Column:
        chars, base = step(place, a["rest"])
        return F.struct(F.concat(chars, a["out"]).alias("out"), ((a["rest"] - a["rest"] % base) / base).cast("long").alias("rest"))

    end = F.aggregate(F.reverse(places), F.struct(F.lit("").alias("out"), v.cast("long").alias("rest")), put)
    return F.when(end["rest"] == 0, end["out"])


def nth(key: str, type_: Column, entity: Column, extra: int, v: Column) -> Column:
    """The v-th surrogate (from 0) of the unit's format with `extra` characters or syllables more; null past the last."""
    of = lambda chars: lambda place, rest: (F.substring(F.lit(chars), (rest % len(chars)).cast("int") + 1, F.lit(1)), F.lit(len(chars)).cast("long"))
    digit, small, large = of("0123456789"), of("abcdefghijklmnopqrstuvwxyz"), of("ABCDEFGHIJKLMNOPQRSTUVWXYZ")
    choose = lambda k: lambda c, rest: F.when(c.rlike("[0-9]"), digit(c, rest)[k]).when(c.rlike("[a-z]"), small(c, rest)[k]).when(c.rlike("[A-Z]"), large(c, rest)[k]).otherwise((c, F.lit(1).cast("long"))[k])
    written = lambda text: spelled(F.filter(F.split(text, ""), lambda c: c != ""), lambda c, rest: (choose(0)(c, rest), choose(1)(c, rest)), v)
    more = lambda c: F.lit(c * extra)
    pair = lambda table: lambda i, rest: (F.substring(F.lit("".join(table)), (rest % len(table)).cast("int") * 2 + 1, F.lit(2)), F.lit(len(table)).cast("long"))
    each = F.sequence(F.lit(1), n_syllables(entity) + extra)
    word = F.initcap(F.concat(F.when(entity.rlike(r"\p{IsCyrillic}"), spelled(each, pair(CYRILLIC), v)).otherwise(spelled(each, pair(LATIN), v)), ending(type_, entity)))
    first, rest_of = F.substring(entity, 1, 1), F.substring(entity, 2, 1000)
    open_ = F.concat(first, written(F.concat(F.substring(rest_of, F.lit(1), F.length(rest_of) - 1), more("0"))))
    valid = F.concat(open_, ((10 - luhn(F.concat(open_, F.lit("0")))) % 10).cast("int").cast("string"))
    places = F.sequence(F.lit(1), F.length(entity) + extra)
    number_ = spelled(F.sequence(F.lit(1), F.lit(4)), lambda i, rest: (F.concat((rest % 254 + 1).cast("string"), F.when(i < 4, ".").otherwise("")), F.lit(254).cast("long")), v)
    return (
        F.when(type_.isin(*WORDS), word)
        .when(type_ == "email", F.concat(written(F.concat(F.substring_index(entity, "@", 1), more("a"))), new_domain(key, entity)))
        .when(type_ == "secret", F.when(entity == F.upper(entity), spelled(places, of("0123456789ABCDEF"), v)).otherwise(spelled(places, of("0123456789abcdef"), v)))
        .when(type_ == "address", number_)
        .when(type_ == "address6", spelled(F.filter(F.split(entity, ""), lambda c: c != ""), lambda c, rest: (F.when(c.rlike("[0-9a-f]"), of("0123456789abcdef")(c, rest)[0]).otherwise(c), F.when(c.rlike("[0-9a-f]"), 16).otherwise(1).cast("long")), v))
        .when(type_ == "account", account_of(entity, written(F.concat(F.substring(entity, 5, 1000), more("0")))))
        .when((type_ == "card") & (luhn(entity) == 0), valid)
        .when(type_.isin("phone", "card"), F.concat(first, written(F.concat(rest_of, more("0")))))
        .otherwise(written(F.concat(entity, more("0"))))
    )


def shape(type_: Column, value: Column) -> Column:
    """Equal for all values of one format (and maybe of others): nth() of a unit stays within one."""
    classes = lambda text: F.regexp_replace(F.regexp_replace(F.regexp_replace(text, "[0-9]", "0"), "[a-z]", "a"), "[A-Z]", "A")
    length = F.length(value).cast("string")
    return (
        F.when(type_.isin(*WORDS), F.concat(length, value.rlike(r"\p{IsCyrillic}").cast("string")))
        .when(type_ == "email", F.concat(classes(F.substring_index(value, "@", 1)), F.lit("@"), F.substring_index(value, "@", -1)))
        .when(type_.isin("phone", "card"), F.concat(F.substring(value, 1, 1), length))
        .when(type_ == "secret", length)
        .when(type_ == "address", "")
        .when(type_ == "address6", F.regexp_replace(value, "[0-9a-f]", "0"))
        .when(type_ == "account", F.concat(F.substring(value, 1, 2), classes(F.substring(value, 5, 1000))))
        .otherwise(classes(value))
    )


def render(mention: Column, type_: Column, core: Column) -> Column:
    """The surrogate in the format of the mention."""
    chars = F.filter(F.split(mention, ""), lambda c: c != "")
    poured = F.aggregate(  # a longer surrogate's last characters follow
        chars,
        F.struct(F.lit("").alias("out"), F.lit(1).alias("k")),
        lambda a, c: F.when(c.rlike("[0-9A-Za-z]"), F.struct(F.concat(a["out"], F.substring(core, a["k"], F.lit(1))).alias("out"), (a["k"] + 1).alias("k"))).otherwise(F.struct(F.concat(a["out"], c).alias("out"), a["k"].alias("k"))),
        lambda a: F.concat(a["out"], F.substring(core, a["k"], F.length(core))),
    )
    cased = F.array_join(F.transform(F.filter(F.split(core, ""), lambda c: c != ""), lambda c, i: F.when(F.substring(mention, i + 1, F.lit(1)).rlike("[A-Z]"), F.upper(c)).otherwise(c)), "")
    return (
        F.when(type_.isin("phone", "card", "social", "account"), poured)
        .when(type_.isin("email", "address6"), cased)
        .when(type_ == "name", F.concat(F.regexp_extract(mention, "^" + TITLE, 0), F.substring(core, 3, 1000)))
        .otherwise(core)
    )


def mentions(text: Column) -> Column:
    return F.when(text.rlike(HINT), F.regexp_extract_all(text, F.lit(ANY), F.lit(0))).otherwise(F.array().cast("array<string>"))


def colliding(table: DataFrame) -> DataFrame:
    """type and entity of the rows whose core an earlier row of their type has, or is an entity of the type."""
    first = table.groupBy("type", "core").agg(F.min("entity").alias("first"), F.count("*").alias("n")).where("n > 1")
    twice = table.join(first, ["type", "core"]).where("entity <> first").select("type", "entity")
    same = table.withColumn("same", folded(F.col("type"), F.col("core")))
    real = same.join(table.select("type", F.col("entity").alias("same")), ["type", "same"], "left_semi").select("type", "entity")
    return materialize(twice.union(real).distinct())


def ranked_free(table: DataFrame, bad: DataFrame, key: str, extra: int) -> DataFrame:
    """The table with the units of `bad` given free values of their formats, in keyed order; those for which none is left
    keep what they have. Of a format with t values in use, the first t + n hold n free ones, if it has so many."""
    t, e = F.col("type"), F.col("entity")
    same_choice = F.when(t == "card", (luhn(e) == 0).cast("string")).when(t == "account", F.concat(is_valid_account(e).cast("string"), F.when(~is_valid_account(e), F.substring(e, 3, 2)).otherwise(""))).when(t == "secret", (e == F.upper(e)).cast("string")).otherwise("")
    rest = bad.withColumn("shape", shape(t, nth(key, t, e, extra, F.lit(0)))).where("shape is not null").withColumn("choice", same_choice)
    rest = rest.withColumn("r", F.row_number().over(Window.partitionBy("type", "shape", "choice").orderBy(F.sha2(F.concat_ws("|", F.lit(key), "entity"), 256), "entity")))
    kept = table.join(bad, ["type", "entity"], "left_anti")
    used = kept.select("type", folded(t, F.col("core")).alias("value")).union(table.select("type", e.alias("value"))).distinct()
    in_use = used.groupBy("type", shape(t, F.col("value")).alias("shape")).agg(F.count("*").alias("t"))
    formats = rest.groupBy("type", "shape", "choice").agg(F.min("entity").alias("entity"), F.count("*").alias("n"))
    values = formats.join(in_use, ["type", "shape"], "left").withColumn("v", F.explode(F.sequence(F.lit(0).cast("long"), F.coalesce("t", F.lit(0)) + F.col("n") - 1)))
    values = values.withColumn("new", nth(key, t, e, extra, F.col("v"))).where("new is not null").withColumn("value", folded(t, F.col("new"))).join(used, ["type", "value"], "left_anti")
    values = values.select("type", "shape", "choice", "new", F.row_number().over(Window.partitionBy("type", "shape", "choice").orderBy("v")).alias("r"))
    given = rest.join(values, ["type", "shape", "choice", "r"]).select("type", "entity", "new")
    done = table.join(given, ["type", "entity"], "left")
    return materialize(done.select("type", "entity", F.when(F.col("new").isNotNull(), MAX_ATTEMPTS + 1 + extra).otherwise(F.col("attempt")).alias("attempt"), F.coalesce("new", "core").alias("core")))


def dictionary(found: DataFrame, key: str) -> DataFrame:
    """type, entity, attempt and core of every distinct unit of the mentions in found (mention, type), with no core twice in
    a type and none that is an entity."""
    entities = found.select(F.explode(units(F.col("type"), canonical(F.col("mention"), F.col("type")))).alias("unit")).select("unit.type", "unit.entity").distinct()
    table = materialize(entities.withColumn("attempt", F.lit(0)).withColumn("core", surrogate(key, F.col("type"), F.col("entity"), F.col("attempt"))))
    for _ in range(MAX_ATTEMPTS):
        bad = colliding(table)
        if bad.isEmpty():
            return table
        again = table.join(bad.withColumn("again", F.lit(1)), ["type", "entity"], "left").withColumn("attempt", F.col("attempt") + F.coalesce("again", F.lit(0)))
        core = F.when(F.col("again") == 1, surrogate(key, F.col("type"), F.col("entity"), F.col("attempt"))).otherwise(F.col("core"))
        table = materialize(again.select("type", "entity", "attempt", core.alias("core")))
    extra = 0
    while not (bad := colliding(table)).isEmpty():
        if extra > 64:  # only IP addresses cannot get longer: half of all four-part ones would have to be in the corpus
            raise ValueError("surrogates still collide: the corpus holds too many of all IP addresses")
        table, extra = ranked_free(table, bad, key, extra), extra + 1
    return table


def people(names: Column) -> Column:
    """(old, new) of the names and family names in pairs of titled mentions and their surrogates, whole names first."""
    bare = F.transform(names, lambda x: F.struct(F.regexp_replace(x["old"], "^" + TITLE, "").alias("old"), F.regexp_replace(x["new"], "^" + TITLE, "").alias("new")))
    last = F.transform(bare, lambda x: F.struct(F.substring_index(x["old"], " ", -1).alias("old"), F.substring_index(x["new"], " ", -1).alias("new")))
    return F.array_distinct(F.concat(F.filter(bare, lambda x: x["old"].contains(" ")), last))


def replace_pii(docs: DataFrame, key: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text with all entities replaced, and n_entities (matches of the pattern), a row for each row of docs.

    Null and empty texts stay, with 0 entities. Rows that share an id, repeated rows and null ids are treated each. Other
    columns of docs are not read.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    # one row for each mention in a document; distinct ones are aggregated before the shuffle, so a hot entity costs no more
    # than one row a task
    pairs = materialize(rows.select("doc_id", F.explode(F.array_distinct(mentions(F.col("text")))).alias("mention")).withColumn("type", kind(F.col("mention"))))
    later = dictionary(pairs.select("mention", "type").distinct(), key).where("attempt > 0").select("type", "entity", "core")
    # documents that have a unit of a later attempt, with its surrogate; few, and none where nothing collided
    each = pairs.select("doc_id", F.explode(units(F.col("type"), canonical(F.col("mention"), F.col("type")))).alias("unit")).select("doc_id", "unit.type", "unit.entity").distinct()
    cores = each.join(later, ["type", "entity"]).groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct(F.concat_ws("|", "type", "entity"), "core"))).alias("cores"))
    cores = materialize(cores.withColumnRenamed("doc_id", "_id"))
    marked = mark_in(rows, "doc_id", cores.select(F.col("_id").alias("doc_id")), "_maybe")
    some, most = marked.where("_maybe").drop("_maybe"), marked.where("not _maybe").drop("_maybe")
    some = some.join(cores, F.col("doc_id").eqNullSafe(F.col("_id")), "left").drop("_id")
    both = some.unionByName(most.withColumn("cores", F.lit(None).cast("map<string,string>"))).withColumn("mentions", mentions(F.col("text")))

    def replaced(m: Column) -> Column:
        typed = F.transform(F.array(m), lambda x: F.struct(x.alias("m"), kind(x).alias("t")))
        named = F.transform(typed, lambda x: F.struct(x["m"].alias("m"), x["t"].alias("t"), canonical(x["m"], x["t"]).alias("e")))
        core = lambda u: F.coalesce(F.col("cores")[F.concat_ws("|", u["type"], u["entity"])], surrogate(key, u["type"], u["entity"], F.lit(0)))
        whole = lambda x: F.concat(F.when(x["t"] == "name", F.substring(x["e"], 1, 2)).otherwise(""), F.array_join(F.transform(units(x["t"], x["e"]), core), " "))
        cored = F.transform(named, lambda x: F.struct(x["m"].alias("m"), x["t"].alias("t"), whole(x).alias("c")))
        return F.transform(cored, lambda x: render(x["m"], x["t"], x["c"]))[0]

    # between the mentions, the names of people who have a title elsewhere in the document
    swaps = F.transform("mentions", lambda m: F.struct(m.alias("old"), replaced(m).alias("new")))
    known = people(F.filter(swaps, lambda x: x["old"].rlike("^" + TITLE)))
    untitled = lambda part, names: F.aggregate(names, part, lambda a, p: F.regexp_replace(a, F.concat(F.lit(r"(?<!\p{L})"), p["old"], F.lit(r"(?!\p{L})")), p["new"]))
    state = F.struct(F.split("text", ANY, -1).alias("parts"), swaps.alias("swaps"), known.alias("people"))
    text = F.transform(  # an array of one, so that each step is computed once
        F.array(state),
        lambda x: F.array_join(F.zip_with(F.transform(x["parts"], lambda part: untitled(part, x["people"])), F.array_append(F.transform(x["swaps"], lambda y: y["new"]), F.lit("")), lambda a, b: F.concat(a, b)), ""),
    )[0]
    return both.select("doc_id", F.when(F.size("mentions") > 0, text).otherwise(F.col("text")).alias("text"), F.greatest(F.size("mentions"), F.lit(0)).cast("long").alias("n_entities"))
