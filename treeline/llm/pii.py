"""Personal data replaced by keyed surrogates, in DataFrame expressions only.

One pattern finds e-mail addresses, phone, card, social-security, bank-account and IP numbers, quoted secrets, and
names after a title or that begin with a common given name. An entity's surrogate is a function of the key and its
canonical form (lower case, digits only), so one entity is one surrogate in all texts and writings; it keeps kind,
layout, letter case and script, valid check digits stay valid, and a name keeps its title. Given and family names are
entities of their own: who is named in full in one place and by family name in another bears one family name in both,
and the given name's gender, from the title or else the name, is kept. All entities of the corpus are checked for
surrogates that meet: the least entity keeps its surrogate and the others are keyed anew until all differ.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import stored, table

_L = r"\p{L}\p{N}"
#: What each kind looks like. Runs are possessive and bounded so that a long run is read once.
_MALE = ("Mr", "Herr", "Sr", "Señor", "Monsieur", "Господин", "Κύριος")
_FEMALE = ("Mrs", "Ms", "Miss", "Frau", "Mme", "Mlle", "Sra", "Señora", "Madame", "Госпожа", "Κυρία")
_TITLE = rf"(?:{'|'.join(sorted([*_MALE, *_FEMALE, 'Dr', 'Prof', 'Doctor', 'Professor'], key=len, reverse=True))})"
#: Common given names by gender, which begin a name without a title.
_MEN = "Alexander Andrew Anthony Antonio Benjamin Carlos Charles Christopher Daniel David Edward François Friedrich Georg George Hans Heinrich James Javier Jean Johann John José Joseph Juan Jürgen Kevin Klaus Luis Manuel Matthew Michael Miguel Nicholas Pablo Patrick Pedro Peter Philippe Pierre Richard Robert Stefan Steven Thomas William Wolfgang Александр Алексей Андрей Дмитрий Сергей Γιάννης Γεώργιος".split()
_WOMEN = "Alice Amanda Ana Angela Anna Barbara Brigitte Carmen Catherine Charlotte Christine Claudia Dorothy Elizabeth Emily Emma Françoise Isabel Jane Jennifer Jessica Johanna Julia Karen Katharina Laura Linda Lucía Margaret María Marie Mary Michelle Monika Nathalie Olivia Patricia Rachel Rebecca Sabine Sandra Sarah Sophie Susan Teresa Ursula Екатерина Елена Мария Наталья Ольга Ελένη Κατερίνα".split()
_NAMED = rf"(?:{'|'.join(sorted(_MEN + _WOMEN, key=len, reverse=True))})"
#: Where a word with a capital goes before another: only there are titles and names looked for.
_CAPITALS = r"(?<![\p{L}\p{N}])(?=\p{Lu}[\p{L}]++\.? \p{Lu})"
_PART = r"\p{Lu}[\p{L}'\-]++"
PATTERNS = {
    "email": rf"(?<![{_L}._%+\-])[{_L}._%+\-]++@(?:[{_L}\-]{{1,63}}+\.){{1,8}}\p{{L}}{{2,24}}+",
    "iban": r"(?<![\p{L}\p{N}])[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![\p{L}\p{N}])",
    "ssn": r"(?<![\d\-])\d{3}-\d{2}-\d{4}(?![\d\-])",
    "ip": r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)\.){3}(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)(?!\.?\d)",
    "phone": r"(?<![\d+(])(?:\+\d{1,3}[ .\-]?)?(?:\(\d{2,4}\)[ .\-]?|\d{3}[.\-])\d{3,4}[ .\-]\d{4}(?!\d)|(?<![\d+])\+\d{1,3}(?:[ .\-]?\d{2,4}){2,4}(?!\d)",
    "card": r"(?<!\d)(?:\d{13,19}|\d{4}[ \-]\d{4}[ \-]\d{4}[ \-]\d{4}|\d{4}[ \-]\d{6}[ \-]\d{5})(?!\d)",
    "secret": r"(?<=(?i:token|secret|password|passwd|api_key|apikey|key)[ ]{0,2}[:=][ ]{0,2}[\"'])[^\"'\s]{8,}+(?=[\"'])|(?<![\p{L}\p{N}])AKIA[0-9A-Z]{16}(?![\p{L}\p{N}])",
    "name": rf"{_CAPITALS}(?:{_TITLE}\.? {_PART}(?: {_PART})?|{_NAMED} {_PART})",
}
PATTERN = "|".join(PATTERNS.values())
#: A text without any of these holds no entity: all kinds but names and access keys have a digit or an @ or a quote in or
#: before them.
CUE = rf"[0-9@]|[\"']|AKIA|{_CAPITALS}(?:{_TITLE}\.?|{_NAMED}) "
#: Up to so many entities with a surrogate keyed anew are held in expressions; more are joined to the texts.
RENAMED_INLINE = 2_000
#: From this attempt on, surrogates are longer than what they replace, so that no kind of entity can run out of them.
WIDER, ROUNDS = 8, 60

#: Given names and syllables of other names by script and gender, and endings of made-up given names.
_GIVEN = {
    ("latin", "m"): "Adrian Bruno Carl David Emil Felix Hugo Ivan Jonas Leon Martin Oscar Paul Simon Victor".split(),
    ("latin", "f"): "Alma Bianca Clara Diana Elena Flora Greta Helen Irene Julia Laura Maria Nora Olga Vera".split(),
    ("cyrillic", "m"): "Антон Борис Виктор Глеб Денис Егор Иван Максим Олег Павел".split(),
    ("cyrillic", "f"): "Анна Вера Дарья Елена Инна Лидия Мария Нина Ольга Софья".split(),
    ("greek", "m"): "Ανδρέας Γιώργος Δημήτρης Ηλίας Κώστας Λουκάς Μάρκος Νίκος Πέτρος Στέφανος".split(),
    ("greek", "f"): "Άννα Βάσω Γιώτα Δανάη Ελένη Ηρώ Θάλεια Ιωάννα Μαρία Σοφία".split(),
}
_SYLLABLES = {
    "latin": "bal der fin gor han kel lam mor nis per ral sen tor val wen zim".split(),
    "cyrillic": "бал вор гол дан зор кир лес мар нов рад сел тим фед хор чер яр".split(),
    "greek": "βαλ γορ δαν ζερ θολ καρ λεν μορ νικ παλ ραν σαμ τολ φαρ χαλ ψαρ".split(),
}
_ENDINGS = {("latin", "m"): "or", ("latin", "f"): "ia", ("cyrillic", "m"): "ан", ("cyrillic", "f"): "ина", ("greek", "m"): "ος", ("greek", "f"): "ία"}


def kind_of(v: Column) -> Column:
    whole = lambda *names: reduce(lambda a, b: a | b, [v.rlike(f"^(?:{PATTERNS[n]})$") for n in names])
    return (
        F.when(F.contains(v, F.lit("@")) & whole("email"), "email")
        .when(whole("iban"), "iban")
        .when(whole("ssn"), "ssn")
        .when(whole("ip"), "ip")
        .when(whole("phone"), "phone")
        .when(whole("card"), "card")
        .when(whole("name"), "name")
        .otherwise("secret")
    )


def canonical(v: Column, kind: Column) -> Column:
    """One form for all writings of an entity; telling apart kinds."""
    digits = F.regexp_replace(v, "[^0-9]", "")
    form = F.when(kind.isin("email", "given", "family"), F.lower(v)).when(kind.isin("ssn", "phone", "card"), digits).when(kind == "iban", F.replace(v, F.lit(" "), F.lit(""))).otherwise(v)
    return F.concat(kind, F.lit(":"), form)


def entity(u: Column) -> Column:
    """The canonical form of a unit; a given name of either gender is another one."""
    return F.concat(F.coalesce(u["gender"], F.lit("")), canonical(u["value"], u["kind"]))


def _title(v: Column) -> Column:
    return F.regexp_extract(v, rf"^({_TITLE}\.? |)", 1)


def _given_and_family(v: Column) -> Column:
    """The parts of a name after its title: given and family name, or family name alone."""
    return F.split(F.regexp_replace(v, rf"^{_TITLE}\.? ", ""), " ")


def gender(v: Column) -> Column:
    """m or f by the title of a name, or else by its given name, or else as its spelling falls."""
    title, first = F.regexp_extract(v, rf"^({_TITLE})\.? ", 1), _given_and_family(v)[0]
    known = F.when(title.isin(*_MALE), "m").when(title.isin(*_FEMALE), "f").when(first.isin(*_MEN), "m").when(first.isin(*_WOMEN), "f")
    return known.otherwise(F.when(F.crc32(F.lower(first).cast("binary")) % 2 == 0, "m").otherwise("f"))


def units(v: Column) -> Column:
    """What is replaced as one: the parts of a name, or the whole value, as an array of (kind, value, gender)."""

    def unit(kind: Column, value: Column, sex: Column) -> Column:
        return F.struct(kind.alias("kind"), value.alias("value"), sex.alias("gender"))

    none = F.lit(None).cast("string")

    def of_name(p: Column) -> Column:
        family = unit(F.lit("family"), F.element_at(p, -1), none)
        return F.when(F.size(p) > 1, F.array(unit(F.lit("given"), p[0], gender(v)), family)).otherwise(F.array(family))

    return _let(kind_of(v), lambda kind: F.when(kind == "name", _let(_given_and_family(v), of_name)).otherwise(F.array(unit(kind, v, none))))


def _number(h: Column, at: Column) -> Column:
    """A number from 0 to 65535 at a place of the hash."""
    return F.conv(F.substring(h, (at * 4) % 252 + 1, F.lit(4)), 16, 10).cast("int")


def _pick(choices: str, n: Column) -> Column:
    return F.substring(F.lit(choices), n % len(choices) + 1, F.lit(1))


def _scrambled(v: Column, h: Column, hexadecimal: Column) -> Column:
    """Letters and digits replaced by keyed ones of their class; digits by their number among the digits, so that all
    layouts of one number get the same digits."""

    def one(i: Column) -> Column:
        c = F.substring(v, i, F.lit(1))
        n = _number(h, F.length(F.regexp_replace(F.substring(v, F.lit(1), i), r"[^\p{L}0-9]", "")))
        return (
            F.when(hexadecimal & c.rlike("[0-9a-f]"), _pick("0123456789abcdef", n))
            .when(c.rlike("[0-9]"), _pick("0123456789", n))
            .when(c.rlike("[a-z]"), _pick("abcdefghijklmnopqrstuvwxyz", n))
            .when(c.rlike("[A-Z]"), _pick("ABCDEFGHIJKLMNOPQRSTUVWXYZ", n))
            .when(c.rlike(r"\p{IsCyrillic}"), _pick("абвгдежзиклмнопрстуфхцчшэюя", n))
            .when(c.rlike(r"\p{IsGreek}"), _pick("αβγδεζηθικλμνξοπρστυφχψω", n))
            .when(c.rlike(r"\p{L}"), _pick("äéíóöúüñçàèêâô", n))
            .otherwise(c)
        )

    return F.array_join(F.transform(F.sequence(F.lit(1), F.length(v)), one), "")


def _name(u: Column, h: Column, attempt: Column) -> Column:
    """A given or family name: given ones from a list at first, made of syllables where that meets another's."""
    v, family = u["value"], u["kind"] == "family"
    script = F.when(v.rlike(r"^\p{IsCyrillic}"), "cyrillic").when(v.rlike(r"^\p{IsGreek}"), "greek").otherwise("latin")
    style = F.concat_ws(" ", script, u["gender"])  # of a family name, the script alone

    def chosen(of: dict, value) -> Column:
        out = F.lit(None)
        for name, x in of.items():
            out = F.when(style == " ".join(name) if isinstance(name, tuple) else F.startswith(style, F.lit(name)), value(x)).otherwise(out)
        return out

    words = lambda x: F.array(*[F.lit(w) for w in x])
    picked = lambda pool, i: pool[_number(h, i) % F.size(pool)]
    made = _let(chosen(_SYLLABLES, words), lambda own: F.array_join(F.transform(F.sequence(F.lit(1), attempt + 3), lambda i: picked(own, i)), ""))
    made = F.concat(F.initcap(made), F.coalesce(chosen(_ENDINGS, F.lit), F.lit("")))
    out = F.when(~family & (attempt == 0), _let(chosen(_GIVEN, words), lambda pool: picked(pool, F.lit(0)))).otherwise(made)
    return _let(out, lambda s: F.when((F.upper(v) == v) & (F.length(v) > 1), F.upper(s)).otherwise(s))


def _let(x: Column, f) -> Column:
    """f of x, where x is worked out once however often f names it."""
    return F.transform(F.array(x), f)[0]


def _weighed(digits: Column) -> Column:
    """The sum of a number's digits by which card numbers are checked: every second from the right counts twofold."""

    def one(total: Column, i: Column) -> Column:
        d = F.substring(digits, F.length(digits) - i, F.lit(1)).cast("int")
        twice = F.when(d > 4, 2 * d - 9).otherwise(2 * d)
        return total + F.when(i % 2 == 1, twice).otherwise(d)

    return F.aggregate(F.sequence(F.lit(0), F.length(digits) - 1), F.lit(0), one)


def _card(v: Column, mixed: Column) -> Column:
    """mixed with its last digit chosen as the check digit, where v has a right one."""
    digits = lambda x: F.regexp_replace(x, "[^0-9]", "")
    last = r"[0-9](?=[^0-9]*$)"
    right = _weighed(digits(v)) % 10 == 0
    check = ((10 - _weighed(F.regexp_replace(digits(mixed), "[0-9]$", "0")) % 10) % 10).cast("string")
    return F.when(right, F.concat(F.regexp_extract(mixed, rf"(?s)^(.*){last}", 1), check, F.regexp_extract(mixed, r"([^0-9]*)$", 1))).otherwise(mixed)


def _rest(account: Column) -> Column:
    """An account number, its first four letters last, modulo 97, letters counting from 10."""
    x = F.concat(F.substring(account, F.lit(5), F.length(account)), F.substring(account, 1, 4))

    def one(total: Column, i: Column) -> Column:
        c = F.substring(x, i, F.lit(1))
        return F.when(c.rlike("[0-9]"), total * 10 + c.cast("int")).otherwise(total * 100 + F.ascii(c) - 55) % 97

    return F.aggregate(F.sequence(F.lit(1), F.length(x)), F.lit(0), one)


def _account(v: Column, mixed: Column) -> Column:
    """mixed with the check digits that a bank account has, where those of v are right."""
    plain = lambda x: F.replace(x, F.lit(" "), F.lit(""))
    check = 98 - _rest(F.concat(F.substring(mixed, 1, 2), F.lit("00"), F.substring(plain(mixed), F.lit(5), F.length(mixed))))
    new = F.concat(F.substring(mixed, 1, 2), F.lpad(check.cast("string"), 2, "0"), F.substring(mixed, F.lit(5), F.length(mixed)))
    return F.when(_rest(plain(v)) == 1, new).otherwise(mixed)


def surrogate(u: Column, attempt: Column, key: str) -> Column:
    """The surrogate of a unit (kind, value, gender)."""
    seed = F.concat_ws("|", F.lit(key), entity(u), attempt.cast("string"))
    both = _let(seed, lambda s: F.concat(F.sha2(s.cast("binary"), 512), F.sha2(F.concat(s, F.lit("|more")).cast("binary"), 512)))
    return _let(both, lambda h: _surrogate(u, attempt, h))


def _surrogate(u: Column, attempt: Column, h: Column) -> Column:
    """All kinds but IP numbers and names keep a start and have the rest scrambled, so the scrambling stands once."""
    v, kind = u["value"], u["kind"]
    octet = lambda i: (_number(h, F.lit(i)) % 254 + 1).cast("string")
    start = (
        F.when(kind == "ssn", F.lit("9"))
        .when(kind == "iban", F.substring(v, 1, 2))
        .when(kind == "phone", F.regexp_extract(v, r"^(\+\d{1,3}(?=[ .\-(])|)", 1))
        .otherwise(F.lit(""))
    )
    rest = F.when(kind == "email", F.concat(F.regexp_extract(v, r"^([^@]*)@", 1), F.lit("@abcdef"))).otherwise(F.substring(v, F.length(start) + 1, F.length(v)))
    # in pieces, since the work on one grows with the square of its length
    pieces = F.regexp_extract_all(rest, F.lit("(?s).{1,200}"), F.lit(0))
    mixed = F.concat(start, F.array_join(F.transform(pieces, lambda x: _scrambled(x, h, (kind == "secret") & v.rlike("^[0-9a-f]{16,}$"))), ""))
    checked = _let(mixed, lambda m: F.when(kind == "card", _card(v, m)).when(kind == "iban", _account(v, m)).when(kind == "email", F.concat(m, F.lit(".example.org"))).otherwise(m))
    more = F.substring(F.translate(h, "abcdef", "012345"), F.lit(9), attempt)
    wide, mail = attempt >= WIDER, kind == "email"
    return (
        # private addresses, then those of a private network of the longer kind
        F.when((kind == "ip") & ~wide, F.concat_ws(".", F.lit("10"), octet(1), octet(2), octet(3)))
        .when(kind == "ip", F.concat(F.lit("fd00"), F.regexp_replace(F.substring(h, 9, 28), "(.{4})", ":$1")))
        .when(kind.isin("given", "family"), _name(u, h, attempt))
        .otherwise(F.concat(F.when(wide & mail, F.concat(more, F.lit("."))).otherwise(""), checked, F.when(wide & ~mail, F.concat(F.lit("-"), more)).otherwise("")))
    )


def _entities(text: Column) -> Column:
    return F.when(text.rlike(CUE), F.regexp_extract_all(text, F.lit(PATTERN), F.lit(0)))


def _found(docs: DataFrame) -> DataFrame:
    """docs with __found, the entities of text in order, written once so that the pattern runs once over each text."""
    return stored(docs.withColumn("__found", _entities(F.col("text"))), "found")


def entities(docs: DataFrame, key: str) -> DataFrame:
    """entity (canonical form), kind, value, gender, attempt, surrogate (canonical form): all entities of docs (text),
    with surrogates that all differ."""
    return _distinct_surrogates(_found(docs.select("text")), key)


def _distinct_surrogates(found: DataFrame, key: str) -> DataFrame:
    """Only entities whose surrogates meet are looked at again. A surrogate may equal another entity of the corpus,
    which is replaced itself, so the texts that come out never mix two entities."""
    u = found.where(F.size("__found") > 0).select(F.explode("__found").alias("v")).groupBy("v").agg(F.lit(1)).select(F.explode(units(F.col("v"))).alias("u"))
    # the least writing of an entity stands for all; each writing's surrogate has the same letters and digits
    every = u.groupBy(entity(F.col("u")).alias("entity"), "u.kind").agg(F.min(F.struct("u.value", "u.gender")).alias("m"))
    every = stored(every.select("entity", "kind", "m.value", "m.gender", F.lit(0).alias("attempt")), "entities")
    unit = F.struct("kind", "value", "gender")

    def replaced(df: DataFrame) -> Column:
        return canonical(surrogate(unit, F.col("attempt"), key), F.col("kind"))

    named = every.withColumn("surrogate", replaced(every))
    for turn in range(ROUNDS):
        named = stored(named, "surrogates")
        meet = named.groupBy("surrogate").agg(F.count("*").alias("c"), F.min("entity").alias("first")).where("c > 1")
        moved = stored(named.join(meet, "surrogate").where("entity <> first").select("entity"), "met")
        if moved.isEmpty():
            return named
        named = named.join(moved.withColumn("met", F.lit(True)), "entity", "left").withColumn("attempt", F.when(F.col("met"), F.lit(turn + 1)).otherwise(F.col("attempt"))).drop("met")
        named = named.withColumn("surrogate", F.when(F.col("attempt") == turn + 1, replaced(named)).otherwise(F.col("surrogate")))
    raise RuntimeError(f"surrogates still meet after {ROUNDS} rounds")


def with_surrogates(docs: DataFrame, key: str = "treeline") -> DataFrame:
    """docs (text and any other columns) with personal data in text replaced, and n_entities (places replaced).

    The key decides all surrogates: give a secret one and keep it to get equal surrogates in later runs. Null texts
    stay null with n_entities 0, empty texts stay empty; rows that repeat get equal texts; a column n_entities is
    replaced. An empty table comes back empty. Names without a title are found if their given name is a common one; a
    family name that stands alone is left.
    """
    docs = docs.drop("n_entities")
    out = _found(docs)
    renamed = stored(_distinct_surrogates(out.select("__found"), key).where("attempt > 0").select("entity", "attempt"), "renamed")
    n = renamed.count()
    if n > RENAMED_INLINE:
        out = _attempts_joined(out, renamed)
        attempt = lambda e: F.coalesce(F.element_at(F.col("__tries"), e), F.lit(0))
    elif n:
        pairs = [x for r in renamed.collect() for x in (F.lit(r.entity), F.lit(r.attempt))]  # RENAMED_INLINE at most
        attempt = lambda e: F.coalesce(F.element_at(F.create_map(*pairs), e), F.lit(0))
    else:
        attempt = lambda e: F.lit(0)

    def one(v: Column) -> Column:
        new = lambda u: surrogate(u, attempt(entity(u)), key)
        return F.concat(F.when(kind_of(v) == "name", _title(v)).otherwise(F.lit("")), F.array_join(F.transform(units(v), new), " "))

    between = F.split(F.col("text"), PATTERN, -1)
    new = F.array_join(F.zip_with(between, F.transform("__found", one), lambda a, b: F.concat(a, F.coalesce(b, F.lit("")))), "")
    n_found = F.coalesce(F.size("__found"), F.lit(0))
    out = out.withColumn("n_entities", F.when(n_found > 0, n_found).otherwise(0).cast("bigint"))
    out = out.withColumn("text", F.when(F.col("n_entities") > 0, new).otherwise(F.col("text")))
    return out.select(*docs.columns, "n_entities")


def _attempts_joined(out: DataFrame, renamed: DataFrame) -> DataFrame:
    """Adds __tries, a map from entity to attempt of the row's own renamed entities, by joins."""
    out = stored(out.withColumn("__row", F.monotonically_increasing_id()), "rows")
    own = out.select("__row", F.explode("__found").alias("v")).select("__row", F.explode(units(F.col("v"))).alias("u"))
    own = own.select("__row", entity(F.col("u")).alias("entity")).distinct()
    tries = own.join(renamed, "entity").groupBy("__row").agg(F.map_from_entries(F.collect_list(F.struct("entity", "attempt"))).alias("__tries"))
    return out.join(tries, "__row", "left")


def op5_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return with_surrogates(table(spark, sf_dir, "documents").select("doc_id", "text"))
