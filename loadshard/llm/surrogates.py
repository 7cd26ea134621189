"""Surrogates for personal data, in DataFrame functions only.

Mentions are found by one alternation of patterns and replaced where they stand. A surrogate is a keyed function
of kind, canonical form and attempt, so that all mentions of an entity agree without a lookup; the table of
entities is used to check that surrogates are distinct and are nobody's real data, and raises the attempt where they
are not. First names and surnames are entities of their own, so that a full name and a surname alone stay one person.
Documents are then joined with the replacements of their own mentions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from loadshard.llm.common import materialize, table, unused

#: Titles by gender, patterns, name pools.
TITLES = {"m": ("Mr", "Herr", "Sr", "Señor", "Monsieur", "Господин"), "f": ("Mrs", "Ms", "Miss", "Frau", "Mme", "Mlle", "Sra", "Señora", "Madame", "Госпожа"), "n": ("Dr", "Prof")}
#: Given names that tell a gender and, before a capitalised word, a name without a title.
GIVEN = {
    "m": "John James Robert Michael William David Thomas Charles Daniel Matthew Anthony Mark Paul Steven Andrew Peter Hans Karl Klaus Jürgen Wolfgang Juan José Carlos Luis Miguel Pedro Javier Jean Pierre Jacques Louis François Michel Иван Сергей Алексей Дмитрий Андрей Николай",
    "f": "Mary Patricia Jennifer Linda Elizabeth Susan Jessica Sarah Karen Nancy Lisa Emily Laura Anna Eva Maria Ursula Monika Petra Sabine Heike Carmen Ana Isabel Lucía Marta Pilar Marie Jeanne Françoise Monique Sophie Camille Мария Елена Ольга Наталья Татьяна Светлана",
}


def _by_initial(words: list[str]) -> str:
    """A pattern of any of the words that tries only those with the right first letter."""
    groups: dict[str, list[str]] = {}
    for w in sorted(words, key=len, reverse=True):
        groups.setdefault(w[0], []).append(w[1:])
    return "(?:" + "|".join(f"{k}(?:{'|'.join(v)})" for k, v in groups.items()) + ")"


EDGE, STOP = r"(?<![\p{L}\p{N}_])", r"(?![\p{L}\p{N}_])"
OCTET = r"(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)"
TITLE = "(?:" + "|".join(sorted((t for v in TITLES.values() for t in v), key=len, reverse=True)) + r")\.?"
NAMED = r"(?=\p{Lu})" + _by_initial([w for v in GIVEN.values() for w in v.split()])
H16 = "[0-9A-Fa-f]{1,4}"
PATTERNS = {
    "email": r"(?<![\p{L}\p{N}._%+-])[\p{L}\p{N}._%+-]++@(?:[\p{L}\p{N}-]+\.)+\p{L}{2,}",
    "name": EDGE + "(?:" + TITLE + r"\x20\p{Lu}[\p{L}'-]+(?:\x20\p{Lu}[\p{L}'-]+)?|" + NAMED + r"\x20\p{Lu}[\p{L}'-]+)",
    "ipv6": r"(?<![\p{L}\p{N}:.])(?=[A-Fa-f:]*[0-9])" + f"(?:(?:{H16}:){{7}}{H16}|(?:{H16}:){{1,6}}(?::{H16}){{1,6}})" + r"(?![\p{L}\p{N}:])",
    "iban": EDGE + r"[A-Z]{2}\d{2}(?:[A-Z0-9]{11,30}|(?:\x20[A-Z0-9]{4}){3,7}(?:\x20[A-Z0-9]{1,3})?)" + STOP,
    "ip": r"(?<![\p{L}\p{N}.])" + f"(?:{OCTET}\\.){{3}}{OCTET}" + r"(?![\p{L}\p{N}]|\.\d)",
    "card": EDGE + r"(?:\d{13,19}|\d{4}\x20\d{4}\x20\d{4}\x20\d{4}|\d{4}-\d{4}-\d{4}-\d{4}|\d{4}[\x20-]\d{6}[\x20-]\d{5})" + STOP,
    "ssn": EDGE + r"\d{3}-\d{2}-\d{4}" + STOP,
    "phone": r"(?<![\p{L}\p{N}+])(?:\+\d{8,15}|(?:\+\d{1,3}[\x20.-]?)?(?:\(\d{2,4}\)[\x20.-]?|\d{2,4}[\x20.-])\d{3,4}[\x20.-]\d{3,4})" + STOP,
}
KINDS = tuple(PATTERNS)
ANY = "|".join(PATTERNS.values())
#: What a text must hold for any pattern to fit; cheap to look for.
HINT = r"[@0-9]|(?:" + TITLE + "|" + EDGE + NAMED + r")\x20\p{Lu}"
ALPHABETS = ("0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "абвгдежзийклмнопрстуфхцчшщъыьэюя", "АБВГДЕЖЗИЙКЛМНОПРСТУФХЦЧШЩЪЫЬЭЮЯ", "αβγδεζηθικλμνξοπρστυφχψω", "ΑΒΓΔΕΖΗΘΙΚΛΜΝΞΟΠΡΣΤΥΦΧΨΩ", "àáâäçèéêëìíîïñòóôöùúûüß", "ÀÁÂÄÇÈÉÊËÌÍÎÏÑÒÓÔÖÙÚÛÜ")
FIRST = {
    ("latin", "m"): "Adam Bruno Carl David Emil Felix Georg Hugo Ivan Jonas Karl Leo Marc Noel Oscar Paul Quentin Ralf Simon Theo Ugo Victor Willy Xaver",
    ("latin", "f"): "Alice Berta Clara Diana Emma Flora Greta Hanna Ida Julia Karla Laura Maria Nora Olga Paula Rita Sara Tina Ursula Vera Wanda Yara Zoe",
    ("cyrillic", "m"): "Антон Борис Виктор Глеб Денис Егор Иван Кирилл Лев Марк Никита Олег Павел Роман Семён Тимур",
    ("cyrillic", "f"): "Анна Вера Галина Дарья Елена Жанна Зоя Ирина Клара Лидия Мария Нина Ольга Полина Рита Софья",
}
SYLLABLES = {"latin": "ba den fel gar hol kin lor mar nes pol ral sen tor ul ver wil ard bei cor dal ern fon gis hem ild jen kas lun mit nor ost per", "cyrillic": "ба вер гор дан жел зар кир лан мор нев ол пет рад сав тим ур фед хар чер шев ал бел вол дор ер кал лог мат ник пол рос сем"}


def kind_of(m: Column) -> Column:
    digits = F.length(F.regexp_replace(m, r"[^0-9]", ""))
    return (
        F.when(m.contains("@"), "email").when(m.rlike(f"^(?:{TITLE}|{NAMED})\\x20"), "name").when(m.rlike("^[0-9A-Fa-f]*:"), "ipv6").when(m.rlike(r"^[A-Z]{2}"), "iban").when(m.rlike(r"^\d{1,3}(\.\d{1,3}){3}$"), "ip")
        .when(m.rlike(r"^\d{3}-\d{2}-\d{4}$"), "ssn").when(~m.rlike(r"^[+(]") & (digits >= 13), "card").otherwise("phone")
    )


def canonical(m: Column, kind: Column) -> Column:
    half = lambda i: F.filter(F.split(F.get(F.split(m, "::"), i), ":"), lambda g: g != "")
    left, right = half(F.lit(0)), F.coalesce(half(F.lit(1)), F.array().cast("array<string>"))
    groups = F.concat(left, F.array_repeat(F.lit("0"), F.greatest(F.lit(0), 8 - F.size(left) - F.size(right))), right)
    ipv6 = F.array_join(F.transform(groups, lambda g: F.regexp_replace(F.lower(g), "^0+(?=.)", "")), ":")
    return F.when(kind.isin("email", "first", "last"), F.lower(m)).when(kind == "iban", F.replace(m, F.lit(" "), F.lit(""))).when(kind == "ipv6", ipv6).when(kind.isin("ip", "name"), m).otherwise(F.regexp_replace(m, "[^0-9]", ""))


def _bytes(*parts: Column) -> Column:
    """128 keyed bytes as 256 hexadecimal digits."""
    seed = F.concat_ws("\x00", *parts)
    return F.concat(F.sha2(seed, 512), F.sha2(F.concat(seed, F.lit("\x01")), 512))


def _byte(stream: Column, i: Column) -> Column:
    return F.conv(F.substring(stream, (i % 64) * 4 + 1, F.lit(4)), 16, 10).cast("int")


def substituted(s: Column, stream: Column, keep_first: bool = False) -> Column:
    """Each letter or digit becomes one of its script and case; its place among letters and digits picks the shift."""

    def one(c: Column, i: Column) -> Column:
        at = F.length(F.regexp_replace(F.substring(s, F.lit(1), i), r"[^\p{L}\p{N}]", ""))
        out = F.when(F.lit(keep_first) & (at == 0), c)
        for alphabet in ALPHABETS:
            a = F.lit(alphabet)
            out = out.when(F.instr(a, c) > 0, F.substring(a, (F.instr(a, c) - 1 + _byte(stream, at)) % len(alphabet) + 1, F.lit(1)))
        return out.otherwise(c)

    return F.array_join(F.transform(F.split(s, ""), one), "")


def luhn_sum(digits: Column, doubled_from: int) -> Column:
    """Sum of digits, each second one doubled, counted from the right; doubled_from 1 for whole numbers, 0 without the last digit."""
    n = F.length(digits)

    def one(d: Column, i: Column) -> Column:
        v = d.cast("int")
        return F.when((n - 1 - i) % 2 == doubled_from, v * 2 - F.when(v > 4, 9).otherwise(0)).otherwise(v)

    return F.aggregate(F.transform(F.filter(F.split(digits, ""), lambda c: c != ""), one), F.lit(0), lambda a, b: a + b)


def _pick(words: str, n: Column) -> Column:
    w = words.split()
    return F.element_at(F.array(*map(F.lit, w)), n % len(w) + 1)


def mod97(iban: Column) -> Column:
    """Remainder of a compact IBAN with its first four characters moved to the end and letters read as 10 to 35."""
    chars = F.split(F.concat(F.substring(iban, F.lit(5), F.length(iban)), F.substring(iban, 1, 4)), "")

    def step(acc: Column, c: Column) -> Column:
        return F.when(c == "", acc).when(c.rlike("[0-9]"), (acc * 10 + F.ascii(c) - 48) % 97).otherwise((acc * 100 + F.ascii(c) - 55) % 97)

    return F.aggregate(chars, F.lit(0), step)


def _made(script: str, stream: Column, size: Column) -> Column:
    """A word of ``size`` syllables."""
    return F.array_join(F.transform(F.sequence(F.lit(1), size), lambda k: _pick(SYLLABLES[script], _byte(stream, k))), "")


def _named(part: Column, kind: Column, canon: Column, stream: Column, attempt: Column) -> Column:
    """First names match gender and script, surnames script; capitals stay capitals. Each attempt after the first adds a
    syllable, so that names never run out."""
    cyrillic = canon.rlike(r"\p{IsCyrillic}")
    out = F.lit(None).cast("string")
    for script in ("latin", "cyrillic"):
        here = cyrillic if script == "cyrillic" else ~cyrillic
        out = F.coalesce(out, F.when(here & (kind == "last"), F.initcap(_made(script, stream, attempt + 3))))
        for g, ending in (("m", ""), ("f", "a" if script == "latin" else "а")):
            fits = here & (kind == "first") & F.startswith(canon, F.lit(g))
            made = F.initcap(F.concat(_made(script, stream, attempt + 1), F.lit(ending)))
            out = F.coalesce(out, F.when(fits, F.when(attempt == 0, _pick(FIRST[script, g], _byte(stream, F.lit(0)))).otherwise(made)))
    return F.when((part == F.upper(part)) & (F.length(part) > 1), F.upper(out)).otherwise(out)


def with_surrogates(ents: DataFrame, key: str) -> DataFrame:
    """Adds s, the replacement of mention m, to rows (m, kind, canon, attempt).

    Each step is a column of its own, so that the plan stays small."""
    m, kind, canon, attempt = (F.col(c) for c in ("m", "kind", "canon", "attempt"))
    email, digits = kind == "email", kind.isin("card", "ssn", "phone")
    out = ents.withColumn("stream", _bytes(F.lit(key), kind, canon, attempt.cast("string")))
    out = out.withColumns({"domain": F.when(email, F.regexp_extract(canon, r"@(.+)\.[^.]+$", 1)), "local": F.when(email, F.regexp_extract(m, "^([^@]+)@", 1))})
    out = out.withColumn("dstream", _bytes(F.lit(key), F.lit("domain"), F.col("domain")))
    # short local parts that run out get longer
    more = F.when(attempt > 4, F.substring(F.regexp_replace("stream", "[^0-9]", ""), F.lit(1), attempt - 4)).otherwise("")
    out = out.withColumns({"local_s": F.concat(substituted(F.col("local"), F.col("stream")), more), "domain_s": substituted(F.col("domain"), F.col("dstream"))})
    # digit kinds: the canonical digits are replaced, a valid check digit is made anew, then all are laid out as in m
    out = out.withColumn("own", F.when(digits, substituted(canon, F.col("stream"), keep_first=True)))
    out = out.withColumn("short", F.substring("own", F.lit(1), F.length("own") - 1)).withColumn("check", ((F.lit(10) - luhn_sum(F.col("short"), 0) % 10) % 10).cast("string"))
    out = out.withColumn("own", F.when((kind == "card") & (luhn_sum(F.when(digits, canon), 1) % 10 == 0), F.concat("short", "check")).otherwise(F.col("own")))
    before = lambda i: F.length(F.regexp_replace(F.substring(m, F.lit(1), i), "[^0-9]", ""))
    out = out.withColumn("laid", F.when(digits, F.array_join(F.transform(F.split(m, ""), lambda c, i: F.when(c.rlike("[0-9]"), F.substring(F.col("own"), before(i) + 1, F.lit(1))).otherwise(c)), "")))
    bban = F.when(kind == "iban", substituted(F.substring(canon, F.lit(3), F.length(canon)), F.col("stream")))
    out = out.withColumn("iban", F.concat(F.substring(canon, 1, 2), bban)).withColumn("bare", F.concat(F.substring("iban", 1, 2), F.lit("00"), F.substring(F.col("iban"), F.lit(5), F.length("iban"))))
    valid = mod97(F.when(kind == "iban", canon)) == 1
    out = out.withColumn("iban", F.when(valid, F.concat(F.substring("iban", 1, 2), F.lpad((98 - mod97(F.col("bare"))).cast("string"), 2, "0"), F.substring(F.col("iban"), F.lit(5), F.length("iban")))).otherwise(F.col("iban")))
    filled = lambda i: F.length(F.replace(F.substring(m, F.lit(1), i), F.lit(" "), F.lit("")))
    out = out.withColumn("iban", F.when(kind == "iban", F.array_join(F.transform(F.split(m, ""), lambda c, i: F.when(c == " ", c).otherwise(F.substring(F.col("iban"), filled(i) + 1, F.lit(1)))), "")))
    ip = F.array_join(F.transform(F.sequence(F.lit(0), F.lit(3)), lambda i: (_byte(F.col("stream"), i) % 254 + 1).cast("string")), ".")
    # the prefix of addresses in documentation, then six groups
    ipv6 = F.concat(F.lit("2001:db8:"), F.array_join(F.transform(F.sequence(F.lit(0), F.lit(5)), lambda i: F.substring(F.col("stream"), i * 4 + 1, F.lit(4))), ":"))
    out = out.withColumn("named", F.when(kind.isin("first", "last"), _named(m, kind, canon, F.col("stream"), attempt)))
    whole = F.when(email, F.concat("local_s", F.lit("@"), "domain_s", F.regexp_extract(m, r"(\.[^.]+)$", 1))).when(kind.isin("first", "last"), F.col("named")).when(kind == "ip", ip).when(kind == "ipv6", ipv6)
    return out.select(*ents.columns, whole.when(kind == "iban", F.col("iban")).otherwise(F.col("laid")).alias("s"))


def mentions(text: Column) -> Column:
    return F.when(text.rlike(HINT), F.regexp_extract_all(text, F.lit(ANY), F.lit(0))).otherwise(F.array().cast("array<string>"))


def described(found: DataFrame) -> DataFrame:
    """(whole, m, kind, canon, of): the entities that each distinct mention (m) names. A name has a surname and perhaps a
    first name, of the gender of its title, else of the given name, else of a hash of it; other mentions are one entity.
    ``of`` is the kind of the mention."""
    m = F.col("m")
    words = F.split(F.regexp_replace(m, f"^{TITLE}\\x20", ""), " ")
    title = F.replace(F.regexp_extract(m, f"^{TITLE}", 0), F.lit("."), F.lit(""))
    given = F.get(words, F.lit(0))
    known = {g: [*GIVEN[g].split(), *FIRST["latin", g].split(), *FIRST["cyrillic", g].split()] for g in "mf"}
    told = lambda g: title.isin(*TITLES[g]) | (~title.isin(*TITLES["m"], *TITLES["f"]) & F.initcap(F.lower(given)).isin(*known[g]))
    gender = F.when(told("m"), "m").when(told("f"), "f").otherwise(F.when(F.xxhash64(F.lower(given)) % 2 == 0, "m").otherwise("f"))
    part = lambda p, kind, canon: F.struct(p.alias("m"), kind.alias("kind"), canon.alias("canon"))
    last = part(F.element_at(words, -1), F.lit("last"), F.lower(F.element_at(words, -1)))
    first = part(given, F.lit("first"), F.concat(gender, F.lit("|"), F.lower(given)))
    rows = found.select("m").distinct().withColumn("of", kind_of(m))
    parts = F.when(F.col("of") != "name", F.array(part(m, F.col("of"), canonical(m, F.col("of"))))).when(F.size(words) > 1, F.array(last, first)).otherwise(F.array(last))
    return rows.select(m.alias("whole"), "of", F.explode(parts).alias("x")).select("whole", "of", "x.*")


def replaced(ments: DataFrame, entities: DataFrame, key: str) -> DataFrame:
    """(m, kind, s): the replacement of each described mention. Titles and layout stay."""
    made = with_surrogates(ments.join(entities, ["kind", "canon"]), key)
    part = lambda k: F.max(F.when(F.col("kind") == k, F.col("s")))
    one = made.groupBy("whole", "of").agg(part("first").alias("first"), part("last").alias("last"), F.max("s").alias("s"))
    title = F.regexp_extract("whole", f"^{TITLE}(?=\\x20)", 0)
    name = F.concat_ws(" ", F.when(title != "", title), "first", "last")
    return one.select(F.col("whole").alias("m"), F.col("of").alias("kind"), F.when(F.col("of") == "name", name).otherwise(F.col("s")).alias("s"))


def assign(ments: DataFrame, key: str, max_rounds: int = 24) -> DataFrame:
    """(kind, canon, attempt) for every entity of the mentions (m, kind, canon).

    A surrogate collides if another entity has it or if it is a real entity of the corpus; the entity first in
    canonical order, of those with the fewest attempts, keeps it."""
    ents = materialize(ments.groupBy("kind", "canon").agg(F.min("m").alias("m")).withColumn("attempt", F.lit(0)))
    real = ents.select("kind", F.col("canon").alias("c"), F.lit(True).alias("real"))
    for _ in range(max_rounds):
        names = F.col("kind").isin("first", "last")
        form = canonical(F.col("s"), F.when(names, F.col("kind")).otherwise(kind_of(F.col("s"))))
        made = materialize(with_surrogates(ents, key).withColumn("c", F.when(F.col("kind") == "first", F.concat(F.substring("canon", 1, 2), form)).otherwise(form)))
        rank = F.row_number().over(W.partitionBy("kind", "c").orderBy("attempt", "canon"))
        judged = materialize(made.join(real, ["kind", "c"], "left").withColumn("bad", (rank > 1) | F.col("real").isNotNull()).select("kind", "canon", "m", (F.col("attempt") + F.col("bad").cast("int")).alias("attempt"), "bad"))
        ents = judged.drop("bad")
        if judged.where("bad").isEmpty():
            return ents.select("kind", "canon", "attempt")
    raise RuntimeError("surrogates did not become distinct")


def replace_entities(docs: DataFrame, key: str = "public-demo-key", id_col: str = "doc_id", text_col: str = "text", bound: int = 64 << 20) -> DataFrame:
    """``docs`` with surrogates in ``text_col``, and mentions_ (how many of each kind, in the order of KINDS; with
    further underscores where the input has such a column).

    Null texts stay null and have none. Rows that repeat an id and text are alike. Overlapping matches: the leftmost,
    then the kind first in KINDS. Mentions of one entity in other spellings (case, separators) get one surrogate
    in their own spelling. ``key`` makes surrogates unlinkable to those of another key. Documents meet their
    replacements by a broadcast if all of these, measured, keep within ``bound`` bytes, else by a shuffle."""
    mine, i, k, told, got, swapped, out = unused(docs.columns, "key", "id", "k", "told", "found", "swapped", "mentions_")
    keyed = docs.withColumn(mine, F.xxhash64(text_col))
    found = materialize(keyed.select(F.col(id_col).alias("id"), F.col(mine).alias("key"), F.explode(F.array_distinct(mentions(F.col(text_col)))).alias("m")))
    ments = materialize(described(found))
    forms = materialize(replaced(ments, assign(ments, key), key))
    per = found.join(forms, "m").groupBy("id", "key").agg(F.map_from_entries(F.collect_set(F.struct("m", F.struct("s", "kind")))).alias(told))
    per = materialize(per.select(F.col("id").alias(i), F.col("key").alias(k), told))
    bytes_ = found.agg(F.sum(F.length("m") * 2 + 64)).first()[0] or 0
    per = F.broadcast(per) if 2 * bytes_ <= bound else per
    rows = keyed.join(per, F.col(id_col).eqNullSafe(F.col(i)) & (F.col(mine) == F.col(k)), "left")
    rows = rows.withColumn(got, F.when(F.col(told).isNotNull(), F.regexp_extract_all(F.col(text_col), F.lit(ANY), F.lit(0))))
    rows = rows.withColumn(swapped, F.transform(got, lambda m: F.try_element_at(F.col(told), m)))
    text = F.col(text_col)
    woven = F.array_join(F.zip_with(F.split(text, ANY, -1), F.col(swapped), lambda gap, s: F.concat(F.coalesce(gap, F.lit("")), F.coalesce(s["s"], F.lit("")))), "")
    count = lambda kind: F.coalesce(F.size(F.filter(swapped, lambda x: x["kind"] == kind)), F.lit(0)).cast("long")
    counts = F.array(*(F.when(F.col(got).isNull(), F.lit(0).cast("long")).otherwise(count(kind)) for kind in KINDS))
    return rows.select(*[F.when(F.col(got).isNotNull(), woven).otherwise(text).alias(c) if c == text_col else F.col(c) for c in docs.columns], counts.alias(out))


def op3_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = replace_entities(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", *(F.get("mentions_", F.lit(i)).alias(f"n_{k}") for i, k in enumerate(KINDS)), "text")
