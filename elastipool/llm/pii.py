"""Personal data replaced by surrogates, with DataFrame functions only.

Detected: e-mail addresses, secrets after a keyword, access keys, bank accounts, IPv4 addresses, payment cards, social-security numbers, phone
numbers, and names after a title; keywords and titles in any case. Each gets a replacement that is keyed (a secret decides it), type-consistent and alike in format: letters stay letters of their
script and case, digits stay digits, separators, top-level domains, country codes and card brands stay, cards that pass the Luhn check still do, and a name
keeps its title and the gender the title tells.

*Coreference*: the replacement depends on the entity's normal form only, so an entity gets one replacement in all documents however it is
punctuated. *Distinctness*: the distinct entities of the whole corpus are compared by their replacements; where two would share one, or one equals an
entity of the corpus, all but the least normal form move on to another attempt, until none collide (after ``ATTEMPTS`` rounds what is left stays, which needs a format with hardly more replacements than entities). The few that moved are joined back by text; all
others need no join, so documents are rewritten map-only.

Null texts stay null, empty ones empty; texts without entities are unchanged. Repeated rows are rewritten alike. Other columns pass through as they are, whatever their
names; ids are not read. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from elastipool.llm.common import materialise, table

KEY = "rotate-me"
ATTEMPTS = 20

#: Formats of the entities (Java regular expressions), in the order they are tried, and titles.
MALE, FEMALE = ("Mr", "Herr", "Señor", "Sr", "Monsieur"), ("Mrs", "Ms", "Miss", "Frau", "Señora", "Sra", "Madame", "Mme", "Mlle")
_OCTET = r"(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)"
#: In any case, but for "miss" and "ms" in lower case, a verb and a unit.
_TITLES = rf"(?!miss\b|ms\b)(?iu:{'|'.join(MALE + FEMALE)})"
_SECRET = r"(?i:password|passwd|pwd|secret|api[_-]?key|token)[ ]?[=:][ ]?[\"']?"
FORMATS = (
    ("EMAIL", r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}+@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)+"),
    ("SECRET", _SECRET + r"[A-Za-z0-9+/_-]{8,}+"),
    ("ACCESS", r"\b(?:AKIA|ASIA)[0-9A-Z]{16}\b"),
    ("IBAN", r"\b[A-Z]{2}\d{2}(?:[ ]?[A-Z0-9]{4}){2,7}(?:[ ]?[A-Z0-9]{1,3})?\b"),
    ("IP", rf"(?<![\d.])(?:{_OCTET}\.){{3}}{_OCTET}(?!\.?\d)"),
    ("CARD", r"(?<!\d)\d{4}[ -]?\d{4}[ -]?\d{4}[ -]?\d{1,7}(?!\d)"),
    ("SSN", r"(?<!\d)\d{3}-\d{2}-\d{4}(?!\d)"),
    ("PHONE", r"(?<![\w+])(?:\+\d{1,3}[ .-]?)?(?:\(\d{2,4}\)[ .-]?|\d{2,4}[ .-])\d{3,4}[ .-]?\d{3,4}(?!\d)|\+\d{1,3}(?:[ .-]?\d{2,4}){3,5}(?!\d)"),
    ("NAME", rf"\b{_TITLES}\.?[ ]\p{{Lu}}[\p{{L}}’-]++(?:[ ]\p{{Lu}}[\p{{L}}’-]++)?"),
)
PATTERN = "|".join(f"(?:{p})" for _, p in FORMATS)
#: What every format needs somewhere: a text without any of it is not searched.
HINT = rf"[0-9@=:]|AKIA|ASIA|\b{_TITLES}\.?[ ]"
ALPHABETS = (
    (r"^[0-9]$", "0123456789"), (r"^[a-z]$", "abcdefghijklmnopqrstuvwxyz"), (r"^[A-Z]$", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
    (r"^[\p{IsCyrillic}&&\p{Ll}]$", "абвгдежзиклмнопрстуфхцчшэюя"), (r"^[\p{IsCyrillic}&&\p{Lu}]$", "АБВГДЕЖЗИКЛМНОПРСТУФХЦЧШЭЮЯ"),
    (r"^[\p{IsGreek}&&\p{Ll}]$", "αβγδεζηθικλμνξοπρστυφχψω"), (r"^[\p{IsGreek}&&\p{Lu}]$", "ΑΒΓΔΕΖΗΘΙΚΛΜΝΞΟΠΡΣΤΥΦΧΨΩ"),
    (r"^\p{IsHan}$", "李王张刘陈杨赵黄周吴徐孙胡朱高林何郭马罗"), (r"^[\p{IsLatin}&&\p{Ll}]$", "abcdefghijklmnopqrstuvwxyz"), (r"^[\p{IsLatin}&&\p{Lu}]$", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
)
SYLLABLES = ["ba", "be", "ca", "co", "da", "de", "fe", "ga", "ha", "jo", "ka", "la", "le", "li", "lo", "ma", "me", "mi", "na", "ne", "ni", "pa", "ra", "re", "ri", "ro", "sa", "se", "ta", "te", "va", "vi"]


def let(value: Column, body) -> Column:
    """``body(value)`` with value computed once, inside an expression."""
    return F.transform(F.array(value), body)[0]


def kind_of(e: Column) -> Column:
    digits = F.length(F.regexp_replace(e, r"[^0-9]", ""))
    return (
        F.when(e.contains("@"), "EMAIL").when(e.rlike("^" + _SECRET), "SECRET").when(e.rlike(r"^(?:AKIA|ASIA)[0-9A-Z]{16}$"), "ACCESS").when(e.rlike(r"^[A-Z]{2}\d{2}"), "IBAN")
        .when(e.rlike(r"^\d{1,3}(?:\.\d{1,3}){3}$"), "IP").when(e.rlike(r"^\d{3}-\d{2}-\d{4}$"), "SSN").when(e.rlike(r"^\d") & (digits >= 13), "CARD").when(e.rlike(r"^[+(\d]"), "PHONE").otherwise("NAME")
    )


def _code(e: Column) -> Column:
    """Digits of a phone number's country code, '' without one."""
    return F.regexp_extract(e, r"^\+(\d{1,3})(?=[ .(-])", 1)


def _secret_head(e: Column) -> Column:
    return F.regexp_extract(e, f"^({_SECRET})", 1)


def _title(e: Column) -> Column:
    return F.regexp_extract(e, r"^(\S+ )", 1)


def normal(e: Column, kind: Column) -> Column:
    """Normal form: one for all ways to write an entity."""
    digits = F.regexp_replace(e, r"[^0-9]", "")
    female = F.lower(F.regexp_replace(_title(e), r"[. ]", "")).isin(*map(str.lower, FEMALE))
    return (
        F.when(kind == "EMAIL", F.lower(e)).when(kind == "SECRET", F.substring(e, F.length(_secret_head(e)) + 1, F.length(e))).when(kind.isin("CARD", "SSN"), digits)
        .when(kind == "PHONE", F.concat(F.length(_code(e)).cast("string"), F.lit("|"), digits)).when(kind == "IBAN", F.regexp_replace(e, " ", ""))
        .when(kind == "NAME", F.concat(F.when(female, "f").otherwise("m"), F.lit("|"), F.regexp_replace(e, r"^\S+ ", ""))).otherwise(e)
    )


def _r(seed: Column, i: Column, n) -> Column:
    return F.pmod(F.xxhash64(seed, i.cast("long")), F.lit(n) if isinstance(n, int) else n).cast("int")


def _chars(s: Column) -> Column:
    return F.when(F.length(s) > 0, F.split(s, "")).otherwise(F.array().cast("array<string>"))


def _letters(s: Column, seed: Column, keep_from: Column | None = None) -> Column:
    """Each letter and digit to another of its alphabet; the same place and case always to the same. Characters from ``keep_from`` on stay."""

    def one(c, i):
        out = None
        for rule, alphabet in ALPHABETS:
            hit = F.substring(F.lit(alphabet), _r(seed, i, len(alphabet)) + 1, 1)
            out = F.when(c.rlike(rule), hit) if out is None else out.when(c.rlike(rule), hit)
        out = out.otherwise(c)
        return out if keep_from is None else F.when(i >= keep_from, c).otherwise(out)

    return F.array_join(F.transform(_chars(s), one), "")


def _luhn(d: Column, n: Column) -> Column:
    """Luhn sum of the digits (array of int) of a number of n digits, from the left."""
    weighed = F.transform(d, lambda x, i: F.when((n - 1 - i) % 2 == 1, F.when(x > 4, x * 2 - 9).otherwise(x * 2)).otherwise(x))
    return F.aggregate(weighed, F.lit(0), lambda a, x: a + x)


def _digits(digits: Column, seed: Column, keep: Column, card: bool) -> Column:
    """Replacement of a string of digits; the first ``keep`` stay."""

    def one(c, i):
        return F.when(i < keep, c.cast("int")).when((c != "0") & (i == keep), _r(seed, i, 9) + 1).otherwise(_r(seed, i, 10))

    got = F.transform(_chars(digits), one)
    if card:
        n = F.length(digits)
        old = F.transform(_chars(digits), lambda c: c.cast("int"))

        def checked(d):
            body = F.slice(d, 1, n - 1)
            return F.concat(body, F.array(F.pmod(F.lit(10) - _luhn(body, n) % 10, F.lit(10))))

        got = F.when(_luhn(old, n) % 10 == 0, let(got, checked)).otherwise(got)
    return F.array_join(got.cast("array<string>"), "")


def _hex(s: Column, seed: Column) -> Column:
    """Hex digits of the case of s."""
    made = F.array_join(F.transform(_chars(s), lambda c, i: F.substring(F.lit("0123456789abcdef"), _r(seed, i, 16) + 1, 1)), "")
    return F.when(s.rlike("[A-F]"), F.upper(made)).otherwise(made)


def _filled(form: Column, marks: Column, place: str = "[0-9]") -> Column:
    """The marks put one by one into the places of ``form`` that match."""
    nth = lambda i: F.size(F.regexp_extract_all(F.substring(form, F.lit(1), i + 1), F.lit(place), F.lit(0)))
    return F.array_join(F.transform(_chars(form), lambda c, i: F.when(c.rlike(f"^{place}$"), F.substring(marks, nth(i), F.lit(1))).otherwise(c)), "")


def _name(rest: Column, norm: Column, seed: Column) -> Column:
    """A made-up name of as many words; of the same script where that is not Latin, with the last letter kept."""

    def word(w, i):
        made = F.array_join(F.transform(F.sequence(F.lit(0), 2 + _r(seed, i * 7 + 5, 2)), lambda k: F.element_at(F.array(*map(F.lit, SYLLABLES)), _r(seed, i * 7 + k, len(SYLLABLES)) + 1)), "")
        end = F.when(norm.startswith("f|"), "na").otherwise("no")
        latin = F.initcap(F.when(i == 0, F.concat(made, end)).otherwise(F.concat(made, F.lit("r"))))
        return F.when(w.rlike(r"^[\p{IsLatin}’-]+$"), latin).otherwise(_letters(w, F.concat(seed, i.cast("string")), F.length(w) - 1))

    return F.array_join(F.transform(F.split(rest, " "), word), " ")


def surrogate(e: Column, kind: Column, norm: Column, attempt: Column, key: str) -> Column:
    """Replacement of an entity as written."""

    def made(seed):
        digits = F.regexp_replace(e, r"[^0-9]", "")
        card, plain = _digits(norm, seed, F.lit(1), True), _digits(norm, seed, F.lit(0), False)
        phone = _digits(digits, seed, F.substring_index(norm, "|", 1).cast("int"), False)
        tld = F.length(F.substring_index(e, ".", -1))
        head = _secret_head(e)
        iban = _filled(e, F.concat(F.substring(norm, 1, 2), _letters(F.substring(norm, F.lit(3), F.length(norm)), seed)), "[^ ]")
        value = F.when(norm.rlike(r"^(?:[0-9a-f]+|[0-9A-F]+)$"), _hex(norm, seed)).otherwise(_letters(norm, seed))
        return (
            F.when(kind == "EMAIL", _letters(e, seed, F.length(e) - tld))
            .when(kind == "SECRET", F.concat(head, value)).when(kind == "ACCESS", F.concat(F.substring(e, 1, 4), _letters(F.substring(e, 5, 16), seed))).when(kind == "IBAN", iban)
            .when(kind == "IP", F.array_join(F.transform(F.split(e, r"\."), lambda o, i: (_r(seed, i, 254) + 1).cast("string")), ".")).when(kind == "CARD", _filled(e, card)).when(kind == "SSN", _filled(e, plain))
            .when(kind == "PHONE", _filled(e, phone)).otherwise(F.concat(_title(e), _name(F.regexp_replace(e, r"^\S+ ", ""), norm, seed)))
        )

    return let(F.sha2(F.concat_ws("|", F.lit(key), kind, norm, attempt.cast("string")), 256), made)


def entities(text: Column) -> Column:
    """Array of (e, t, n): entities as written, their kinds and normal forms, in text order."""
    matches = F.when(text.rlike(HINT), F.regexp_extract_all(text, F.lit(PATTERN), F.lit(0))).otherwise(F.when(text.isNotNull(), F.array().cast("array<string>")))
    found = F.transform(matches, lambda e: F.struct(e.alias("e"), kind_of(e).alias("t")))
    return F.transform(found, lambda x: F.struct(x["e"].alias("e"), x["t"].alias("t"), normal(x["e"], x["t"]).alias("n")))


def _key_of(x) -> Column:
    return F.concat(x["t"], F.lit("|"), x["n"])


def rewritten(text: Column, attempts: Column | None, key: str) -> Column:
    """(n, text): number of entities and the text with each replaced. Gaps and entities come from the same pattern, so they alternate."""

    def put(found):
        def one(gap, x):
            n = F.lit(0) if attempts is None else F.coalesce(F.element_at(attempts, _key_of(x)), F.lit(0))
            return F.when(x.isNull(), gap).otherwise(F.concat(gap, surrogate(x["e"], x["t"], x["n"], n, key)))

        new = F.when(F.size(found) == 0, text).otherwise(F.array_join(F.zip_with(F.split(text, PATTERN, -1), found, one), ""))
        return F.struct(F.size(found).alias("n"), new.alias("text"))

    return F.when(text.isNull(), F.struct(F.lit(0).alias("n"), text.alias("text"))).otherwise(let(entities(text), put))


def moved(docs: DataFrame, text: Column, key: str) -> DataFrame | None:
    """(k, attempt) of the entities whose first replacement collides; None if there is none."""
    x = F.explode(F.array_distinct(F.transform(entities(text), lambda x: F.struct(x["t"].alias("t"), x["n"].alias("n"), F.when(x["t"].isin("CARD", "SSN", "IBAN"), x["n"]).when(x["t"] == "PHONE", _canon(x["n"])).when(x["t"] == "NAME", F.concat(_title_of(x["n"]), F.substring_index(x["n"], "|", -1))).when(x["t"] == "SECRET", F.concat(F.lit("token="), x["n"])).when(x["t"] == "EMAIL", x["n"]).otherwise(x["e"]).alias("form")))))
    ents = materialise(docs.select(x.alias("x")).select("x.*").distinct(), "entities")
    tries, known = ents.withColumn("attempt", F.lit(0)), None
    for _ in range(ATTEMPTS):
        now = tries.withColumn("s", surrogate(F.col("form"), F.col("t"), F.col("n"), F.col("attempt"), key))
        taken = now.select("t", F.col("s").alias("form"), F.lit(False).alias("real"), F.col("n").alias("owner")).union(ents.select("t", "form", F.lit(True), F.lit(None).cast("string")))
        clash = taken.groupBy("t", "form").agg(F.max("real").alias("real"), F.min("owner").alias("low"), F.count("owner").alias("owners")).where((F.col("owners") > 1) | (F.col("real") & (F.col("owners") > 0)))
        lose = now.join(clash.select("t", F.col("form").alias("s"), "real", "low"), ["t", "s"]).where(F.col("real") | (F.col("n") != F.col("low"))).select("t", "n", F.lit(1).alias("up"))
        lose = materialise(lose.distinct(), "clashes")
        if lose.isEmpty():
            break
        tries = tries.join(lose, ["t", "n"], "left").select("t", "n", "form", (F.col("attempt") + F.coalesce("up", F.lit(0))).alias("attempt"))
        known = tries = materialise(tries, "attempts")
    return None if known is None else known.where("attempt > 0").select(F.concat("t", F.lit("|"), "n").alias("k"), "attempt")


def _canon(n: Column) -> Column:
    """A phone number's normal form as written plainly."""
    code, digits = F.substring_index(n, "|", 1).cast("int"), F.substring_index(n, "|", -1)
    return F.when(code > 0, F.concat(F.lit("+"), F.substring(digits, F.lit(1), code), F.lit(" "), F.substring(digits, code + 1, F.length(digits)))).otherwise(digits)


def _title_of(n: Column) -> Column:
    return F.when(n.startswith("f|"), "Ms ").otherwise("Mr ")


def redacted(docs: DataFrame, text_col: str = "text", key: str = KEY, count_col: str | None = None) -> DataFrame:
    """``docs`` with every entity of the text replaced; other columns as they are, and the number of entities if ``count_col`` is given."""
    text = docs[text_col].cast("string")
    over = moved(docs, text, key)
    own = "made"
    while own in docs.columns:
        own += "_"
    if over is None:
        made = rewritten(text, None, key)
        rows = docs.select(*[docs[c] for c in docs.columns if c != text_col], made.alias(own))
    else:
        keys = docs.where(text.isNotNull()).select(F.md5(text.cast("binary")).alias("h"), F.explode(F.array_distinct(F.transform(entities(text), _key_of))).alias("k"))
        by_text = keys.join(over, "k").groupBy("h").agg(F.map_from_entries(F.collect_set(F.struct("k", "attempt"))).alias("attempts"))
        whole = docs.select(F.struct("*").alias("row"), F.md5(text.cast("binary")).alias("h"), text.alias("text")).join(by_text, "h", "left")
        rows = whole.select(*[F.col("row")[c].alias(c) for c in docs.columns if c != text_col], rewritten(F.col("text"), F.coalesce("attempts", F.create_map().cast("map<string,int>")), key).alias(own))
    out = [F.col(own)["text"].alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns]
    return rows.select(*out, *([F.col(own)["n"].alias(count_col)] if count_col else []))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return redacted(table(spark, sf_dir, "documents", "doc_id", "text"), count_col="n_entities")

