"""Surrogates for personal data, in DataFrame functions only.

Detected entities get keyed replacements of their own type: same digits layout, letter case, script and gender. An entity
has a normal form, so spellings of one entity share a surrogate, under any title; surrogates of distinct entities are checked
over the whole corpus, against each other and against its real entities, and redrawn until none collides. A name found
behind a title is replaced in the rest of its text as well.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from simweave.plans.staging import stage

# Fixed patterns of the entity types, tried in this order at the start of a word.
MALE = "Mr|Herr|Señor|Sr|Monsieur|г-н|господин"
FEMALE = "Mrs|Ms|Miss|Frau|Señora|Sra|Madame|Mme|Mlle|г-жа|госпожа"
NEUTRAL = "Dr|Prof|Professor|Doctor|Doktor"
_OCTET = r"(?:25[0-5]|2[0-4]\d|1?\d?\d)"
PATTERNS = {
    "email": r"[\p{L}\p{N}][\p{L}\p{N}._%+\-]*+@[\p{L}\p{N}\-]++(?:\.[\p{L}\p{N}\-]++)++",
    "ip": rf"{_OCTET}(?:\.{_OCTET}){{3}}(?!\d|\.\d)",
    "card": r"(?:\d{16}|\d{4}-\d{4}-\d{4}-\d{4}|\d{4} \d{4} \d{4} \d{4})(?!\d)",
    "ssn": r"\d{3}-\d{2}-\d{4}(?![\d\-])",
    "iban": r"[A-Z]{2}\d{2}(?:(?: \d{4}){3,6}(?: \d{1,3})?|[A-Z0-9]{11,30})(?![A-Za-z0-9])",
    "phone": r"(?:\+\d{1,3}[ .\-]?(?:\(\d{1,4}\)|\d{1,4})(?:[ .\-]?\d{2,4}){2,4}|\(\d{3}\) ?\d{3}[ \-]\d{4}|\d{3}-\d{3}-\d{4})(?!\d)",
    "secret": r"AKIA[0-9A-Z]{16}(?![0-9A-Za-z])|gh[pousr]_[A-Za-z0-9]{36}|sk-[A-Za-z0-9]{20,}+|(?i:password|passwd|pwd|secret|api[_\-]?key|access[_\-]?key|auth[_\-]?token|token)\s{0,2}[=:]\s{0,2}[\"']?[A-Za-z0-9+/_\-]{8,}+",
    "name": rf"(?:{MALE}|{FEMALE}|{NEUTRAL})\.? \p{{Lu}}[\p{{L}}'’\-]++(?: \p{{Lu}}[\p{{L}}'’\-]++){{0,2}}",
}
ENTITY = r"(?<![\p{L}\p{N}_])(?:" + "|".join(PATTERNS.values()) + ")"

CONSONANTS, VOWELS = "bdfghklmnprstvzj", "aeiouaeiouaeioua"
CYRILLIC_CONSONANTS, CYRILLIC_VOWELS = "бвгджзклмнпрстфх", "аеиоуаеиоуаеиоуа"
GREEK_CONSONANTS, GREEK_VOWELS = "βγδζθκλμνξπρστφχ", "αειουαειουαειουα"
HEX = "0123456789abcdef"
#: Most redrawn entities kept as a literal map; more are joined to the documents instead.
LITERAL_REDRAWS = 10_000


def _let(value: Column, body) -> Column:
    return F.transform(F.array(value), body)[0]


def _draw(key: str, *parts: Column) -> Column:
    """256 keyed bits as hex digits."""
    return F.sha2(F.concat_ws("\x1f", F.lit(key), *(p.cast("string") for p in parts)), 256)


def _permuted_digits(key: str, kind: str | Column, digits: Column, attempt: Column) -> Column:
    """A keyed permutation, for each kind, of the digit strings of one length (34 at most): no two of them share a result."""
    kind = F.lit(kind) if isinstance(kind, str) else kind

    def body(d: Column) -> Column:
        n_left = F.floor(F.length(d) / 2).cast("int")
        n_right = F.length(d) - n_left
        power = lambda n: F.pow(F.lit(10.0), n).cast("long")
        start = F.struct(F.coalesce(F.left(d, n_left).try_cast("long"), F.lit(0)).alias("a"), F.coalesce(F.right(d, n_right).try_cast("long"), F.lit(0)).alias("b"))

        def turn(acc: Column, r: Column) -> Column:
            f = lambda x: F.conv(F.left(_draw(key, kind, F.length(d), attempt, r, x), F.lit(13)), 16, 10).cast("long")
            return F.when(r % 2 == 0, F.struct(((acc["a"] + f(acc["b"])) % power(n_left)).alias("a"), acc["b"].alias("b"))).otherwise(
                F.struct(acc["a"].alias("a"), ((acc["b"] + f(acc["a"])) % power(n_right)).alias("b"))
            )

        done = F.aggregate(F.array(*(F.lit(r) for r in range(6))), start, turn)
        pad = lambda x, n: F.when(n > 0, F.lpad(x.cast("string"), n, F.lit("0"))).otherwise("")
        return _let(done, lambda x: F.concat(pad(x["a"], n_left), pad(x["b"], n_right)))

    return _let(digits, body)


def _syllables(hexes: Column, n: int, like: Column) -> Column:
    """n keyed syllables in the script of like."""
    script = lambda latin, cyrillic, greek: F.when(like.rlike(r"\p{IsCyrillic}"), cyrillic).when(like.rlike(r"\p{IsGreek}"), greek).otherwise(latin)
    part = lambda k, a, b, c: script(*(F.translate(F.substring(hexes, k, 1), HEX, x) for x in (a, b, c)))
    pairs = [(part(1 + 2 * k, CONSONANTS, CYRILLIC_CONSONANTS, GREEK_CONSONANTS), part(2 + 2 * k, VOWELS, CYRILLIC_VOWELS, GREEK_VOWELS)) for k in range(n)]
    return F.concat(*(x for p in pairs for x in p))


def _like_digits(hexes: Column, n: Column) -> Column:
    return F.translate(F.substring(F.repeat(hexes, F.ceil(n / 64).cast("int")), F.lit(1), n), "abcdef", "135792")


def _luhn(digits: Column) -> Column:
    """Luhn sum of a digit string, its last digit undoubled."""
    value = lambda c, i: F.when((F.length(digits) - i) % 2 == 0, _let(c.cast("int") * 2, lambda x: F.when(x > 9, x - 9).otherwise(x))).otherwise(c.cast("int"))
    return F.aggregate(F.transform(F.split(digits, ""), value), F.lit(0), lambda a, x: a + x)


def kind_of(found: Column) -> Column:
    """Type of a matched string; null for a card number without a valid check digit, which is left alone."""
    digits = F.regexp_replace(found, r"\D", "")
    return (
        F.when(found.contains("@"), "email").when(found.rlike(r"^\d{1,3}(\.\d{1,3}){3}$"), "ip")
        .when(found.rlike(r"^(\d{4}[ \-]?){3}\d{4}$"), F.when(_luhn(digits) % 10 == 0, "card"))
        .when(found.rlike(r"^\d{3}-\d{2}-\d{4}$"), "ssn").when(found.rlike(r"^[+(\d]"), "phone").when(found.rlike(r"^[A-Z]{2}\d{2}"), "iban")
        .when(found.rlike(rf"^(?:{MALE}|{FEMALE}|{NEUTRAL})\.? \p{{Lu}}"), "name").otherwise("secret")
    )


_TITLE = rf"^(?:{MALE}|{FEMALE}|{NEUTRAL})\.? "
_SECRET_HEAD = r"^(?:[A-Za-z_\-]+\s{0,2}[=:]\s{0,2}[\"']?|AKIA|gh[pousr]_|sk-)?"


def normal_of(kind: Column, found: Column) -> Column:
    """Normal form: what spellings of one entity have in common."""
    return (
        F.when(kind == "email", F.lower(found)).when(kind == "ip", found).when(kind.isin("card", "ssn", "phone"), F.regexp_replace(found, r"\D", ""))
        .when(kind == "iban", F.regexp_replace(found, " ", ""))
        .when(kind == "name", F.lower(F.regexp_replace(found, _TITLE, "")))
        .otherwise(F.regexp_replace(found, _SECRET_HEAD, ""))
    )


def gender_of(kind: Column, found: Column) -> Column:
    """'m' or 'f' by the title before a name, else 'n'."""
    return F.when(kind != "name", "n").when(found.rlike(rf"^(?:{MALE})\.? "), "m").when(found.rlike(rf"^(?:{FEMALE})\.? "), "f").otherwise("n")


def surrogate_of(key: str, kind: Column, normal: Column, attempt: Column, gender: Column) -> Column:
    """Normal form of the surrogate of a normal form."""

    def email(x: Column) -> Column:
        local, domain = F.regexp_extract(x, "^(.*)@", 1), F.regexp_extract(x, "@(.*)$", 1)

        # the digits of a local part are permuted as one string, so addresses that differ in digits only stay apart
        digits = F.regexp_replace(local, "[^0-9]", "")
        layout = F.concat_ws(" ", F.lit("email"), F.regexp_replace(local, "[0-9]", "0"), domain)
        mixed = F.when(F.length(digits) == 0, "").when(F.length(digits) <= 34, _permuted_digits(key, layout, digits, attempt)).otherwise(_like_digits(_draw(key, F.lit("digits"), attempt, x), F.length(digits)))

        def segment(acc: Column, e: Column) -> Column:
            s, i = e["s"], e["i"]
            letters = F.left(_syllables(_draw(key, F.lit("email"), attempt, i, x), 8, s), F.greatest(F.length(s), F.when(i == 0, 8).otherwise(2)))
            number = s.rlike("^[0-9]")
            put = F.when(s.rlike("^[._%+\\-]"), s).when(number, F.substring(acc["d"], F.lit(1), F.length(s))).otherwise(letters)
            return F.struct(F.concat(acc["o"], put).alias("o"), F.when(number, F.substring(acc["d"], F.length(s) + 1, F.length(acc["d"]))).otherwise(acc["d"]).alias("d"))

        parts = F.regexp_extract_all(local, F.lit(r"([._%+\-]|[0-9]+|[^0-9._%+\-]+)"), F.lit(1))
        numbered = F.transform(parts, lambda s, i: F.struct(s.alias("s"), i.alias("i")))
        filled = _let(mixed, lambda d: F.aggregate(numbered, F.struct(F.lit("").alias("o"), d.alias("d")), segment, lambda acc: acc["o"]))
        labels = F.split(domain, r"\.")
        hosts = F.transform(F.slice(labels, 1, F.size(labels) - 1), lambda s, i: _syllables(_draw(key, F.lit("domain"), i, F.array_join(F.slice(labels, i + 1, F.size(labels)), ".")), 4, s))
        return F.concat(filled, F.lit("@"), F.array_join(hosts, "."), F.lit(".example"))

    def ip(x: Column) -> Column:
        def body(o: Column) -> Column:
            start = F.struct((o[0].cast("int") * 256 + o[1].cast("int")).alias("a"), (o[2].cast("int") * 256 + o[3].cast("int")).alias("b"))

            def turn(acc: Column, r: Column) -> Column:
                f = F.conv(F.left(_draw(key, F.lit("ip"), attempt, r, acc["b"]), F.lit(4)), 16, 10).cast("int")
                return F.struct(acc["b"].alias("a"), acc["a"].bitwiseXOR(f).alias("b"))

            done = F.aggregate(F.array(*(F.lit(r) for r in range(6))), start, turn)
            octets = lambda v: [F.floor(v / 256).cast("int").cast("string"), (v % 256).cast("string")]
            return _let(done, lambda s: F.concat_ws(".", *octets(s["a"]), *octets(s["b"])))

        return _let(F.split(x, r"\."), body)

    def card(x: Column) -> Column:
        body = F.concat(F.left(x, F.lit(1)), _permuted_digits(key, "card", F.substring(x, 2, 14), attempt))
        return _let(body, lambda b: F.concat(b, F.pmod(-_luhn(F.concat(b, F.lit("0"))), F.lit(10)).cast("string")))

    def phone(x: Column) -> Column:
        last = F.right(x, F.least(F.lit(10), F.length(x)))
        head = F.left(x, F.length(x) - F.length(last))
        mixed = _permuted_digits(key, "phone", F.concat(F.left(last, F.lit(3)), F.substring(last, 7, 4)), attempt)
        fiction = _let(mixed, lambda p: F.concat(head, F.left(p, F.lit(3)), F.lit("555"), F.right(p, F.lit(4))))
        return F.when((F.length(last) == 10) & (F.substring(last, 4, 3) == "555"), fiction).otherwise(F.concat(head, _permuted_digits(key, "phone", last, attempt)))

    def iban(x: Column) -> Column:
        return F.concat(F.left(x, F.lit(2)), _like(F.substring(x, 3, 64), "iban", x))

    def _like(s: Column, tag: str, whole: Column) -> Column:
        """Each character replaced within its class."""
        blocks = F.transform(F.sequence(F.lit(0), F.floor(F.length(s) / 64).cast("int")), lambda k: _draw(key, F.lit(tag), attempt, k, whole))
        is_hex = s.rlike("^[0-9a-f]*$")

        def body(h: Column) -> Column:
            def one(c: Column, i: Column) -> Column:
                x = F.substring(h, i + 1, F.lit(1))
                low = F.when(is_hex, F.translate(x, "0123456789", "fedcbafedc")).otherwise(F.translate(x, HEX, "qwrtypsdfghjklzx"))
                return F.when(c.rlike("[0-9]"), F.translate(x, "abcdef", "135792")).when(c.rlike("[a-z]"), low).when(c.rlike("[A-Z]"), F.translate(x, HEX, "QWRTYPSDFGHJKLZX")).otherwise(c)

            return F.array_join(F.transform(F.split(s, ""), one), "")

        return _let(F.array_join(blocks, ""), body)

    def name(x: Column) -> Column:
        words = F.split(x, " ")

        def word(w: Column, i: Column) -> Column:
            given = i < F.size(words) - 1
            stem = _syllables(_draw(key, F.lit("name"), attempt, w), 4, w)
            cyrillic = w.rlike(r"\p{IsCyrillic}")
            first = F.when(gender == "f", F.when(cyrillic, "на").otherwise("na")).when(gender == "m", F.when(cyrillic, "н").otherwise("n")).otherwise(F.when(cyrillic, "ми").otherwise("mi"))
            last = F.when(cyrillic, F.when(gender == "f", "рова").otherwise("ров")).otherwise("r")
            return F.concat(stem, F.when(given, first).otherwise(last))

        return F.array_join(F.transform(words, word), " ")

    return (
        F.when(kind == "email", email(normal)).when(kind == "ip", ip(normal)).when(kind == "card", card(normal))
        .when(kind == "ssn", _permuted_digits(key, "ssn", normal, attempt)).when(kind == "phone", phone(normal)).when(kind == "iban", iban(normal))
        .when(kind == "name", name(normal)).otherwise(_like(normal, "secret", normal))
    )


def _name_like(plain: Column, surrogate: Column) -> Column:
    """A name's surrogate in the letter case of the name, which has no title."""
    return F.when((plain == F.upper(plain)) & (F.length(plain) > 1), F.upper(surrogate)).otherwise(F.initcap(surrogate))


def _render(kind: Column, found: Column, surrogate: Column) -> Column:
    """The surrogate in the layout of the matched string."""
    fill = F.aggregate(
        F.split(found, ""), F.struct(F.lit("").alias("o"), F.lit(1).alias("k")),
        lambda acc, c: F.when(c.rlike("[0-9]"), F.struct(F.concat(acc["o"], F.substring(surrogate, acc["k"], F.lit(1))).alias("o"), (acc["k"] + 1).alias("k")))
        .otherwise(F.struct(F.concat(acc["o"], c).alias("o"), acc["k"].alias("k"))),
        lambda acc: acc["o"],
    )
    spaced = F.aggregate(
        F.split(found, ""), F.struct(F.lit("").alias("o"), F.lit(1).alias("k")),
        lambda acc, c: F.when(c != " ", F.struct(F.concat(acc["o"], F.substring(surrogate, acc["k"], F.lit(1))).alias("o"), (acc["k"] + 1).alias("k")))
        .otherwise(F.struct(F.concat(acc["o"], c).alias("o"), acc["k"].alias("k"))),
        lambda acc: acc["o"],
    )
    return (
        F.when(kind == "email", F.when(found == F.upper(found), F.upper(surrogate)).otherwise(surrogate))
        .when(kind.isin("card", "ssn", "phone"), fill).when(kind == "iban", spaced)
        .when(kind == "name", F.concat(F.regexp_extract(found, _TITLE, 0), _name_like(F.regexp_replace(found, _TITLE, ""), surrogate)))
        .when(kind == "secret", F.concat(F.regexp_extract(found, _SECRET_HEAD, 0), surrogate)).otherwise(surrogate)
    )


def _entities(text: Column) -> Column:
    """found, kind, normal and gender of every match; kind is null for what is left alone."""
    found = F.regexp_extract_all(text, F.lit(f"({ENTITY})"), F.lit(1))
    typed = F.transform(found, lambda m: F.struct(m.alias("found"), kind_of(m).alias("kind")))
    return F.transform(typed, lambda e: F.struct(e["found"].alias("found"), e["kind"].alias("kind"), normal_of(e["kind"], e["found"]).alias("normal"), gender_of(e["kind"], e["found"]).alias("gender")))


def draw_surrogates(docs: DataFrame, key: str, text_col: str = "text", max_redraws: int = 20) -> DataFrame:
    """kind, normal, gender, surrogate (normal form), attempt and told of every distinct entity of the corpus (staged).

    A name's gender is that of its titles in the whole corpus, 'n' if they differ or tell none; told is false where a title
    somewhere tells something else. Of entities that share a surrogate all but the smallest normal form are drawn again, as are
    those whose surrogate is a real entity of the corpus. Surrogates are then distinct, or an error is raised; where a format is so
    full of real entities that max_redraws find no free place, the last draw stays if it is distinct.
    """
    text = F.col(text_col)
    hits = docs.where(text.rlike(ENTITY)).select(F.explode(_entities(text)).alias("e")).where("e.kind is not null")
    man, woman, none = (F.max(F.col("e.gender") == g) for g in "mfn")
    distinct = hits.groupBy("e.kind", "e.normal").agg(man.alias("m"), woman.alias("f"), none.alias("n"))
    gender = F.when(F.col("m") & ~F.col("f"), "m").when(F.col("f") & ~F.col("m"), "f").otherwise("n")
    distinct = distinct.select("kind", "normal", gender.alias("gender"), (F.col("m").cast("int") + F.col("f").cast("int") + F.col("n").cast("int") == 1).alias("told"))
    drawn = stage(distinct.withColumn("attempt", F.lit(0)).withColumn("surrogate", surrogate_of(key, F.col("kind"), F.col("normal"), F.col("attempt"), F.col("gender"))), "entities")
    real = drawn.select(F.col("kind").alias("k"), F.col("normal").alias("real"))
    same = Window.partitionBy("kind", "surrogate").orderBy("attempt", "normal")
    for turn in range(max_redraws + 1):
        judged = drawn.withColumn("again", F.row_number().over(same) > 1)
        judged = judged.join(real, (F.col("kind") == F.col("k")) & (F.col("surrogate") == F.col("real")), "left")
        judged = judged.withColumn("taken", F.col("real").isNotNull()).drop("k", "real")
        clashing = judged.where(F.col("again") | F.col("taken")) if turn < max_redraws else judged.where("again")
        if not clashing.limit(1).count():
            return drawn
        if turn == max_redraws:
            raise RuntimeError("surrogates still collide; use a longer key or more redraws")
        again = clashing.withColumn("attempt", F.col("attempt") + 1)
        again = again.withColumn("surrogate", surrogate_of(key, F.col("kind"), F.col("normal"), F.col("attempt"), F.col("gender")))
        drawn = stage(judged.where(~(F.col("again") | F.col("taken"))).unionByName(again).drop("again", "taken"), "entities")
    return drawn


def _repeats_of_names(text: Column, replaced: Column) -> Column:
    """text with what it says again of its replaced names, without a title: whole names, then last words of three letters or
    more, unless the text has that word in lower case, too, and so uses it as a common word. replaced: found and surrogate."""
    plain = lambda e: F.regexp_replace(e["found"], _TITLE, "")
    names = F.transform(replaced, lambda e: F.struct(plain(e).alias("w"), _name_like(plain(e), e["surrogate"]).alias("r")))
    whole = F.filter(names, lambda p: p["w"].contains(" "))
    last = F.transform(names, lambda p: F.struct(F.element_at(F.split(p["w"], " "), -1).alias("w"), F.element_at(F.split(p["r"], " "), -1).alias("r")))
    before, after = r"(?<![\p{L}\p{N}_'’\-])", r"(?![\p{L}\p{N}_\-])"
    common = lambda p: F.regexp_like(text, F.concat(F.lit(before), F.lower(p["w"]), F.lit(after)))
    last = F.filter(last, lambda p: (F.length(p["w"]) >= 3) & ~common(p))
    pairs = F.concat(F.reverse(F.array_sort(F.array_distinct(whole))), F.array_distinct(last))
    return F.aggregate(pairs, text, lambda acc, p: F.regexp_replace(acc, F.concat(F.lit(before), p["w"], F.lit(after)), p["r"]))


def replace_entities(docs: DataFrame, key: str = "corpus-surrogates", text_col: str = "text", count_col: str | None = "n_entities") -> DataFrame:
    """docs with every detected entity in text_col replaced by its surrogate, and their number in count_col.

    Names count where a title shows them; their repeats in the same text are replaced as well. Null text stays null and counts
    0; texts without entities are returned as they are, byte by byte. All other columns pass through; if one is named like
    count_col, the new one gets an underscore more. Repeated rows are replaced alike, as a surrogate depends on the key and the
    corpus's entities alone. An empty table gives an empty result. A first pass finds the distinct entities; the second replaces
    them in place. Entities drawn again, and names whose titles tell different genders, come to it as a literal table
    if there are at most LITERAL_REDRAWS, else by a join.
    """
    drawn = draw_surrogates(docs, key, text_col)
    special = drawn.where("attempt > 0 or not told").select(F.concat_ws(":", "kind", "normal").alias("k"), F.struct("attempt", "gender").alias("v"))
    known = special.limit(LITERAL_REDRAWS + 1).collect()
    text, own = F.col(text_col), "__surrogate_row"
    if len(known) > LITERAL_REDRAWS:
        docs = stage(docs.withColumn(own, F.monotonically_increasing_id()), "surrogate-docs")
        uses = docs.where(text.rlike(ENTITY)).select(own, F.explode(_entities(text)).alias("e")).select(own, F.concat_ws(":", "e.kind", "e.normal").alias("k")).distinct()
        maps = uses.join(special, "k").groupBy(own).agg(F.map_from_entries(F.collect_list(F.struct("k", "v"))).alias("__special"))
        docs = docs.join(maps, own, "left").drop(own)
        of = lambda k: F.try_element_at(F.col("__special"), k)
    elif known:
        table = F.create_map(*(x for r in known for x in (F.lit(r["k"]), F.struct(F.lit(r["v"]["attempt"]).alias("attempt"), F.lit(r["v"]["gender"]).alias("gender")))))
        of = lambda k: F.try_element_at(table, k)
    else:
        of = None

    def one(e: Column) -> Column:
        if of is None:
            s = surrogate_of(key, e["kind"], e["normal"], F.lit(0), e["gender"])
        else:
            s = _let(of(F.concat_ws(":", e["kind"], e["normal"])), lambda v: surrogate_of(key, e["kind"], e["normal"], F.coalesce(v["attempt"], F.lit(0)), F.coalesce(v["gender"], e["gender"])))
        return F.struct(e["found"].alias("found"), e["kind"].alias("kind"), s.alias("surrogate"))

    def swap(done: Column) -> Column:
        shown = F.transform(done, lambda e: F.when(e["kind"].isNull(), e["found"]).otherwise(_render(e["kind"], e["found"], e["surrogate"])))
        joined = F.array_join(F.zip_with(F.split(text, ENTITY, -1), shown, lambda a, b: F.concat(a, F.coalesce(b, F.lit("")))), "")
        names = F.filter(done, lambda e: F.coalesce(e["kind"] == "name", F.lit(False)))
        return F.when(F.size(names) == 0, joined).otherwise(_let(joined, lambda x: _repeats_of_names(x, names)))

    hit = text.rlike(ENTITY)
    while count_col is not None and count_col in docs.columns:
        count_col += "_"
    counted = docs if count_col is None else docs.withColumn(count_col, F.when(hit, F.size(F.filter(_entities(text), lambda e: e["kind"].isNotNull()))).otherwise(0))
    return counted.withColumn(text_col, F.when(hit, _let(F.transform(_entities(text), one), swap)).otherwise(text)).drop("__special")
