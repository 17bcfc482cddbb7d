"""Surrogates for personal data, with Spark expressions only.

Detected entities (e-mail addresses, phone numbers, payment card numbers, IPv4 addresses, social security numbers, IBANs and
names after a title) are replaced in place by keyed surrogates of the same type and format. A surrogate depends on the key,
the entity's type and its canonical form alone, so one entity gets one surrogate in all documents and spellings
(coreference), and nothing has to be looked up for most.

* Digit formats are permuted: a four-round keyed Feistel network over the digits that may vary, around a step that moves
  all, so different entities cannot meet and none stays as it is. Separators, country codes, card issuer digit and Luhn remainder, the first octet and reserved exchange
  ``555`` stay (other phones walk on until they are outside it). Octets are kept below 256 by permuting the number the last three make; an IBAN's letters
  move too, and its check digits give the remainder that they gave.
* E-mail addresses and names are drawn by keyed hash: letters stay letters of the same case, digits digits, names keep gender
  (from the title) and script (Latin or Cyrillic). These may collide, so entities are gathered once: where several draw one
  surrogate, or one that is itself an entity of the corpus, all but the first in keyed order draw again, with an
  attempt number. Names still in conflict after the last attempt carry a serial mark of their canonical form.

Only texts with entities are exploded. Conflicts (normally few) are told to a text by the hash of its list of entities: a bitmap
of the lists concerned, a bounded table, picks the rows, which alone meet their conflicts by an exchange, each list dealt into parts.

Defined results: a null text stays null and has no entities; empty texts stay empty; texts are scanned whole; repeated rows
get equal replacements; other columns pass through; results are ``text`` replaced in place and ``n_entities``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

#: What is detected, in order of preference at one position.
PATTERNS = (
    ("email", r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}+@(?:[A-Za-z0-9-]{1,63}\.){1,5}[A-Za-z]{2,24}"),
    ("iban", r"(?<![A-Za-z0-9])[A-Z]{2}(?:0[2-9]|[1-8]\d|9[0-8])(?: ?[A-Z0-9]{4}){2}(?: ?[A-Z0-9]{3}|(?: ?[A-Z0-9]{4}){1,5}(?: ?[A-Z0-9]{1,3})?)(?![A-Za-z0-9])"),
    ("card", r"(?<![\w.])\d{4}([ -]?)\d{4}\1\d{4}\1\d{1,4}(?!\d)"),
    ("ssn", r"(?<![\w-])\d{3}-\d{2}-\d{4}(?![\w-])"),
    ("phone", r"(?<![\w+])(?:\+\d{1,3}[ .-]?)?(?:\(\d{3}\)[ .-]?|\d{3}[ .-])\d{3}[ .-]\d{4}(?!\d)"),
    ("ip", r"(?<![\w.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?![\w]|\.\d)"),
    ("name", r"(?<![\p{L}])(?:Mr|Mrs|Ms|Miss|Dr|Herr|Frau|Monsieur|Madame|Señora|Señor|г-жа|г-н)\.? \p{Lu}\p{Ll}+(?: \p{Lu}\p{Ll}+)?"),
)
#: Titles by gender (Dr is open), and given names of each gender and script.
FEMALE, MALE = ("Mrs", "Ms", "Miss", "Frau", "Madame", "Señora", "г-жа"), ("Mr", "Herr", "Monsieur", "Señor", "г-н")
GIVEN = {
    ("f", "latin"): "Alice Beatrix Camilla Dorothy Emilia Frieda Greta Helena Irma Judith Katja Lydia Monika Nadja Olympia Paula".split(),
    ("m", "latin"): "Albert Boris Casimir David Emil Felix Gustav Hugo Igor Jakob Karl Lukas Magnus Norbert Oskar Paul".split(),
    ("f", "cyrillic"): "Алла Белла Вера Галина Дарья Елена Жанна Зоя Инна Клара Лидия Мария Нина Ольга Полина Рита".split(),
    ("m", "cyrillic"): "Антон Борис Вадим Глеб Денис Егор Захар Иван Кирилл Лев Макар Никита Олег Павел Роман Семён".split(),
}
#: Syllables of drawn surnames.
SYLLABLES = {"latin": "ba ke li mo nu ra se ti vo za der fin gal hol jas kam".split(), "cyrillic": "ба ке ли мо ну ра се ти во за дер фин гал хол яс кам".split()}
ENDINGS = {"latin": "berg dorf feld mann stein wald".split(), "cyrillic": "ский нов рин тов шин ков".split()}

ROUNDS, ATTEMPTS = 4, 4
#: Steps of the cycle walk that keeps other phones out of the reserved exchange; one in 10^12 needs more.
WALKS = 3
#: Bits of the bitmap of entity lists with conflicts (at most 131,072 rows of 64), and parts that a hot list is dealt into.
BITS, SALTS = 1 << 23, 16


def _joined() -> str:
    """One pattern of all kinds; only the card pattern has a group, renumbered by the one around each kind."""
    out, groups = [], 0
    for _, p in PATTERNS:
        inner = p.count("([ -]?)")
        out.append("(" + p.replace(r"\1", rf"\{groups + 2}") + ")")
        groups += 1 + inner
    return "|".join(out)


ANY = _joined()


#: What every entity holds somewhere: an at sign, a digit before a digit or separator, or the start of a title.
HINT = r"@|[0-9][0-9. ()-]|[MDHFSг](?:r|s|iss|err|rau|onsieur|adame|eñor|-)"


def entities(text: Column) -> Column:
    """All entities of a text; the hint, far cheaper than the patterns, spares texts that can have none."""
    return F.when(text.rlike(HINT), F.regexp_extract_all(text, F.lit(ANY), F.lit(0)))


def kind_of(m: Column) -> Column:
    out = F.lit(PATTERNS[-1][0])
    for kind, p in reversed(PATTERNS[:-1]):
        out = F.when(m.rlike("^(?:" + p + ")$"), F.lit(kind)).otherwise(out)
    return out


def canonical(kind: Column, m: Column) -> Column:
    """What makes two spellings one entity."""
    return (
        F.when(kind == "email", F.lower(m))
        .when(kind == "name", F.regexp_replace(m, r"^[^ ]+ ", ""))
        .when(kind == "iban", F.replace(m, F.lit(" "), F.lit("")))
        .when(kind == "ip", m)
        .otherwise(F.regexp_replace(m, r"\D", ""))
    )


def let(value: Column, body) -> Column:
    """``body`` of a value that is worked out once, however often the body uses it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _hash(key: str, *parts: Column) -> Column:
    return F.sha2(F.concat_ws("\x1f", F.lit(key), *parts).cast("binary"), 256)


def _number(h: Column, start: int = 1, digits: int = 12) -> Column:
    """A number from hexadecimal digits of a hash."""
    return F.conv(F.substring(h, start, digits), 16, 10).cast("long")


def _permuted(key: str, kind: Column, digits: Column) -> Column:
    """A permutation of the decimal strings of each length of two or more that leaves none as it is; shorter ones stay.

    Alternating Feistel rounds on the two halves, then a step that moves everything (the right half by a number that is not
    0), then the rounds undone: a permutation conjugate to one without fixed points has none."""
    def cut(d: Column) -> Column:
        half = F.floor(F.length(d) / 2).cast("int")
        return F.struct(F.substr(d, F.lit(1), half).alias("l"), F.substr(d, half + 1).alias("r"))

    def moved(target: Column, shift: Column) -> Column:
        size = F.length(target)
        padded = F.lpad(F.pmod(target.cast("long") + shift, F.pow(F.lit(10.0), size).cast("long")).cast("string"), 20, "0")
        return F.substr(padded, F.lit(21) - size)

    def turn(s: Column, i: Column) -> Column:
        middle, r = i == ROUNDS, F.least(i, 2 * ROUNDS - i)
        left = ~middle & (r % 2 == 0)
        target, source = F.when(left, s["l"]).otherwise(s["r"]), F.when(left, s["r"]).otherwise(s["l"])
        drawn_ = _number(_hash(key, kind, r.cast("string"), source))
        step = 1 + F.pmod(_number(_hash(key, kind, F.lit("step"), F.length(target).cast("string"))), F.pow(F.lit(10.0), F.length(target)).cast("long") - 1)
        to = moved(target, F.when(middle, step).when(i < ROUNDS, drawn_).otherwise(-drawn_))
        return F.struct(F.when(left, to).otherwise(s["l"]).alias("l"), F.when(left, s["r"]).otherwise(to).alias("r"))

    def run(d: Column) -> Column:
        moved_ = F.aggregate(F.sequence(F.lit(0), F.lit(2 * ROUNDS)), cut(d), turn, lambda s: F.concat(s["l"], s["r"]))
        return F.when(F.length(d) < 2, d).otherwise(moved_)

    return let(digits, run)


def _luhn(digits: Column) -> Column:
    """Luhn sum of a digit string whose last digit counts once."""

    def total(ds: Column) -> Column:
        n = F.length(ds)
        each = F.transform(F.split(ds, ""), lambda d, i: F.when(F.pmod(n - i, F.lit(2)) == 1, d.cast("int")).otherwise(F.element_at(F.array(*[F.lit(v) for v in (0, 2, 4, 6, 8, 1, 3, 5, 7, 9)]), d.cast("int") + 1)))
        return F.aggregate(each, F.lit(0), lambda a, d: a + F.coalesce(d, F.lit(0)))

    return let(digits, total)


def _card(key: str, digits: Column) -> Column:
    def run(d: Column) -> Column:
        head = F.concat(F.substr(d, F.lit(1), F.lit(1)), _permuted(key, F.lit("card"), F.substr(d, F.lit(2), F.length(d) - 2)))
        return let(head, lambda h: F.concat(h, F.pmod(_luhn(d) - _luhn(F.concat(h, F.lit("0"))), F.lit(10)).cast("string")))

    return let(digits, run)


def _ip(key: str, m: Column) -> Column:
    """The number that the last three octets make, moved by Feistel rounds on its two 12-bit halves."""
    def cut(o: Column) -> Column:
        value = o[1].cast("int") * 65536 + o[2].cast("int") * 256 + o[3].cast("int")
        return F.struct(o[0].alias("o"), F.shiftright(value, 12).alias("l"), value.bitwiseAND(F.lit(4095)).alias("r"))

    def turn(r: int):
        def run(s: Column) -> Column:
            source = s["r"] if r % 2 == 0 else s["l"]
            shift = F.pmod(_number(_hash(key, F.lit(f"ip{r}"), source.cast("string"))), F.lit(4096)).cast("int")
            return F.struct(s["o"].alias("o"), (s["l"].bitwiseXOR(shift) if r % 2 == 0 else s["l"]).alias("l"), (s["r"] if r % 2 == 0 else s["r"].bitwiseXOR(shift)).alias("r"))

        return run

    def step(s: Column) -> Column:
        shift = (1 + F.pmod(_number(_hash(key, F.lit("ip"), F.lit("step"))), F.lit(4095))).cast("int")
        return F.struct(s["o"].alias("o"), s["l"].alias("l"), s["r"].bitwiseXOR(shift).alias("r"))

    state = let(F.split(m, r"\."), cut)
    for f in (*map(turn, range(ROUNDS)), step, *map(turn, reversed(range(ROUNDS)))):
        state = let(state, f)
    octets = lambda v: F.concat_ws(".", F.shiftright(v, 16).cast("string"), F.shiftright(v, 8).bitwiseAND(F.lit(255)).cast("string"), v.bitwiseAND(F.lit(255)).cast("string"))
    return let(state, lambda s: F.concat_ws(".", s["o"], let(s["l"] * 4096 + s["r"], octets)))


def _mod97(alnum: Column) -> Column:
    """Remainder modulo 97 of the number that digits and letters (A: 10, ..., Z: 35) make."""
    code = lambda c: F.when(c.rlike("^[A-Z]$"), F.ascii(c) - 55).otherwise(F.coalesce(c.cast("int"), F.lit(0)))
    return F.aggregate(F.split(alnum, ""), F.lit(0), lambda r, c: F.when(c == "", r).otherwise(F.pmod(r * F.when(c.rlike("^[A-Z]$"), 100).otherwise(10) + code(c), F.lit(97))))


def _iban(key: str, canon: Column) -> Column:
    """The country stays; letters move by a keyed step a place, digits are permuted, and the check digits give the remainder
    modulo 97 that they gave before."""
    def shifted(rest: Column, country: Column) -> Column:
        def one(c: Column, i: Column) -> Column:
            by = 1 + F.pmod(_number(_hash(key, F.lit("iban"), country, i.cast("string"))), F.lit(25)).cast("int")
            return F.when(c.rlike("^[A-Z]$"), F.chr(F.lit(65) + F.pmod(F.ascii(c) - 65 + by, F.lit(26)))).otherwise(c)

        return F.array_join(F.transform(F.split(rest, ""), one), "")

    def run(s: Column) -> Column:
        country, rest = F.left(s, F.lit(2)), F.substr(s, F.lit(5))
        digits = _permuted(key, F.concat(F.lit("iban"), F.regexp_replace(rest, r"\d", "0")), F.regexp_replace(rest, r"\D", ""))

        def checked(new: Column) -> Column:
            was = _mod97(F.concat(rest, country, F.substr(s, F.lit(3), F.lit(2))))
            check = 2 + F.pmod(was - 2 - _mod97(F.concat(new, country, F.lit("00"))), F.lit(97))
            return F.concat(country, F.lpad(check.cast("string"), 2, "0"), new)

        return let(_dressed(shifted(rest, country), digits), checked)

    return let(canon, run)


def _dressed(m: Column, digits: Column, places: str = r"^\d$") -> Column:
    """``digits`` in the places of the match's digits, or of its signs that ``places`` matches."""

    def run(s: Column) -> Column:
        at = F.transform(s["cs"], lambda c: c.rlike(places).cast("int"))

        def put(a: Column) -> Column:
            one = lambda c, i: F.when(c.rlike(places), F.substr(s["ds"], F.aggregate(F.slice(a, 1, i + 1), F.lit(0), lambda t, x: t + x), F.lit(1))).otherwise(c)
            return F.array_join(F.transform(s["cs"], one), "")

        return let(at, put)

    return let(F.struct(F.split(m, "").alias("cs"), digits.alias("ds")), run)


def _letters(key: str, kind: str, canon: Column, attempt: Column) -> Column:
    """Each letter by a letter of its case, each digit by a digit, drawn from one hash; other signs stay."""
    hashed = F.concat(*[_hash(key, F.lit(f"{kind}{i}"), canon, attempt.cast("string")) for i in range(3)])

    def draw(h: Column):
        def one(c: Column, i: Column) -> Column:
            x = F.conv(F.substr(h, F.pmod(i, F.lit(96)) * 2 + 1, F.lit(2)), 16, 10).cast("int")
            letter = lambda a, n: F.chr(F.lit(ord(a)) + F.pmod(x, F.lit(n)))
            return F.when(c.rlike("^[a-z]$"), letter("a", 26)).when(c.rlike("^[A-Z]$"), letter("A", 26)).when(c.rlike("^[0-9]$"), letter("0", 10)).otherwise(c)

        return one

    return let(hashed, lambda h: F.array_join(F.transform(F.split(canon, ""), draw(h)), ""))


def _pick(words: list[str], x: Column) -> Column:
    return F.element_at(F.array(*[F.lit(w) for w in words]), (F.pmod(x, F.lit(len(words))) + 1).cast("int"))


def _name(key: str, canon: Column, female: Column, attempt: Column) -> Column:
    """Given name (where there was one) and surname of the same gender and script."""
    def of(script: str):
        def run(h: Column) -> Column:
            given = F.when(female, _pick(GIVEN["f", script], _number(h, 1, 6))).otherwise(_pick(GIVEN["m", script], _number(h, 1, 6)))
            sur = F.concat(F.initcap(_pick(SYLLABLES[script], _number(h, 7, 6))), *[_pick(SYLLABLES[script], _number(h, p, 6)) for p in (13, 19, 25)], _pick(ENDINGS[script], _number(h, 31, 6)))
            return F.when(canon.contains(" "), F.concat_ws(" ", given, sur)).otherwise(sur)

        return let(_hash(key, F.lit("name"), canon, attempt.cast("string")), run)

    return F.when(canon.rlike(r"\p{IsCyrillic}"), of("cyrillic")).otherwise(of("latin"))


def is_female(m: Column) -> Column:
    title = F.regexp_extract(m, r"^([^ .]+)", 1)
    return title.isin(*FEMALE) | (~title.isin(*MALE) & (F.pmod(F.xxhash64(canonical(F.lit("name"), m)), F.lit(2)) == 0))


def drawn(key: str, kind: Column, canon: Column, female: Column, attempt: Column) -> Column:
    """The surrogate's canonical form for the kinds that are drawn, on one attempt."""
    local, domain = F.substring_index(canon, "@", 1), F.substring_index(canon, "@", -1)
    whole = F.concat(_letters(key, "local", F.concat(local, F.lit("@")), F.concat_ws(":", domain, attempt.cast("string"))), _letters(key, "domain", domain, F.lit(0)))
    # the top domain stays
    email = F.concat(F.regexp_extract(whole, r"^(.*)\.[^.]*$", 1), F.lit("."), F.substring_index(domain, ".", -1))
    return F.when(kind == "email", email).otherwise(_name(key, canon, female, attempt))


DRAWN = ("email", "name")


def surrogate(key: str, m: Column, kind: Column, canon: Column, chosen: Column | None) -> Column:
    """The replacement of a match; ``chosen`` overrides the first draw. Every part is worked out only for its kind."""
    first = drawn(key, kind, canon, is_female(m), F.lit(0))
    value = F.coalesce(chosen, first) if chosen is not None else first
    digits = F.regexp_replace(m, r"\D", "")

    def phone_digits(d: Column) -> Column:
        # a phone's last ten digits vary but for a reserved exchange, which no other comes into; a country code before them stays
        reserved = lambda v: F.substr(v, F.lit(4), F.lit(3)) == "555"
        whole = lambda v: _permuted(key, F.lit("phone10"), v)
        again = lambda v: F.when(reserved(v), whole(v)).otherwise(v)

        def inside(local: Column) -> Column:
            moved = _permuted(key, F.lit("phone7"), F.concat(F.left(local, F.lit(3)), F.right(local, F.lit(4))))
            return let(moved, lambda v: F.concat(F.left(v, F.lit(3)), F.lit("555"), F.right(v, F.lit(4))))

        def run(local: Column) -> Column:
            outside = whole(local)
            for _ in range(WALKS):
                outside = let(outside, again)
            return F.when(reserved(local), inside(local)).otherwise(outside)

        return F.concat(F.left(d, F.length(d) - 10), let(F.right(d, F.lit(10)), run))

    phone = let(digits, phone_digits)
    return (
        F.when(kind == "email", value)
        .when(kind == "name", F.concat(F.regexp_extract(m, r"^([^ ]+ )", 1), value))
        .when(kind == "card", _dressed(m, _card(key, digits)))
        .when(kind == "ip", _ip(key, m))
        .when(kind == "phone", _dressed(m, phone))
        .when(kind == "iban", _dressed(m, _iban(key, canon), "^[A-Z0-9]$"))
        .otherwise(_dressed(m, _permuted(key, kind, digits)))
    )


def once(df: DataFrame, name: str, value: Column) -> DataFrame:
    """``df`` with a column that is evaluated once a row however often it is used: a generator of one element keeps the
    optimizer from writing the expression out at each use."""
    return df.select("*", F.explode(F.array(value)).alias(name))


def found(docs: DataFrame) -> DataFrame:
    """``docs`` with ``_hits``: array<struct<m, kind, canon>> of the text's entities."""
    docs = once(docs, "_ms", F.coalesce(entities(F.col("text")), F.expr("cast(array() as array<string>)")))
    docs = once(docs, "_kinds", F.transform("_ms", lambda m: F.struct(m.alias("m"), kind_of(m).alias("kind"))))
    hits = F.transform("_kinds", lambda s: F.struct(s["m"].alias("m"), s["kind"].alias("kind"), canonical(s["kind"], s["m"]).alias("canon")))
    return once(docs, "_hits", hits).drop("_ms", "_kinds")


def choose(mentions: DataFrame, key: str) -> DataFrame:
    """(kind, canon, chosen) of the drawn entities whose first draw does not stand: it meets another's or an entity of the
    corpus, or their titles name different genders. ``mentions`` is (m, kind, canon)."""
    drawable = mentions.filter(F.col("kind").isin(*DRAWN)).select("kind", "canon", is_female(F.col("m")).alias("female"))
    who = drawable.groupBy("kind", "canon").agg(F.max("female").alias("female"), F.min("female").alias("least"))
    draw = lambda a: drawn(key, F.col("kind"), F.col("canon"), F.col("female"), F.lit(a))
    who = who.withColumn("draw", draw(0)).checkpoint()
    real = who.select("kind", F.col("canon").alias("draw"))
    order = _hash(key, F.col("canon"))

    def standing(proposed: DataFrame, taken: DataFrame) -> DataFrame:
        """``proposed`` with ``ok``: the first in keyed order of those that draw what is not taken."""
        first = proposed.groupBy("kind", "draw").agg(F.min(order).alias("first"))
        held = taken.distinct().withColumn("held", F.lit(True))
        return proposed.join(first, ["kind", "draw"]).join(held, ["kind", "draw"], "left").withColumn("ok", (order == F.col("first")) & F.col("held").isNull()).drop("first", "held")

    state = standing(who, real).checkpoint()
    changed = state.filter(F.col("ok") & (F.col("female") != F.col("least"))).select("kind", "canon", F.col("draw").alias("chosen"))
    left = state.filter(~F.col("ok"))
    taken = real.unionByName(state.filter("ok").select("kind", "draw"))
    for attempt in range(1, ATTEMPTS + 1):
        if left.isEmpty():
            return changed
        again = draw(attempt)
        if attempt == ATTEMPTS:
            mark = F.substring(order, 1, 12)
            again = F.when(F.col("kind") == "email", F.concat(mark, F.lit("."), again)).otherwise(F.concat(again, F.lit(" "), F.initcap(F.translate(mark, "0123456789", "ghijklmnop"))))
        state = standing(left.drop("draw", "ok").withColumn("draw", again), taken).checkpoint()
        ok = state if attempt == ATTEMPTS else state.filter("ok")
        changed = changed.unionByName(ok.select("kind", "canon", F.col("draw").alias("chosen")))
        taken = taken.unionByName(ok.select("kind", "draw"))
        left = state.filter(~F.col("ok"))
    return changed


def replace_entities(docs: DataFrame, key: str = "surrogates-1") -> DataFrame:
    """``docs`` with entities of ``text`` replaced, and ``n_entities``."""
    from ..operators.components import checkpoint_dir

    checkpoint_dir(docs.sparkSession)
    columns = [c for c in docs.columns if c != "n_entities"]
    hit = found(docs.select(*columns))
    drawable = lambda hits: F.array_sort(F.array_distinct(F.filter(hits, lambda s: s["kind"].isin(*DRAWN))))
    # the different lists of drawn entities, by which conflicts are told to the texts: repeated texts share theirs
    named = lambda hits: F.transform(drawable(hits), lambda s: F.concat_ws(":", s["kind"], s["canon"]))
    listed = lambda hits: F.when(F.exists(hits, lambda s: s["kind"].isin(*DRAWN)), F.xxhash64(named(hits)))
    lists = hit.select(listed(F.col("_hits")).alias("_list"), drawable(F.col("_hits")).alias("hits")).filter("_list is not null").distinct().select("_list", F.inline("hits")).checkpoint()
    changed = choose(lists.select("m", "kind", "canon").distinct(), key).checkpoint()

    def replaced(df: DataFrame, chosen: Column | None) -> DataFrame:
        pick = (lambda s: F.element_at(chosen, F.concat_ws(":", s["kind"], s["canon"]))) if chosen is not None else (lambda s: None)
        new = F.transform("_hits", lambda s: surrogate(key, s["m"], s["kind"], s["canon"], pick(s)))
        text = F.when(F.size("_hits") == 0, F.col("text")).otherwise(F.array_join(F.zip_with(F.split("text", ANY, -1), new, lambda p, s: F.concat(p, F.coalesce(s, F.lit("")))), ""))
        return df.select(*[text.alias("text") if c == "text" else F.col(c) for c in columns], F.size("_hits").cast("long").alias("n_entities"))

    if changed.isEmpty():
        return replaced(hit, None)
    told = lists.select("_list", "kind", "canon").distinct().join(changed, ["kind", "canon"]).groupBy("_list").agg(F.map_from_entries(F.collect_list(F.struct(F.concat_ws(":", "kind", "canon"), "chosen"))).alias("_chosen")).checkpoint()
    # a bounded bitmap of the lists with conflicts parts the rows; only those it has meet their conflicts by an exchange
    spot = F.pmod("_list", F.lit(BITS))
    bits = told.groupBy(F.shiftright(spot, 6).alias("_word")).agg(F.bit_or(F.expr(f"shiftleft(1L, cast(pmod(_list, {BITS}) & 63 as int))")).alias("_bits"))
    hit = once(hit, "_list", listed(F.col("_hits")))
    marked = hit.join(F.broadcast(bits), F.shiftright(spot, 6) == F.col("_word"), "left").withColumn("_open", F.coalesce(F.expr(f"getbit(_bits, cast(pmod(_list, {BITS}) & 63 as int)) = 1"), F.lit(False)))
    salted = told.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    open_ = marked.filter("_open").withColumn("_salt", F.pmod(F.xxhash64(*[c for c in columns if docs.schema[c].dataType.simpleString() in HASHED]), F.lit(SALTS)).cast("int"))
    return replaced(marked.filter("not _open"), None).unionByName(replaced(open_.join(salted, ["_list", "_salt"], "left"), F.col("_chosen")))


#: Types of columns by which rows of one list of entities are dealt into parts.
HASHED = ("bigint", "int", "string", "double")


def op2_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return replace_entities(table(spark, sf_dir, "documents", "doc_id", "text")).select("doc_id", "text", "n_entities")
