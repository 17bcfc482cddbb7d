"""Surrogates of digit formats against a plain version in Python, and what collisions and IBANs must keep."""

import hashlib

import pytest
from pyspark.sql import functions as F

from epsgraph.llm import surrogates

KEY = "k"


def sha(*parts):
    return hashlib.sha256("\x1f".join((KEY, *parts)).encode()).hexdigest()


def number(h):
    return int(h[:12], 16)


def permuted(kind, d):
    if len(d) < 2:
        return d
    half, rounds = len(d) // 2, surrogates.ROUNDS
    s = [d[:half], d[half:]]

    def move(side, by):
        size = len(s[side])
        s[side] = str((int(s[side]) + by) % 10**size).zfill(size)

    for r in range(rounds):
        move(r % 2, number(sha(kind, str(r), s[1 - r % 2])))
    move(1, 1 + number(sha(kind, "step", str(len(s[1])))) % (10 ** len(s[1]) - 1))
    for r in reversed(range(rounds)):
        move(r % 2, -number(sha(kind, str(r), s[1 - r % 2])))
    return "".join(s)


def dressed(m, signs, is_place=str.isdigit):
    it = iter(signs)
    return "".join(next(it) if is_place(c) else c for c in m)


def digits_of(m):
    return "".join(c for c in m if c.isdigit())


def luhn(d):
    return sum(int(c) if i % 2 == 0 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(reversed(d)))


def mod97(s):
    return int("".join(str(int(c, 36)) for c in s)) % 97


def card(m):
    d = digits_of(m)
    head = d[0] + permuted("card", d[1:-1])
    return dressed(m, head + str((luhn(d) - luhn(head + "0")) % 10))


def phone(m):
    d = digits_of(m)
    v = d[-10:]
    if v[3:6] == "555":
        x = permuted("phone7", v[:3] + v[6:])
        v = x[:3] + "555" + x[3:]
    else:
        v = permuted("phone10", v)
        while v[3:6] == "555":
            v = permuted("phone10", v)
    return dressed(m, d[:-10] + v)


def ip(m):
    o = [int(x) for x in m.split(".")]
    v = o[1] << 16 | o[2] << 8 | o[3]
    s = [v >> 12, v & 4095]
    go = lambda r: s.__setitem__(r % 2, s[r % 2] ^ number(sha(f"ip{r}", str(s[1 - r % 2]))) % 4096)
    for r in range(surrogates.ROUNDS):
        go(r)
    s[1] ^= 1 + number(sha("ip", "step")) % 4095
    for r in reversed(range(surrogates.ROUNDS)):
        go(r)
    v = s[0] << 12 | s[1]
    return f"{o[0]}.{v >> 16}.{v >> 8 & 255}.{v & 255}"


def iban(m):
    c = m.replace(" ", "")
    country, check, rest = c[:2], c[2:4], c[4:]
    shape = "".join("0" if x.isdigit() else x for x in rest)
    moved = "".join(chr(65 + (ord(x) - 65 + 1 + number(sha("iban", country, str(i))) % 25) % 26) if x.isalpha() else x for i, x in enumerate(rest))
    new = dressed(moved, permuted("iban" + shape, digits_of(rest)))
    check = 2 + (mod97(rest + country + check) - 2 - mod97(new + country + "00")) % 97
    return dressed(m, country + f"{check:02d}" + new, str.isalnum)


PLAIN = {"card": card, "phone": phone, "ip": ip, "iban": iban, "ssn": lambda m: dressed(m, permuted("ssn", digits_of(m)))}


def made():
    n = range(40)
    yield from (("card", f"4111 1111 {1000 + 37 * i} 1{i % 10}{i % 7}1") for i in n)
    yield from (("card", f"5500{i:02d}0000000{i % 10}04") for i in n)
    yield from (("phone", f"+1 (7{i:02d}) 555-38{i:02d}") for i in n)
    yield from (("phone", f"212.8{i:02d}.5309") for i in n)
    yield from (("ip", f"10.{i}.{7 * i % 256}.3") for i in n)
    yield from (("ssn", f"123-4{i % 10}-67{i:02d}") for i in n)
    yield from (("iban", f"{c}{98 - mod97(r + c + '00'):02d}{r}") for c, r in [("GB", f"NWBK601613319268{i:02d}") for i in n] + [("DE", f"3704004405320130{i:02d}") for i in n] + [("MT", "MALT011000012345MTLCAST" + f"{i:03d}S") for i in n])
    yield "iban", "GB29 NWBK 6016 1331 9268 19"


def test_digit_formats_equal_the_plain_version(spark):
    rows = [(i, k, m) for i, (k, m) in enumerate(made())]
    df = spark.createDataFrame([(i, f"see {m} now") for i, _, m in rows], "doc_id long, text string")
    got = {r.doc_id: r.text for r in surrogates.replace_entities(df, KEY).collect()}
    seen = {}
    for i, kind, m in rows:
        new = got[i][4:-4]
        assert new == PLAIN[kind](m), (kind, m)
        assert new != m and (kind == "ip" or [c.isdigit() for c in new] == [c.isdigit() for c in m])
        c = lambda x: x.replace(" ", "")
        assert seen.setdefault((kind, c(new)), c(m)) == c(m)
        if kind == "iban":
            assert mod97(c(new)[4:] + c(new)[:4]) == 1
        if kind == "card":
            assert luhn(digits_of(new)) % 10 == luhn(digits_of(m)) % 10


@pytest.mark.parametrize("n", [1, 2, 3])
def test_permutations_have_no_fixed_points(spark, n):
    d = spark.range(10**n).select(F.lpad(F.col("id").cast("string"), n, "0").alias("d"))
    got = dict(d.select("d", surrogates._permuted(KEY, F.lit("x"), F.col("d"))).collect())
    assert sorted(got) == sorted(got.values())
    assert all(v == permuted("x", k) for k, v in got.items()) and (n == 1 or all(k != v for k, v in got.items()))


def test_conflicts_reach_every_copy_of_a_text(spark, monkeypatch):
    """Repeated texts and repeated lists of entities, more often than a list is dealt into parts, get the same replacement."""
    monkeypatch.setattr(surrogates, "SYLLABLES", {"latin": ["ba"], "cyrillic": ["ба"]})
    monkeypatch.setattr(surrogates, "ENDINGS", {"latin": ["berg"], "cyrillic": ["нов"]})
    people = [f"Mr {g} {s}" for g in ("Adam", "Otto", "Hans", "Fritz") for s in ("Klein", "Gross", "Jung", "Alt")]
    rows = [(i, f"{p} and Mr Uwe Lang{'!' * (i % 3)}") for i, p in enumerate(people * 20)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.text.rstrip("!").split(" and ") for r in surrogates.replace_entities(df).collect()}
    assert len(got) == len(rows) and len({b for _, b in got.values()}) == 1
    assert len({tuple(got[i]) for i in range(len(people))}) == len(people)
    assert all(got[i] == got[i % len(people)] for i in got)
