"""Pseudonyms: the SQL network against a plain one, shapes kept, equal values linked, clean text untouched."""

import hashlib
import re
from datetime import date, timedelta

from edgefold.llm import pii

DOC = "doc_id long, text string"


def digest(tweak, r, half):
    return int(hashlib.sha256(f"{pii.KEY}|{tweak}|{r}|{half}".encode()).hexdigest()[:15], 16)


def network(a, b, size_a, size_b, tweak):
    for r in range(1, pii.ROUNDS + 1):
        if r % 2 == 0:
            a = (a + digest(tweak, r, b)) % size_a
        else:
            b = (b + digest(tweak, r, a)) % size_b
    return a, b


def digits(d, tweak):
    u = len(d) // 2
    a, b = network(int(d[:u]), int(d[u:]), 10**u, 10 ** (len(d) - u), f"{tweak}{len(d)}")
    return str(a).zfill(u) + str(b).zfill(len(d) - u)


def luhn(d):
    return sum((x - 9 if x > 9 else x) for i, c in enumerate(reversed(d)) for x in [int(c) * (1 + i % 2)]) % 10


def account(d):
    offset = luhn(d)
    body = digits(d[:-1], f"account{offset}/")
    return body + str((20 + offset - luhn(body + "0")) % 10)


def run(spark, texts):
    rows = spark.createDataFrame(list(enumerate(texts)), DOC)
    return [r for r in sorted(pii.pseudonymise(rows).collect(), key=lambda r: r.doc_id)]


def test_accounts(spark):
    numbers = ["4111111111111111", "9807915762804490", "0000000000000000", "5927243074273351", "123456789012345", "4111 1111 1111 1111"]
    got = run(spark, [f"x {n}!! y" for n in numbers])
    for n, r in zip(numbers, got):
        new = r.text[2:-4]
        flat, was = re.sub(r"\D", "", new), re.sub(r"\D", "", n)
        assert flat == account(was) and luhn(flat) == luhn(was) and re.sub(r"\d", "9", new) == re.sub(r"\d", "9", n) and r.n_account == 1


def test_dates_phones_addresses_mails(spark):
    texts = ["on 2024-02-29 and 29.02.2024.", "call +1 (017) 555-7713 now", "at 233.254.104.120.", "to und.34@mail7.example.com, ok", "bad 2023-02-29 300.1.1.1 1899-01-01 3.14 2024"]
    day, phone, address, mail, bad = run(spark, texts)
    n = (date(2024, 2, 29) - date(1900, 1, 1)).days
    a, b = network(n % pii.DAYS_A, n // pii.DAYS_A, pii.DAYS_A, pii.DAYS_B, "date")
    new = date(1900, 1, 1) + timedelta(days=a + b * pii.DAYS_A)
    assert day.text == f"on {new:%Y-%m-%d} and {new:%d.%m.%Y}." and (day.n_iso, day.n_day) == (1, 1)
    d = digits("0175557713", "phone")
    assert phone.text == f"call +1 ({d[:3]}) {d[3:6]}-{d[6:]} now" and phone.n_phone == 1
    a, b = network(233 * 256 + 254, 104 * 256 + 120, 65536, 65536, "address")
    assert address.text == f"at {a // 256}.{a % 256}.{b // 256}.{b % 256}."
    assert re.fullmatch(r"to [a-z]{3}\.\d\d@mail7\.example\.com, ok", mail.text) and mail.text != texts[3]
    assert bad.text == texts[4] and bad.n_changed == 0


def test_equal_values_stay_linked_and_others_apart(spark):
    numbers = [f"{n:016d}" for n in range(400)]
    got = run(spark, [f"{n} {n}" for n in numbers])
    assert all(r.text[:16] == r.text[17:] for r in got) and len({r.text for r in got}) == 400
    mails = run(spark, [f"ab{i}c@x.org" for i in range(100)])
    assert len({r.text for r in mails}) == 100


def test_hard_cases(spark):
    long = "a" * 200_000 + " 4111111111111111"
    rows = run(spark, [None, "", "no numbers", "@", "+", "1" * 25, long, "4111111111111111"])
    assert rows[0].text is None and rows[0].n_changed == 0
    assert [r.text for r in rows[1:6]] == ["", "no numbers", "@", "+", "1" * 25]
    assert rows[6].text[-16:] == rows[7].text == account("4111111111111111")
    assert pii.pseudonymise(spark.createDataFrame([], DOC)).count() == 0
    clash = spark.createDataFrame([(None, "x", "y", "z")], "doc_id long, text string, _t string, _v string")
    assert pii.pseudonymise(clash).first().text == "x"


def test_no_python_in_the_plan(spark):
    plan = pii.pseudonymise(spark.createDataFrame([(1, "a")], DOC))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas", plan)
