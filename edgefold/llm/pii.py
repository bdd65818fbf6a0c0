"""Format-preserving pseudonyms for personal data, in DataFrame functions only.

Candidates are found with one pattern; each is validated by its kind and then permuted by a keyed
Feistel network within its own format, so the pseudonym has the same shape, equal values get equal
pseudonyms in every document, and different values stay different:

* account and card numbers (13 to 19 digits, also in groups of four): all but the last digit are
  permuted; the last is set so that the number's check-sum remainder - 0 for a valid card - is kept.
  By default their form is all that is validated: not every account number has a check sum, so any number of
  that form is permuted, time stamps, ISBN-13 and order numbers among them. With ``accounts="checked"`` the
  check sum must hold, and every other number stays;
* phone numbers with a country code: the digits after the country code;
* IPv4 addresses with octets up to 255, without leading zeros: permuted among all 32-bit addresses;
* calendar dates of 1900-01-01 to 2099-11-13 (ISO, or day.month.year): permuted among those days;
* local parts of e-mail addresses: letters and digits, each within its class.

A candidate that fails its kind's validation stays as it is. Gaps between candidates are copied. No pattern repeats
a group without bound, so texts of any length are matched in a bounded stack.

Whoever has the key can undo the pseudonyms. It is an argument, or the session's setting ``KEY_SETTING``; ``KEY`` in
this module is for tests and examples.

Cases: null text stays null with counts 0; null ids are kept; repeated rows get equal results; empty
tables give empty results; very long texts are treated whole; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KEY = "edgefold-default-key"
KEY_SETTING = "spark.edgefold.pseudonym.key"
ROUNDS = 8
#: The forms of candidates.
EMAIL = r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++@(?=[A-Za-z0-9-]++\.[A-Za-z0-9-])[A-Za-z0-9.-]++"
ISO_DATE = r"(?<![0-9.-])[0-9]{4}-[0-9]{2}-[0-9]{2}(?![0-9-])"
DAY_DATE = r"(?<![0-9./])[0-9]{2}\.[0-9]{2}\.[0-9]{4}(?![0-9])"
PHONE = r"(?<![0-9A-Za-z+])\+[0-9]{1,3}[ .-]?\(?[0-9]{2,4}\)?[ .-]?[0-9]{3,4}[ .-]?[0-9]{3,4}(?![0-9])"
ADDRESS = r"(?<![0-9.])[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?![0-9])(?!\.[0-9])"
ACCOUNT = r"(?<![0-9A-Za-z.])(?:[0-9]{13,19}|[0-9]{4}(?:[ -][0-9]{4}){3}(?![ -][0-9]))(?![0-9A-Za-z])"
CANDIDATE = f"(?:{'|'.join((EMAIL, ISO_DATE, DAY_DATE, PHONE, ADDRESS, ACCOUNT))})"
KINDS = ("email", "iso", "day", "phone", "address", "account")
#: Days of the permuted calendar: two factors whose product is their number.
FIRST_DAY, DAYS_A, DAYS_B = "1900-01-01", 250, 292


def _q(text: str) -> str:
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _round(key: str, tweak: str, r: str, half: str) -> str:
    """Round function: 60 bits of a keyed digest of the round number and the other half."""
    return f"cast(conv(substr(sha2(concat_ws('|', {_q(key)}, {tweak}, {r}, {half}), 256), 1, 15), 16, 10) AS bigint)"


def feistel_sql(a: str, b: str, size_a: str, size_b: str, tweak: str, key: str) -> str:
    """SQL of a permutation of pairs (a, b) of [0, size_a) x [0, size_b), as a struct (a, b)."""
    new_a = f"pmod(t.a + {_round(key, tweak, 'r', 't.b')}, {size_a})"
    new_b = f"pmod(t.b + {_round(key, tweak, 'r', 't.a')}, {size_b})"
    step = f"CASE WHEN r % 2 = 0 THEN named_struct('a', {new_a}, 'b', t.b) ELSE named_struct('a', t.a, 'b', {new_b}) END"
    return f"aggregate(sequence(1, {ROUNDS}), named_struct('a', cast({a} AS bigint), 'b', cast({b} AS bigint)), (t, r) -> {step})"


def _bound(value: str, name: str, body: str) -> str:
    return f"element_at(transform(array({value}), {name} -> {body}), 1)"


def digits_sql(d: str, tweak: str, key: str) -> str:
    """SQL that permutes a string of 2 to 18 digits among those of its length."""
    left, right = f"cast(floor(length({d}) / 2) AS int)", f"(length({d}) - cast(floor(length({d}) / 2) AS int))"
    pair = feistel_sql(f"substr({d}, 1, {left})", f"substr({d}, {left} + 1)", f"cast(pow(10, {left}) AS bigint)", f"cast(pow(10, {right}) AS bigint)", f"concat({tweak}, length({d}))", key)
    return _bound(pair, "f", f"concat(lpad(f.a, {left}, '0'), lpad(f.b, {right}, '0'))")


def refilled_sql(m: str, new: str) -> str:
    """SQL that puts the digits ``new`` in place of the digits of ``m``, other characters staying."""
    nth = f"length(regexp_replace(substr({m}, 1, i + 1), '[^0-9]', ''))"
    return f"array_join(transform(split({m}, ''), (c, i) -> CASE WHEN c RLIKE '[0-9]' THEN substr({new}, {nth}, 1) ELSE c END), '')"


def checksum_sql(d: str, with_last: bool) -> str:
    """SQL of the Luhn sum of ``d``; without its last digit yet to come if ``with_last`` is false."""
    place = "0" if with_last else "1"
    doubled = f"(length({d}) - 1 - i + {place}) % 2 = 1"
    value = f"cast(c AS int) * CASE WHEN {doubled} THEN 2 ELSE 1 END"
    return f"aggregate(transform(split({d}, ''), (c, i) -> {value} - CASE WHEN {value} > 9 THEN 9 ELSE 0 END), 0, (x, y) -> x + y) % 10"


def account_sql(m: str, key: str, checked: bool) -> str:
    """Permute all digits but the last; the last keeps the remainder of the check-sum, which must be 0 if ``checked``."""
    body = _bound(
        f"named_struct('p', substr(d, 1, length(d) - 1), 'o', {checksum_sql('d', True)})",
        "x",
        _bound(digits_sql("x.p", "concat('account', x.o, '/')", key), "n", f"concat(n, (20 + x.o - {checksum_sql('n', False)}) % 10)"),
    )
    made = _bound(body, "e", refilled_sql(m, "e"))
    if checked:
        made = f"CASE WHEN {checksum_sql('d', True)} = 0 THEN {made} ELSE {m} END"
    return _bound(f"regexp_replace({m}, '[^0-9]', '')", "d", made)


def phone_sql(m: str, key: str) -> str:
    """Permute the digits after the country code, which ends at the first mark or leaves ten digits."""
    code = f"regexp_extract({m}, '^\\\\+([0-9]{{1,3}})(?=[^0-9]|[0-9]{{10}}$)', 1)"
    parts = f"named_struct('c', {code}, 'd', regexp_replace({m}, '[^0-9]', ''))"
    return _bound(parts, "x", _bound(f"concat(x.c, {digits_sql('substr(x.d, length(x.c) + 1)', _q('phone'), key)})", "e", refilled_sql(m, "e")))


def address_sql(m: str, key: str) -> str:
    pair = feistel_sql("cast(o[0] AS int) * 256 + cast(o[1] AS int)", "cast(o[2] AS int) * 256 + cast(o[3] AS int)", "65536", "65536", _q("address"), key)
    shown = _bound(pair, "f", "concat_ws('.', f.a div 256, f.a % 256, f.b div 256, f.b % 256)")
    made = f"CASE WHEN forall(o, x -> cast(x AS int) <= 255 AND (x = '0' OR x NOT LIKE '0%')) THEN {shown} ELSE {m} END"
    return _bound(f"split({m}, '[.]')", "o", made)


def date_sql(m: str, form: str, key: str) -> str:
    pair = feistel_sql(f"n % {DAYS_A}", f"n div {DAYS_A}", str(DAYS_A), str(DAYS_B), _q("date"), key)
    shown = _bound(pair, "f", f"date_format(date_add(date'{FIRST_DAY}', cast(f.a + f.b * {DAYS_A} AS int)), '{form}')")
    made = f"CASE WHEN n BETWEEN 0 AND {DAYS_A * DAYS_B - 1} THEN {shown} ELSE {m} END"
    return _bound(f"datediff(to_date(try_to_timestamp({m}, '{form}')), date'{FIRST_DAY}')", "n", made)


def email_sql(m: str, key: str) -> str:
    """Feistel over two halves of the local part, shifting letters and digits within their classes."""

    def shifted(half: str, other: str, r: str) -> str:
        seed = f"sha2(concat_ws('|', {_q(key)}, 'email', {r}, {other}), 256)"
        byte = "cast(conv(substr(sha2(concat_ws('|', h, i div 16), 256), (i % 16) * 4 + 1, 4), 16, 10) AS int)"
        inside = lambda low, n: f"chr(ascii('{low}') + (ascii(c) - ascii('{low}') + {byte}) % {n})"
        new = f"CASE WHEN c RLIKE '[a-z]' THEN {inside('a', 26)} WHEN c RLIKE '[A-Z]' THEN {inside('A', 26)} WHEN c RLIKE '[0-9]' THEN {inside('0', 10)} ELSE c END"
        return _bound(seed, "h", f"array_join(transform(split({half}, ''), (c, i) -> {new}), '')")

    local, half = f"substring_index({m}, '@', 1)", f"cast(ceil(length(substring_index({m}, '@', 1)) / 2) AS int)"
    step = f"CASE WHEN r % 2 = 0 THEN named_struct('a', {shifted('t.a', 't.b', 'r')}, 'b', t.b) ELSE named_struct('a', t.a, 'b', {shifted('t.b', 't.a', 'r')}) END"
    loop = f"aggregate(sequence(1, {ROUNDS}), named_struct('a', substr({local}, 1, {half}), 'b', substr({local}, {half} + 1)), (t, r) -> {step})"
    return _bound(loop, "f", f"concat(f.a, f.b, '@', substring_index({m}, '@', -1))")


def pseudonym_sql(m: str, key: str, checked: bool = False) -> str:
    """SQL that maps a candidate to (kind, new)."""
    full = lambda p: f"{m} RLIKE {_q(f'^(?:{p})$')}"
    cases = (
        ("email", f"{m} LIKE '%@%'", email_sql(m, key)),
        ("phone", f"{m} LIKE '+%'", phone_sql(m, key)),
        ("iso", full("[0-9]{4}-[0-9]{2}-[0-9]{2}"), date_sql(m, "yyyy-MM-dd", key)),
        ("day", full("[0-9]{2}[.][0-9]{2}[.][0-9]{4}"), date_sql(m, "dd.MM.yyyy", key)),
        ("address", full("[0-9.]*[.][0-9.]*"), address_sql(m, key)),
    )
    when = " ".join(f"WHEN {test} THEN named_struct('kind', '{kind}', 'new', {made})" for kind, test, made in cases)
    return f"CASE {when} ELSE named_struct('kind', 'account', 'new', {account_sql(m, key, checked)}) END"


def pseudonymise(docs: DataFrame, key: str | None = None, id_col: str = "doc_id", text_col: str = "text", accounts: str = "form") -> DataFrame:
    """(id, text, n_<kind> for every kind, n_changed) with pseudonyms in place of validated values.

    ``accounts`` is "form" or "checked": whether a number's form alone or its check sum too validates it.
    """
    if accounts not in ("form", "checked"):
        raise ValueError(f"accounts must be form or checked, not {accounts}")
    key = key or docs.sparkSession.conf.get(KEY_SETTING, KEY)
    rows = docs.select(F.col(id_col).alias("_id"), F.col(text_col).cast("string").alias("_t"))
    found = f"regexp_extract_all(_t, {_q(CANDIDATE)}, 0)"
    gaps = f"split(_t, {_q(CANDIDATE)}, -1)"
    named = f"transform({found}, m -> {_bound(pseudonym_sql('m', key, accounts == 'checked'), 'p', 'named_struct(' + chr(39) + 'old' + chr(39) + ', m, ' + chr(39) + 'kind' + chr(39) + ', p.kind, ' + chr(39) + 'new' + chr(39) + ', p.new)')})"
    rows = rows.withColumn("_v", F.expr(f"CASE WHEN _t RLIKE '[0-9@]' THEN {named} END"))
    text = F.expr(f"CASE WHEN size(_v) > 0 THEN array_join(zip_with({gaps}, transform(_v, v -> v.new), (g, n) -> concat(g, coalesce(n, ''))), '') ELSE _t END")
    count = lambda test: F.when(F.col("_v").isNull(), 0).otherwise(F.size(F.filter("_v", test))).cast("long")
    of_kind = lambda kind: lambda v: v["kind"] == kind
    counts = [count(of_kind(k)).alias(f"n_{k}") for k in KINDS]
    return rows.select(F.col("_id").alias(id_col), text.alias("text"), *counts, count(lambda v: v["new"] != v["old"]).alias("n_changed"))
