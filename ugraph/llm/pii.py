"""Format-preserving pseudonyms of personal numbers and dates, by DataFrame functions alone.

What is found and valid is replaced by a keyed permutation of its own format, so equal values stay equal in all
documents and different ones stay different: card numbers (13 to 19 digits with a right check digit; the new check
digit is right too), phone numbers (8 to 15 digits after a plus sign, or with an area code in brackets; the country
code stays), IPv4 addresses, calendar dates from 1900 to 2099 (2100-01-01 is the last day that a date can become), the
local parts of e-mail addresses (digits stay digits, letters letters of their case) and long hexadecimal secrets. The
permutation is a Feistel network of ROUNDS rounds over the two halves of the value, with a keyed digest as round
function. Every replacement has as many characters as what it replaces. The key is the caller's.

Defined cases: null text stays null; texts without such values stay as they are; numbers that fail their check stay;
columns other than text pass through, whatever their names; an empty table stays empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ROUNDS = 8
#: Setting from which ``session_key`` takes the key, and the key of test data, where it is unset.
KEY_SETTING, TEST_KEY = "spark.ugraph.pseudonymKey", "pseudonym-key-1"


def session_key(spark: SparkSession) -> str:
    return spark.conf.get(KEY_SETTING, TEST_KEY)


#: What may be a value, by kind. Look-arounds keep a match from starting or ending inside a longer run.
PATTERNS = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}@[A-Za-z0-9-]{1,63}(?:\.[A-Za-z0-9-]{1,63}){0,8}\.[A-Za-z]{2,24}(?![A-Za-z0-9-])",
    "secret": r"(?<![A-Za-z0-9])[0-9A-Fa-f]{32,128}(?![A-Za-z0-9])",
    "ip": r"(?<![0-9.])[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?!\.?[0-9])",
    "date": r"(?<![0-9./-])(?:(?:19|20)[0-9]{2}-[0-9]{2}-[0-9]{2}|[0-9]{2}\.[0-9]{2}\.(?:19|20)[0-9]{2}|[0-9]{2}/[0-9]{2}/(?:19|20)[0-9]{2})(?![0-9/-])",
    "phone": r"(?<![0-9+])(?:\+[0-9]{1,3}[ .-]?)?\([0-9]{2,4}\)[ .-]?[0-9]{3,4}[ .-]?[0-9]{3,4}(?![0-9])|(?<![0-9+])\+[0-9]{1,3}(?:[ .-]?[0-9]{2,4}){2,4}(?![0-9])",
    "card": r"(?<![0-9])(?:[0-9]{13,19}|[0-9]{4}(?:[ -][0-9]{4}){3})(?![0-9])",
}
KINDS = list(PATTERNS)
ANY = "|".join(f"(?:{p})" for p in PATTERNS.values())
#: Days from 1900-01-01 on which dates are permuted: 150 x 487.
DATE_PARTS, DATE_FROM = (150, 487), "1900-01-01"


def _quoted(text: str) -> str:
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _round(kind: str, key: str, other: str) -> str:
    return f"cast(conv(substring(sha2(concat_ws(':', {_quoted(key)}, {_quoted(kind)}, cast(i as string), cast({other} as string)), 256), 1, 15), 16, 10) as bigint)"


def feistel(a: str, b: str, size_a: str, size_b: str, kind: str, key: str) -> str:
    """SQL of the pair (a, b) after all rounds; a is below size_a and b below size_b before and after."""
    return (
        f"aggregate(sequence(0, {ROUNDS - 1}), named_struct('a', cast({a} as bigint), 'b', cast({b} as bigint)), (s, i) -> named_struct("
        f"'a', CASE WHEN i % 2 = 0 THEN pmod(s.a + {_round(kind, key, 's.b')}, cast({size_a} as bigint)) ELSE s.a END, "
        f"'b', CASE WHEN i % 2 = 1 THEN pmod(s.b + {_round(kind, key, 's.a')}, cast({size_b} as bigint)) ELSE s.b END))"
    )


def _digits(s: str) -> str:
    return f"regexp_replace({s}, '[^0-9]', '')"


def _permuted_digits(d: str, kind: str, key: str) -> str:
    """A digit string of 2 to 18 digits, permuted among those of its length."""
    a = f"cast(substring({d}, 1, length({d}) div 2) as bigint)"
    b = f"cast(substring({d}, length({d}) div 2 + 1, 18) as bigint)"
    size_a, size_b = f"pow(10, length({d}) div 2)", f"pow(10, length({d}) - length({d}) div 2)"
    pair = feistel(a, b, size_a, size_b, kind, key)
    return f"element_at(transform(array({pair}), r -> concat(lpad(cast(r.a as string), length({d}) div 2, '0'), lpad(cast(r.b as string), cast(length({d}) - length({d}) div 2 as int), '0'))), 1)"


def luhn_sum(d: str, doubled_first: bool) -> str:
    """The check sum of a digit string, from the right; doubled_first: the rightmost digit is doubled."""
    turn = 0 if doubled_first else 1
    v = f"cast(substring({d}, length({d}) - i, 1) as int)"
    return f"aggregate(sequence(0, length({d}) - 1), 0, (t, i) -> t + CASE WHEN i % 2 = {turn} THEN CASE WHEN {v} > 4 THEN 2 * {v} - 9 ELSE 2 * {v} END ELSE {v} END)"


def _refill(s: str, d: str) -> str:
    """``s`` with its digits replaced, in order, by those of ``d``."""
    return f"array_join(transform(sequence(1, length({s})), i -> CASE WHEN substring({s}, i, 1) BETWEEN '0' AND '9' THEN substring({d}, length({_digits(f'substring({s}, 1, i)')}), 1) ELSE substring({s}, i, 1) END), '')"


def _let(value: str, name: str, body: str) -> str:
    return f"element_at(transform(array({value}), {name} -> {body}), 1)"


def _card(key: str) -> str:
    body = _permuted_digits("u", "card", key)
    whole = _let(body, "w", f"concat(w, cast((10 - {luhn_sum('w', True)} % 10) % 10 as string))")
    return _let(_digits("p"), "d", _let("substring(d, 1, length(d) - 1)", "u", _let(whole, "v", _refill("p", "v"))))


def _phone(key: str) -> str:
    code = "length(regexp_replace(regexp_extract(p, '^\\\\+[0-9]{1,3}(?=[ .(-])', 0), '[^0-9]', ''))"
    rest = _permuted_digits("u", "phone", key)
    return _let(_digits("p"), "d", _let(code, "c", _let("substring(d, c + 1, 18)", "u", _let(rest, "w", _let("concat(substring(d, 1, c), w)", "v", _refill("p", "v"))))))


def _ip(key: str) -> str:
    """Permuted among the addresses whose numbers have as many digits as these: each number within its own range."""
    size = "CASE length(x) WHEN 1 THEN 10 WHEN 2 THEN 90 ELSE 156 END"
    low = "CASE length(x) WHEN 1 THEN 0 WHEN 2 THEN 10 ELSE 100 END"
    o = "split(p, '[.]')"
    n, k, base = "transform(o, x -> cast(x as bigint))", f"transform(o, x -> {size})", f"transform(o, x -> {low})"
    pair = feistel("(n[0] - m[0]) * k[1] + n[1] - m[1]", "(n[2] - m[2]) * k[3] + n[3] - m[3]", "k[0] * k[1]", "k[2] * k[3]", "ip", key)
    text = "concat_ws('.', cast(r.a div k[1] + m[0] as string), cast(r.a % k[1] + m[1] as string), cast(r.b div k[3] + m[2] as string), cast(r.b % k[3] + m[3] as string))"
    return _let(o, "o", _let(n, "n", _let(k, "k", _let(base, "m", _let(pair, "r", text)))))


def _date_of(p: str) -> str:
    return f"coalesce(try_to_date({p}, 'yyyy-MM-dd'), try_to_date({p}, 'dd.MM.yyyy'), try_to_date({p}, 'dd/MM/yyyy'), try_to_date({p}, 'MM/dd/yyyy'))"


def _date(key: str) -> str:
    a, b = DATE_PARTS
    days = f"datediff({_date_of('p')}, DATE'{DATE_FROM}')"
    pair = feistel(f"n div {b}", f"n % {b}", str(a), str(b), "date", key)
    shape = "CASE WHEN p LIKE '____-%' THEN 'yyyy-MM-dd' WHEN p LIKE '%.%' THEN 'dd.MM.yyyy' WHEN try_to_date(p, 'dd/MM/yyyy') IS NOT NULL THEN 'dd/MM/yyyy' ELSE 'MM/dd/yyyy' END"
    moved = f"date_add(DATE'{DATE_FROM}', cast(r.a * {b} + r.b as int))"
    return _let(days, "n", _let(pair, "r", f"date_format({moved}, {shape})"))


def _moved(part: str, other: str, alphabets: tuple[str, ...], kind: str, key: str) -> str:
    """``part`` with each character moved along its alphabet by two digits of a keyed digest of ``other``; i is the round."""
    c = f"substring({part}, j, 1)"
    digest = f"sha2(concat_ws(':', {_quoted(key)}, {_quoted(kind)}, cast(i as string), {other}), 512)"
    step = "cast(conv(substring(h, 2 * j - 1, 2), 16, 10) as int)"
    cases = " ".join(f"WHEN instr('{a}', {c}) > 0 THEN substring('{a}', (instr('{a}', {c}) - 1 + {step}) % {len(a)} + 1, 1)" for a in alphabets)
    return f"CASE WHEN {part} = '' THEN '' ELSE {_let(digest, 'h', f"array_join(transform(sequence(1, length({part})), j -> CASE {cases} ELSE {c} END), '')")} END"


def _permuted_text(x: str, alphabets: tuple[str, ...], kind: str, key: str) -> str:
    """A string of at most 128 characters, permuted among those with the same alphabets in the same places."""
    pair = (
        f"aggregate(sequence(0, {ROUNDS - 1}), named_struct('a', substring({x}, 1, length({x}) div 2), 'b', substring({x}, length({x}) div 2 + 1, 128)), (s, i) -> named_struct("
        f"'a', CASE WHEN i % 2 = 0 THEN {_moved('s.a', 's.b', alphabets, kind, key)} ELSE s.a END, "
        f"'b', CASE WHEN i % 2 = 1 THEN {_moved('s.b', 's.a', alphabets, kind, key)} ELSE s.b END))"
    )
    return _let(pair, "r", "concat(r.a, r.b)")


def _email(key: str) -> str:
    """The same for any case of letters; the case stays in its place."""
    moved = _permuted_text("l", ("0123456789", "abcdefghijklmnopqrstuvwxyz"), "mail", key)
    cased = "array_join(transform(sequence(1, length(w)), j -> CASE WHEN substring(w, j, 1) BETWEEN 'A' AND 'Z' THEN upper(substring(v, j, 1)) ELSE substring(v, j, 1) END), '')"
    return _let("substring_index(p, '@', 1)", "w", _let("lower(w)", "l", _let(moved, "v", f"concat({cased}, substring(p, length(w) + 1, 1000))")))


def _secret(key: str) -> str:
    return _let("lower(p)", "l", _let(_permuted_text("l", ("0123456789abcdef",), "secret", key), "w", "CASE WHEN p = upper(p) THEN upper(w) ELSE w END"))


VALID = {
    "email": "true",
    "secret": "p RLIKE '[0-9]' AND p RLIKE '[A-Fa-f]'",
    "ip": "forall(split(p, '[.]'), x -> cast(x as int) <= 255 AND (length(x) = 1 OR x NOT LIKE '0%'))",
    "date": f"{_date_of('p')} IS NOT NULL",
    "phone": f"length({_digits('p')}) BETWEEN 8 AND 15",
    "card": _let(_digits("p"), "d", f"d RLIKE '[1-9]' AND {luhn_sum('d', False)} % 10 = 0"),
}
REPLACE = {"email": _email, "secret": _secret, "ip": _ip, "date": _date, "phone": _phone, "card": _card}


def kind_of(p: str = "p") -> str:
    """SQL of the kind of a found string, null where it fails its check."""
    tests = " ".join(f"WHEN {p} RLIKE {_quoted('^(?:' + PATTERNS[k] + ')$')} THEN CASE WHEN {VALID[k]} THEN '{k}' END" for k in KINDS)
    return f"CASE {tests} END"


def replacement(key: str) -> str:
    cases = " ".join(f"WHEN '{k}' THEN {REPLACE[k](key)}" for k in KINDS)
    return f"coalesce(CASE {kind_of()} {cases} END, p)"


def masked(docs: DataFrame, key: str, counts: bool = False) -> DataFrame:
    """``docs`` with its text replaced; ``counts`` adds n_<kind> for each kind: valid values found."""
    t, hit, gap = "__pii_text", "__pii_hits", "__pii_gaps"
    step = docs.withColumn(t, F.col("text").cast("string"))
    some = F.col(t).rlike("[0-9@]")
    step = step.withColumn(hit, F.when(some, F.regexp_extract_all(F.col(t), F.lit(ANY), F.lit(0))))
    step = step.withColumn(gap, F.when(F.size(hit) > 0, F.split(F.col(t), ANY, -1)))
    moved = F.expr(f"array_join(flatten(zip_with({gap}, transform({hit}, p -> {replacement(key)}), (g, r) -> array(g, coalesce(r, '')))), '')")
    text = F.when(F.size(hit) > 0, moved).otherwise(F.col(t))
    out = [text.alias("text") if c == "text" else F.col(f"`{c}`") for c in docs.columns]
    if counts:
        kinds = F.expr(f"transform({hit}, p -> {kind_of()})")
        step = step.withColumn("__pii_kinds", kinds)
        out += [F.when(F.col(hit).isNull(), 0).otherwise(F.expr(f"size(filter(__pii_kinds, x -> x = '{k}'))")).cast("long").alias(f"n_{k}") for k in KINDS]
    return step.select(*out)


def pii_digest(docs: DataFrame) -> DataFrame:
    """op10: doc_id, the replaced text and how many values of each kind were replaced."""
    return masked(docs.select("doc_id", "text"), session_key(docs.sparkSession), counts=True)
