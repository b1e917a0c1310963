"""Format-preserving pseudonyms for personal numbers, dates and e-mail names.

DataFrame functions only. Each value found is validated (Luhn digit, calendar, ranges), read as a number of its format's
domain, and moved within that domain by a keyed Feistel network on two mixed-radix halves, so that equal values get equal
pseudonyms in all documents, different values different ones, and the result is valid in the same format.
Separators stay where they are. Domains of dates are blocks of 73,000 days from 1900-01-01; Luhn digits are computed anew.
Dates are yyyy-MM-dd (also before a time), dd/MM/yyyy, dd.MM.yyyy and their one-digit forms, which get one-digit forms. Dates that are valid only with the month first
(the day is over 12) move among such dates: days up to 28 over years, months and days, later ones over years and the months that have the day; 02/29 of a leap year among those from 1904 to 2096.
Phone numbers keep their country code; those without one are ten digits as (ddd) ddd-dddd, ddd-ddd-dddd or ddd.ddd.dddd.
E-mail names are moved character by character within lower case, upper case and digits; the domain name stays.

A null text stays null; an empty one stays empty; texts without digits and `@` are not searched. Repeated rows are treated each on its own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import free_name, pick, table

#: Stands for the secret that a user passes in.
KEY = "change-this-key"
ROUNDS = 8

OCTET = r"(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)"
#: Kind and pattern, in the order in which they are tried. Each starts and ends where no longer word or number goes on.
KINDS = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}@(?:[A-Za-z0-9-]{1,63}\.){1,8}[A-Za-z]{2,24}",
    "ip": rf"(?<![\w.]){OCTET}(?:\.{OCTET}){{3}}(?![\w]|\.\d)",
    "date": r"(?<![\w./-])(?:\d{4}-\d{2}-\d{2}(?:(?=T\d{2}:\d{2})|(?![\w/-]))|\d{1,2}(?:/\d{1,2}/|\.\d{1,2}\.)\d{4}(?![\w/-]|\.\d))",
    "ssn": r"(?<![\w-])\d{3}-\d{2}-\d{4}(?![\w-])",
    "card": r"(?<![\w.-])(?:\d{4}[ -]\d{4}[ -]\d{4}[ -]\d{4}|\d{4}[ -]\d{6}[ -]\d{5}|\d{13,19})(?![\w-])",
    "phone": r"(?<![\w+])\+\d{1,3}[ .-]?\(?\d{3}\)?[ .-]?\d{3}[ .-]?\d{4}(?!\w)",
    "intl": r"(?<![\w+])\+[1-9]\d{0,3}(?:[ .-]?\(?\d{1,8}\)?){1,6}(?!\w)",
    "local": r"(?<![\w.(+-])(?:\(\d{3}\) ?\d{3}[ .-]\d{4}|\d{3}-\d{3}-\d{4}|\d{3}\.\d{3}\.\d{4})(?![\w-]|\.\d)",
}
#: Country codes of one and of two digits in the public numbering plan; all others have three.
COUNTRY = r"(?:1|7|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|\d{3})"
ANY = "|".join(f"(?:{p})" for p in KINDS.values())


def _q(s: str) -> str:
    return "'" + s.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _hash(key: str, kind: str, turn: str, value: str) -> str:
    return f"sha2(concat_ws('|', {_q(key)}, '{kind}', {turn}, {value}), 256)"


def feistel(key: str, kind: str, x: str, y: str, a: str, b: str) -> str:
    """SQL: struct(x, y) moved within [0, a) x [0, b): each turn adds to one half a keyed hash of the other, so that every turn can be undone."""
    h = lambda v: f"cast(conv(substring({_hash(key, kind, 'r', v)}, 1, 15), 16, 10) AS bigint)"
    even = f"named_struct('x', (s.x + {h('s.y')} % ({a})) % ({a}), 'y', s.y)"
    odd = f"named_struct('x', s.x, 'y', (s.y + {h('s.x')} % ({b})) % ({b}))"
    return f"aggregate(sequence(0, {ROUNDS - 1}), named_struct('x', cast({x} AS bigint), 'y', cast({y} AS bigint)), (s, r) -> if(r % 2 = 0, {even}, {odd}))"


def _digits(key: str, kind: str, digits: str) -> str:
    """SQL: a string of digits, at most 20, moved within the strings of its length."""
    la = f"cast(ceil(length({digits}) / 2) AS int)"
    lb = f"(length({digits}) - {la})"
    moved = feistel(key, kind, f"left({digits}, {la})", f"if({lb} = 0, '0', right({digits}, {lb}))", f"cast(pow(10, {la}) AS bigint)", f"cast(pow(10, {lb}) AS bigint)")
    return f"element_at(transform(array({moved}), z -> concat(lpad(cast(z.x AS string), {la}, '0'), if({lb} = 0, '', lpad(cast(z.y AS string), {lb}, '0')))), 1)"


def luhn_sum(digits: str, first: int) -> str:
    """SQL: the Luhn sum from the right; first is 1 if the last digit is doubled, else 0."""
    v = "cast(d AS int)"
    return f"aggregate(transform(split(reverse({digits}), ''), (d, i) -> if(i % 2 = {1 - first}, if({v} > 4, 2 * {v} - 9, 2 * {v}), {v})), 0, (s, d) -> s + d)"


def _refill(form: str, digits: str) -> str:
    """SQL: the digits put, in order, where form has digits."""
    return f"aggregate(split({form}, ''), named_struct('o', '', 'k', 1), (s, c) -> if(c BETWEEN '0' AND '9', named_struct('o', concat(s.o, substring({digits}, s.k, 1)), 'k', s.k + 1), named_struct('o', concat(s.o, c), 'k', s.k)), s -> s.o)"


def _let(value: str, name: str, body: str) -> str:
    """SQL: body with a name for a value, which is computed once."""
    return f"element_at(transform(array({value}), {name} -> {body}), 1)"


def _pseudonyms(key: str) -> dict[str, str]:
    """SQL by kind: the pseudonym of m, or m itself where it isn't valid."""
    card = _let("regexp_replace(m, '[^0-9]', '')", "n", f"if({luhn_sum('n', 0)} % 10 = 0, {_let(_digits(key, 'card', 'left(n, length(n) - 1)'), 'p', _refill('m', f'concat(p, cast((10 - {luhn_sum("p", 1)} % 10) % 10 AS string))'))}, m)")
    phone = _let(
        "regexp_replace(m, '[^0-9]', '')",
        "n",
        _let("regexp_extract(m, '^(.*?)[(]?[0-9]{3}[)]?[ .-]?[0-9]{3}[ .-]?[0-9]{4}$', 1)", "c", f"concat(c, {_refill('substring(m, length(c) + 1)', _digits(key, 'phone', 'right(n, 10)'))})"),
    )
    ip = _let(
        "transform(split(m, '[.]'), x -> cast(x AS bigint))", "o", _let(feistel(key, "ip", "o[0] * 256 + o[1]", "o[2] * 256 + o[3]", "65536L", "65536L"), "z", "concat_ws('.', z.x div 256, z.x % 256, z.y div 256, z.y % 256)")
    )
    ssn = _let(
        "transform(split(m, '-'), x -> cast(x AS bigint))",
        "o",
        "if(o[0] BETWEEN 1 AND 899 AND o[0] <> 666 AND o[1] > 0 AND o[2] > 0, "
        + _let(
            feistel(key, "ssn", "(o[0] - if(o[0] > 666, 2, 1)) * 99 + o[1] - 1", "o[2] - 1", "898L * 99", "9999L"),
            "z",
            "concat_ws('-', lpad(cast(z.x div 99 + if(z.x div 99 + 1 >= 666, 2, 1) AS string), 3, '0'), lpad(cast(z.x % 99 + 1 AS string), 2, '0'), lpad(cast(z.y + 1 AS string), 4, '0'))",
        )
        + ", m)",
    )
    # parts of a date as numbers, by its separator; of day and month the first is the day, unless only the month can be
    cut = "transform(split(m, '[-/.]'), x -> cast(x AS bigint))"
    valid = lambda y, mo, d: f"try_cast(concat_ws('-', lpad(cast({y} AS string), 4, '0'), lpad(cast({mo} AS string), 2, '0'), lpad(cast({d} AS string), 2, '0')) AS date)"
    write = lambda a, b, y: f"concat(if(short, cast({a} AS string), lpad(cast({a} AS string), 2, '0')), sep, if(short, cast({b} AS string), lpad(cast({b} AS string), 2, '0')), sep, lpad(cast({y} AS string), 4, '0'))"
    moved_day = lambda n: _let(feistel(key, "date", f"pmod({n}, 73000) div 365", f"pmod({n}, 73000) % 365", "200L", "365L"), "z", f"date_add(DATE'1900-01-01', cast(floor({n} / 73000) * 73000 + z.x * 365 + z.y AS int))")
    days = lambda v: f"datediff({v}, DATE'1900-01-01')"
    iso = _let(f"{days('try_cast(m AS date)')}", "n", f"if(n IS NULL, m, date_format({moved_day('n')}, 'yyyy-MM-dd'))")
    day_first = _let(days(valid("o[2]", "o[1]", "o[0]")), "n", f"if(n IS NULL, NULL, {_let(moved_day('n'), 'v', write('day(v)', 'month(v)', 'year(v)'))})")
    block = "(o[2] - pmod(o[2] - 1900, 200))"
    early = _let(feistel(key, "month first", "pmod(o[2] - 1900, 200)", "(o[0] - 1) * 16 + o[1] - 13", "200L", "192L"), "z", write("z.y div 16 + 1", "z.y % 16 + 13", f"{block} + z.x"))
    months = "if(o[1] = 31, array(1, 3, 5, 7, 8, 10, 12), array(1, 3, 4, 5, 6, 7, 8, 9, 10, 11, 12))"
    late = _let(months, "ms", _let(feistel(key, "month end", "pmod(o[2] - 1900, 200)", "array_position(ms, cast(o[0] AS int)) - 1", "200L", "cast(size(ms) AS bigint)"), "z", write("ms[cast(z.y AS int)]", "o[1]", f"{block} + z.x")))
    leap = f"if(o[2] BETWEEN 1904 AND 2096, {_let(feistel(key, 'leap day', '(o[2] - 1904) div 4 div 7', '(o[2] - 1904) div 4 % 7', '7L', '7L'), 'z', write('o[0]', 'o[1]', '1904 + 4 * (z.x * 7 + z.y)'))}, m)"
    month_first = f"if({valid('o[2]', 'o[0]', 'o[1]')} IS NULL OR sep <> '/', m, CASE WHEN o[1] <= 28 THEN {early} WHEN o[0] = 2 THEN {leap} ELSE {late} END)"
    other = _let(cut, "o", _let("if(m LIKE '%/%', '/', '.')", "sep", _let("length(m) < 10", "short", f"coalesce({day_first}, {month_first})")))
    date = f"if(substring(m, 5, 1) = '-', {iso}, {other})"
    intl = _let(
        "regexp_replace(m, '[^0-9]', '')",
        "n",
        _let(f"length(regexp_extract(n, '^{COUNTRY}', 0))", "c", f"if(length(n) BETWEEN 8 AND 15, {_refill('m', f'concat(left(n, c), {_digits(key, "intl", "substring(n, c + 1)")})')}, m)"),
    )
    local = _let("regexp_replace(m, '[^0-9]', '')", "n", _refill("m", _digits(key, "local", "n")))
    shift = lambda c, s, base, n: f"chr({base} + (ascii({c}) - {base} + {s}) % {n})"
    step = lambda c, s: f"CASE WHEN {c} BETWEEN 'a' AND 'z' THEN {shift(c, s, 97, 26)} WHEN {c} BETWEEN 'A' AND 'Z' THEN {shift(c, s, 65, 26)} WHEN {c} BETWEEN '0' AND '9' THEN {shift(c, s, 48, 10)} ELSE {c} END"
    moved = lambda half, other: _let(_hash(key, "email", "r", other), "h", f"array_join(transform(split({half}, ''), (c, i) -> {step('c', "cast(conv(substring(h, 2 * i + 1, 2), 16, 10) AS int)")}), '')")
    mixed = f"aggregate(sequence(0, {ROUNDS - 1}), named_struct('x', left(n, cast(ceil(length(n) / 2) AS int)), 'y', right(n, cast(floor(length(n) / 2) AS int))), (s, r) -> if(r % 2 = 0 OR s.y = '', named_struct('x', {moved('s.x', 's.y')}, 'y', s.y), named_struct('x', s.x, 'y', {moved('s.y', 's.x')})), s -> concat(s.x, s.y))"
    email = _let("substring_index(m, '@', 1)", "n", f"concat({mixed}, substring(m, length(n) + 1))")
    return {"email": email, "ip": ip, "date": date, "ssn": ssn, "card": card, "phone": phone, "intl": intl, "local": local}


def _kind() -> str:
    return "CASE " + " ".join(f"WHEN regexp_like(m, {_q('^(?:' + p + ')$')}) THEN '{k}'" for k, p in KINDS.items()) + " END"


def pseudonymise(docs: DataFrame, key: str = KEY) -> DataFrame:
    """All columns of docs with the text rewritten, and n_found: how many values were replaced. A column of that name in docs is replaced."""
    found = F.when(F.col("text").rlike("[0-9@]"), F.regexp_extract_all("text", F.lit(ANY), F.lit(0))).otherwise(F.array().cast("array<string>"))
    name = free_name(docs, "found")
    with_found = docs.withColumn(name, found)
    typed = with_found.withColumn(name, F.expr(f"transform({name}, m -> named_struct('m', m, 'k', {_kind()}))"))
    by_kind = " ".join(f"WHEN '{k}' THEN {e}" for k, e in _pseudonyms(key).items())
    new = typed.withColumn(name, F.expr(f"transform({name}, v -> named_struct('k', v.k, 'm', v.m, 'p', {_let('v.m', 'm', f'CASE v.k {by_kind} ELSE m END')}))"))
    rebuilt = F.expr(f"if(size({name}) = 0, text, array_join(zip_with(split(text, {_q(ANY)}, -1), transform({name}, v -> v.p), (a, b) -> concat(a, coalesce(b, ''))), ''))")
    out = new.withColumn("text", rebuilt).withColumn("n_found", F.expr(f"size(filter({name}, v -> v.p <> v.m))").cast("long"))
    return out.drop(name)


def op1_pii(spark, sf_dir) -> DataFrame:
    return pseudonymise(pick(table(spark, sf_dir, "documents"), "doc_id", "text"))
