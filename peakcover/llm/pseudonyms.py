"""Format-preserving pseudonyms for personal numbers, dates, addresses and secrets, in DataFrame operations only.

A text is cut wherever one of the patterns can start, so candidates may overlap.  At each cut the kinds are tried
in order, the more specific first, and the first that validates (Luhn for cards, length by country and modulo 97
for IBANs, octets, calendar dates, number ranges) is taken; one that does not validate hides nothing behind it.
A taken value is replaced by a keyed permutation of its own format: an alternating Feistel network over two
halves of the value, whose round function is SHA-256 of key, kind, round and half, reduced to the half's size.
It is a bijection on the format, so equal values get equal pseudonyms in all documents and different values
different ones; check digits are set anew.  Separators take no part: a card, an IBAN or a phone number written
in several ways is one value, and so is a date.

Defined cases: null texts stay null; candidates that fail validation stay as they are; of overlapping values the
first is replaced; patterns are bounded and possessive, so very long texts cost time in proportion to their
length; dates have the years 1 to 9999 and stay in their period (before 100, four centuries at a time from 100
on, 1700 to 1899, 1900 to 2099, from 9700 on); a secret is what stands after a word for one and has a digit, or
a token of a known form; rows are independent, so repeated rows get equal results and an empty table gives none;
added columns replace columns of their name.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .line_dedup import let

#: The key of the registered query alone, where the session names none; the operator has no default.
TEST_KEY = "public test key"
KEY_SETTING = "spark.peakcover.pseudonym.key"
ROUNDS = 10
SECRET_WORD = r"(?i:passw(?:or)?d|passphrase|pwd|secret|token|api[_-]?key|access[_-]?key|private[_-]?key|credential)s?"
SECRET_SIGN = r"[\"']?\s{0,4}+(?::=|=>|[:=])\s{0,4}+[\"']?"
#: Fixed patterns, the more specific kinds first; each repetition is bounded, and possessive where it is of a group.
PATTERNS = {
    "email": (r"(?<![\w.%+-])[A-Za-z0-9._%+-]{1,64}+@[A-Za-z0-9-]{1,63}+(?:\.[A-Za-z0-9-]{1,63}+){1,126}+",),
    "secret": (r"(?<![A-Za-z])" + SECRET_WORD + SECRET_SIGN + r"(?=[A-Za-z_+/=~.-]{0,255}+[0-9])[A-Za-z0-9_+/=~.-]{8,256}+", r"(?<![A-Za-z0-9])(?:(?:AKIA|ASIA)[0-9A-Z]{16}|gh[opsu]_[A-Za-z0-9]{36})(?!\w)"),
    "iban": (r"(?<!\w)[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]){11,30}",),
    "date": (r"(?<![\w./-])(?:[0-9]{4}-[0-9]{2}-[0-9]{2}|[0-9]{2}\.[0-9]{2}\.[0-9]{4}|[0-9]{2}/[0-9]{2}/[0-9]{4})(?![\w/-])",),
    "ip": (r"(?<![\w.])[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?!\w|\.[0-9])",),
    "ssn": (r"(?<![\w-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![\w-])",),
    "card": (r"(?<!\w)[0-9]{13,19}(?!\w)", r"(?<!\w)[0-9]{4}(?: [0-9]{4}){3} [0-9]{1,3}(?!\w)", r"(?<!\w)[0-9]{4}(?:-[0-9]{4}){3}-[0-9]{1,3}(?!\w)", r"(?<!\w)[0-9]{4}(?: [0-9]{4}){3}(?!\w)", r"(?<!\w)[0-9]{4}(?:-[0-9]{4}){3}(?!\w)", r"(?<!\w)[0-9]{4}(?: [0-9]{6} |-[0-9]{6}-)[0-9]{4,5}(?!\w)"),
    "phone": (r"(?<!\w)(?:\+[0-9]{1,3}[ .-]?)?(?:\([0-9]{2,4}\)[ .-]?|[0-9]{2,4}[ .-])[0-9]{3}[ .-]?[0-9]{3,4}(?!\w)", r"(?<!\w)\+[0-9]{8,15}(?!\w)"),
}
START = "(?=" + "|".join(p for forms in PATTERNS.values() for p in forms) + ")"
THOUSANDS = r"^[0-9]{1,3}([ .])[0-9]{3}\1[0-9]{3}$"
#: The lengths of IBANs by country, and the calling codes of one and two digits.
IBAN_LENGTHS = "AD24 AE23 AL28 AT20 AZ28 BA20 BE16 BG22 BH22 BR29 BY28 CH21 CR22 CY28 CZ24 DE22 DK18 DO28 EE20 EG29 ES24 FI18 FO18 FR27 GB22 GE22 GI23 GL18 GR27 GT28 HR21 HU28 IE22 IL23 IQ23 IS26 IT27 JO30 KW30 KZ20 LB28 LC32 LI21 LT20 LU20 LV21 LY25 MC27 MD24 ME22 MK19 MR27 MT31 MU30 NL18 NO15 PK24 PL28 PS29 PT25 QA29 RO24 RS22 SA24 SC31 SE24 SI19 SK24 SM27 ST25 SV28 TL23 TN24 TR26 UA29 VA22 VG24 XK20"
CALLING_CODE = "^(1|7|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|[0-9]{3})"
DATE_FORMS = ("yyyy-MM-dd", "dd.MM.yyyy", "MM/dd/yyyy", "dd/MM/yyyy")
#: First year of a period, first year after it, and two factors of its number of days; four centuries have 189 x 773.
PERIODS = ((1, 100, 51, 709), (1700, 1900, 184, 397), (1900, 2100, 17, 4297), (9700, 10000, 276, 397))
#: A value is looked for in so many characters, and so many cuts, from its start on.
REACH, CUTS = 400, 32
BLOCK = 256


def quoted(value: str) -> str:
    return "'" + value.replace("\\", "\\\\").replace("'", "\\'") + "'"


def feistel(left: str, right: str, left_size: str, right_size: str, kind: str, key: str) -> str:
    """SQL for the struct (l, r) that the keyed permutation of left_size x right_size values makes of two numbers."""
    pull = f"cast(conv(substr(sha2(concat_ws('|', {quoted(key)}, {kind}, i, {{x}}), 256), 1, 13), 16, 10) as bigint)"
    odd = f"named_struct('l', pmod(f.l + {pull.format(x='f.r')} % s.a, s.a), 'r', f.r)"
    even = f"named_struct('l', f.l, 'r', pmod(f.r + {pull.format(x='f.l')} % s.b, s.b))"
    run = f"aggregate(sequence(1, {ROUNDS}), named_struct('l', s.l, 'r', s.r), (f, i) -> if(i % 2 = 1, {odd}, {even}))"
    return let("s", f"named_struct('l', cast({left} as bigint), 'r', cast({right} as bigint), 'a', cast({left_size} as bigint), 'b', cast({right_size} as bigint))", run)


def in_format(value: str, kind: str, key: str, hexadecimal: bool = False) -> str:
    """SQL that permutes the digits and letters of a text, class by class; other characters stay.

    Texts of more than 24 characters are permuted in blocks of 24, each keyed by its number and the block before it.
    """
    letters = 6 if hexadecimal else 26
    radix = f"CASE WHEN c >= '0' AND c <= '9' THEN 10 WHEN rlike(c, '^[a-zA-Z]$') THEN {letters} ELSE 1 END"
    digit = "CASE WHEN c >= '0' AND c <= '9' THEN ascii(c) - 48 WHEN rlike(c, '^[a-z]$') THEN ascii(c) - 97 WHEN rlike(c, '^[A-Z]$') THEN ascii(c) - 65 ELSE 0 END"
    chars = f"transform(filter(split(b.t, ''), c -> c <> ''), c -> named_struct('c', c, 'k', cast({radix} as bigint), 'd', cast({digit} as bigint)))"
    fold = "aggregate({part}, 0L, (t, z) -> if(z.k = 1, t, t * z.k + z.d))"
    size = "aggregate({part}, 1L, (t, z) -> t * z.k)"
    l, r = "slice(m.cs, 1, size(m.cs) div 2)", "slice(m.cs, size(m.cs) div 2 + 1, size(m.cs))"
    mixed = feistel(fold.format(part=l), fold.format(part=r), size.format(part=l), size.format(part=r), f"concat({quoted(kind)}, b.p)", key)
    # digits come back from the last place to the first
    back = "aggregate(reverse({part}), named_struct('v', {v}, 's', ''), (t, z) -> named_struct('v', if(z.k = 1, t.v, t.v div z.k), 's', concat(CASE WHEN z.k = 1 THEN z.c WHEN z.c <= '9' THEN cast(t.v % z.k as string) ELSE char(cast(if(z.c >= 'a', 97, 65) + t.v % z.k as int)) END, t.s))).s"
    block = let("m", f"named_struct('cs', {chars})", let("e", mixed, f"concat({back.format(part=l, v='e.l')}, {back.format(part=r, v='e.r')})"))
    blocks = "transform(sequence(0, greatest(0, (length(w) - 1) div 24)), j -> named_struct('t', substr(w, j * 24 + 1, 24), 'p', if(j = 0, '', concat(j, substr(w, j * 24 - 23, 24)))))"
    return let("w", value, f"array_join(transform({blocks}, b -> {block}), '')")


def refilled(shape: str, signs: str) -> str:
    """SQL for ``shape`` with its letters and digits replaced, in order, by the characters of ``signs``."""
    step = "if(rlike(c, '^[0-9A-Za-z]$'), named_struct('n', t.n + 1, 's', concat(t.s, substr(h.d, t.n + 1, 1))), named_struct('n', t.n, 's', concat(t.s, c)))"
    return let("h", f"named_struct('d', {signs})", f"aggregate(filter(split({shape}, ''), c -> c <> ''), named_struct('n', 0, 's', ''), (t, c) -> {step}).s")


def luhn_sum(digits: str, doubled: int) -> str:
    """SQL for the Luhn sum of a digit string; every other digit from the right counts double, from the first (0) or second (1)."""
    d = "cast(substr(reverse(g), j + 1, 1) as int)"
    return let("g", digits, f"aggregate(sequence(0, length(g) - 1), 0, (t, j) -> t + if(j % 2 = {doubled}, {d} * 2 - if({d} > 4, 9, 0), {d}))")


def mod97(value: str) -> str:
    """SQL for the remainder of an IBAN without spaces: the first four characters moved to the end, letters as 10 to 35."""
    moved = f"concat(substr({value}, 5), substr({value}, 1, 4))"
    return f"aggregate(filter(split({moved}, ''), c -> c <> ''), 0, (t, c) -> cast(if(c <= '9', t * 10 + ascii(c) - 48, t * 100 + ascii(c) - 55) % 97 as int))"


def digits_of(x: str) -> str:
    return f"regexp_replace({x}, '[^0-9]', '')"


def date_of(x: str) -> str:
    return "coalesce(" + ", ".join(f"to_date(try_to_timestamp({x}, '{f}'))" for f in DATE_FORMS) + ")"


def form_of(x: str) -> str:
    return "CASE " + " ".join(f"WHEN try_to_timestamp({x}, '{f}') IS NOT NULL THEN '{f}'" for f in DATE_FORMS) + " END"


def at_start(x: str, pattern: str) -> str:
    """SQL for what the pattern matches after the first character of ``x``, empty if nothing."""
    return f"regexp_extract({x}, {quoted('(?s)^.(' + pattern + ')')}, 1)"


def iban_at(x: str) -> str:
    """SQL for the IBAN of its country's length (or, for an unknown country, of any) that starts at ``x``, spaces included."""
    lengths = "map(" + ", ".join(f"'{e[:2]}', {e[2:]}" for e in IBAN_LENGTHS.split()) + ")"
    exact = f"regexp_extract(y, concat('^[A-Z]{{2}}[0-9]{{2}}(?: ?[A-Z0-9]){{', {lengths}[substr(y, 1, 2)] - 4, '}}(?![A-Za-z0-9])'), 0)"
    cut = let("y", at_start(x, PATTERNS["iban"][0]), f"CASE WHEN y = '' THEN '' WHEN {lengths}[substr(y, 1, 2)] IS NULL THEN {at_start(x, PATTERNS['iban'][0] + '(?![A-Za-z0-9])')} ELSE {exact} END")
    return let("u", cut, f"if(u <> '' AND {mod97(f'replace(u, {quoted(chr(32))}, {quoted(str())})')} = 1, u, '')")


def found_at(x: str) -> str:
    """SQL for the first valid value after the first character of ``x``: struct (k: kind, v: text), null if none."""
    valid = {
        "email": "true", "secret": "true",
        "date": f"{date_of('u')} IS NOT NULL",
        "ip": "forall(split(u, '[.]'), o -> cast(o as int) <= 255)",
        "ssn": "substr(u, 1, 3) NOT IN ('000', '666') AND substr(u, 1, 1) <> '9' AND substr(u, 5, 2) <> '00' AND substr(u, 8) <> '0000'",
        "card": f"{luhn_sum(digits_of('u'), 1)} % 10 = 0",
        "phone": f"NOT rlike(u, {quoted(THOUSANDS)})",
    }
    tried = []
    for kind, forms in PATTERNS.items():
        for p in forms:
            value = iban_at(x) if kind == "iban" else let("u", at_start(x, p), f"CASE WHEN u = '' THEN '' WHEN {valid[kind]} THEN u ELSE '' END")
            tried.append(f"named_struct('k', '{kind}', 'v', {value})")
    return f"get(filter(array({', '.join(tried)}), t -> t.v <> ''), 0)"


def pseudonym_of(x: str, kind: str, key: str) -> str:
    """SQL for the pseudonym of a validated value."""
    name, host = f"substring_index({x}, '@', 1)", f"substring_index({x}, '@', -1)"
    top = f"substring_index({host}, '.', -1)"
    email = f"concat({in_format(name, 'email', key)}, '@', {in_format(f'substr({host}, 1, length({host}) - length({top}) - 1)', 'host', key)}, '.', {top})"
    number = f"aggregate(slice(split({x}, '[.]'), {{a}}, 2), 0L, (t, o) -> t * 256 + cast(o as bigint))"
    ip = let("e", feistel(number.format(a=1), number.format(a=3), "65536", "65536", "'ip'", key), "concat_ws('.', e.l div 256, e.l % 256, e.r div 256, e.r % 256)")
    choose = lambda i: "CASE " + " ".join(f"WHEN year(p.d) >= {q[0]} AND year(p.d) < {q[1]} THEN {q[i]}" for q in PERIODS) + f" ELSE {('100 + 400 * ((year(p.d) - 100) div 400)', None, 189, 773)[i]} END"
    period = f"named_struct('d', p.d, 's', make_date({choose(0)}, 1, 1), 'a', {choose(2)}, 'b', {choose(3)})"
    moved = let("e", feistel("datediff(q.d, q.s) div q.b", "datediff(q.d, q.s) % q.b", "q.a", "q.b", "'date'", key), f"date_format(date_add(q.s, cast(e.l * q.b + e.r as int)), {form_of(x)})")
    date = let("p", f"named_struct('d', {date_of(x)})", let("q", period, moved))
    area = f"cast(substr({x}, 1, 3) as int)"
    # the 898 areas without 000 and 666, and groups and serials without zeros, counted from 0
    ssn = let("e", feistel(f"{area} - if({area} > 666, 2, 1)", f"(cast(substr({x}, 5, 2) as int) - 1) * 9999 + cast(substr({x}, 8) as int) - 1", "898", str(99 * 9999), "'ssn'", key), "concat_ws('-', lpad(e.l + if(e.l + 1 >= 666, 2, 1), 3, '0'), lpad(e.r div 9999 + 1, 2, '0'), lpad(e.r % 9999 + 1, 4, '0'))")
    bare = let("e", in_format(f"substr({digits_of(x)}, 1, length({digits_of(x)}) - 1)", "card", key), f"concat(e, (10 - {luhn_sum('e', 0)} % 10) % 10)")
    card = refilled(x, bare)
    solid = f"replace({x}, ' ', '')"
    code = let("e", f"concat(substr({solid}, 1, 2), '00', {in_format(f'substr({solid}, 5)', 'iban', key)})", f"concat(substr(e, 1, 2), lpad(98 - {mod97('e')}, 2, '0'), substr(e, 5))")
    iban = refilled(x, code)
    called = f"if(startswith({x}, '+'), regexp_extract({digits_of(x)}, {quoted(CALLING_CODE)}, 1), '')"
    phone = let("a", called, refilled(x, f"concat(a, {in_format(f'substr({digits_of(x)}, length(a) + 1)', 'phone', key)})"))
    word = f"regexp_extract({x}, {quoted('^(?:' + SECRET_WORD + SECRET_SIGN + '|A[KS]IA|gh[opsu]_)')}, 0)"
    secret = let("a", word, let("y", f"substr({x}, length(a) + 1)", f"concat(a, if(rlike(y, '^[0-9a-fA-F]+$'), {in_format('y', 'secret', key, hexadecimal=True)}, {in_format('y', 'secret', key)}))"))
    return f"CASE {kind} WHEN 'email' THEN {email} WHEN 'ip' THEN {ip} WHEN 'date' THEN {date} WHEN 'ssn' THEN {ssn} WHEN 'card' THEN {card} WHEN 'iban' THEN {iban} WHEN 'phone' THEN {phone} WHEN 'secret' THEN {secret} END"


def pseudonymise(docs: DataFrame, key: str, text: str = "text") -> DataFrame:
    """All rows of ``docs`` with the text's validated values replaced, and ``found``: the values replaced, by kind."""
    body = f"`{text}`"
    window = f"concat(if(k = 0, '\\n', right(v.ps[k - 1], 1)), substr(array_join(transform(slice(v.ps, k + 1, {CUTS}), q -> substr(q, 1, {REACH})), ''), 1, {REACH}))"
    judged = let("x", window, let("g", found_at("x"), "named_struct('p', p, 'n', length(p), 'k', g.k, 'v', g.v)"))
    cuts = f"transform(v.ps, (p, k) -> {judged})"
    # left to right: -1 is a value, else so many characters belong to a value that began before
    step = "CASE WHEN s.left > 0 THEN named_struct('left', greatest(s.left - z.n, 0), 'drop', concat(s.drop, array(least(s.left, z.n)))) WHEN z.k IS NOT NULL THEN named_struct('left', greatest(length(z.v) - z.n, 0), 'drop', concat(s.drop, array(-1))) ELSE named_struct('left', 0, 'drop', concat(s.drop, array(0))) END"
    # block by block, as a state that grows with the whole text would be copied at every cut
    part = f"aggregate(slice(c.cs, b * {BLOCK} + 1, {BLOCK}), named_struct('left', a.left, 'drop', cast(array() as array<int>)), (s, z) -> {step})"
    parts = let("u", part, "named_struct('left', u.left, 'drops', concat(a.drops, array(u.drop)))")
    taken = f"flatten(aggregate(sequence(0, (size(c.cs) - 1) div {BLOCK}), named_struct('left', 0, 'drops', cast(array() as array<array<int>>)), (a, b) -> {parts}).drops)"
    fresh = f"concat(coalesce({pseudonym_of('z.v', 'z.k', key)}, z.v), substr(z.p, length(z.v) + 1))"
    glued = f"array_join(transform(c.cs, (z, k) -> if(d[k] = -1, {fresh}, substr(z.p, d[k] + 1))), '')"
    kinds = "transform(filter(c.cs, (z, k) -> d[k] = -1), z -> z.k)"
    row = let("v", f"named_struct('ps', split({body}, {quoted(START)}, -1))", let("c", f"named_struct('cs', {cuts})", let("d", taken, f"named_struct('text', {glued}, 'kinds', {kinds})")))
    kept = [F.col(c) for c in docs.columns if c not in (text, "found")]
    work = docs.withColumn("__new", F.expr(f"CASE WHEN rlike({body}, {quoted(START)}) THEN {row} END"))
    counts = F.expr("map_from_entries(transform(array_sort(array_distinct(coalesce(__new.kinds, array()))), k -> named_struct('key', k, 'value', cast(size(filter(__new.kinds, z -> z = k)) as bigint))))")
    return work.select(*kept, F.coalesce("__new.text", text).alias(text), counts.alias("found"))


def op6_pseudonyms(spark, sf_dir: str) -> DataFrame:
    """The key is the session's ``spark.peakcover.pseudonym.key``, or the public test key."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = pseudonymise(docs, spark.conf.get(KEY_SETTING, TEST_KEY))
    return out.select("doc_id", "text", F.expr("aggregate(map_values(found), 0L, (t, n) -> t + n)").alias("n_values"), F.to_json("found").alias("found"))
