"""Format-preserving pseudonyms for personal data. DataFrame functions only.

Matches are validated (card numbers by the Luhn digit, IBANs by their country's length and modulo 97, addresses by
their octets, dates by the calendar; phone and social security numbers, e-mail addresses and secrets by their shape only)
and put through a keyed Feistel network over their own alphabet, so the pseudonym has the same format, equal values
get equal pseudonyms in all documents, and whoever has the key can undo it. Check digits are computed anew, so
pseudonyms are valid too. What fails validation is left alone. The domain of an e-mail address stays as it is.

In a run of groups of four digits every start is tried, so a card is found whatever digits stand before or after it.

Kinds: email (letters and digits of the local part), card, phone (last ten digits), ip, ssn, iban (digits
of the account), date (three notations, between 1900-01-01 and 2100-05-02), secret (access keys, hexadecimal
values after a name such as token or password, and quoted ones of 20 digits or more).

Defined cases: a null text stays null; a text without matches is returned as it is; overlapping candidates
are taken from left to right; the same row twice gives the same result twice; long texts are handled whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kbspark.llm.common import unused

# One pattern for each kind of candidate; the first that matches at a place wins.
IBAN_LENGTHS = {
    "AD": 24, "AE": 23, "AL": 28, "AT": 20, "AZ": 28, "BA": 20, "BE": 16, "BG": 22, "BH": 22, "BR": 29, "CH": 21, "CR": 22, "CY": 28, "CZ": 24, "DE": 22, "DK": 18, "DO": 28, "EE": 20,
    "EG": 29, "ES": 24, "FI": 18, "FO": 18, "FR": 27, "GB": 22, "GE": 22, "GI": 23, "GL": 18, "GR": 27, "GT": 28, "HR": 21, "HU": 28, "IE": 22, "IL": 23, "IQ": 23, "IS": 26, "IT": 27,
    "JO": 30, "KW": 30, "KZ": 20, "LB": 28, "LI": 21, "LT": 20, "LU": 20, "LV": 21, "MC": 27, "MD": 24, "ME": 22, "MK": 19, "MR": 27, "MT": 31, "MU": 30, "NL": 18, "NO": 15, "PK": 24,
    "PL": 28, "PT": 25, "QA": 29, "RO": 24, "RS": 22, "SA": 24, "SE": 24, "SI": 19, "SK": 24, "SM": 27, "TN": 24, "TR": 26, "UA": 29, "VA": 22, "VG": 24, "XK": 20,
}


def iban_pattern() -> str:
    """Each country's account in groups of four with or without blanks, no longer and no shorter; other countries, any length."""
    by_length: dict[int, list[str]] = {}
    for country, n in IBAN_LENGTHS.items():
        by_length.setdefault(n - 4, []).append(country)
    exact = [f"(?:{'|'.join(cs)})[0-9]{{2}}(?: ?[A-Z0-9]{{4}}){{{n // 4}}}" + (f" ?[A-Z0-9]{{{n % 4}}}" if n % 4 else "") for n, cs in sorted(by_length.items())]
    other = f"(?!{'|'.join(IBAN_LENGTHS)})[A-Z]{{2}}[0-9]{{2}}(?: ?[A-Z0-9]{{4}}){{2,7}}(?: ?[A-Z0-9]{{1,3}})?"
    return f"(?<![A-Za-z0-9])(?=[A-Z]{{2}}[0-9]{{2}})(?:{'|'.join([*exact, other])})(?![A-Za-z0-9])"


OCTET = "(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
PATTERNS = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9][A-Za-z0-9._%+-]*+@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)+",
    "iban": iban_pattern(),
    "phone": r"(?<![0-9+(])(?:\+?[0-9]{1,3}[ .-]?)?\([0-9]{3}\)[ .-]?[0-9]{3}[ .-]?[0-9]{4}(?![0-9])|(?<![0-9+])\+[0-9]{1,3}[ .-][0-9]{3}[ .-][0-9]{3}[ .-][0-9]{4}(?![0-9])",
    "date": r"(?<![0-9-])(?:19|20|21)[0-9]{2}-[01][0-9]-[0-3][0-9](?![0-9-])|(?<![0-9./])[0-3][0-9]([./])[01][0-9]\1(?:19|20|21)[0-9]{2}(?![0-9])",
    "ssn": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    "ip": rf"(?<![0-9.]){OCTET}(?:\.{OCTET}){{3}}(?![0-9]|\.[0-9])",
    "card": r"(?<![0-9])[0-9]{13,19}(?![0-9])",
    "cards": r"(?<![0-9])[0-9]{4}(?:[ -][0-9]{4}(?![0-9]|[./-][0-9]{2}[./-])){2,}+(?:[ -][0-9]{1,3}(?![0-9]|[ ./-][0-9]))?",
    "split_card": r"(?<![0-9])[0-9](?:[ -]?[0-9]){12,18}(?![0-9])",
    "secret": r"(?<![A-Za-z0-9])AKIA[A-Z0-9]{16}(?![A-Za-z0-9])|(?i:token|password|passwd|secret|api[_-]?key) ?[=:] ?\"?[0-9A-Fa-f]{12,}+|(?<=\")[0-9A-Fa-f]{20,}+(?=\")",
}
ANY = "|".join(f"(?:{p})" for p in PATTERNS.values())
#: Every kind has one of these; most texts have none, and are passed on after this one scan.
SIGNS = "[0-9@]|AKIA|(?i:token|passw|secret|api.?key)"
DAYS = (270, 271)  # their product is the number of days that dates are permuted in
ROUNDS = 10


def powers(radix: int, n: int) -> Column:
    return F.array(*(F.lit(radix**i).cast("long") for i in range(n + 1)))


def feistel(a: Column, b: Column, mod_a: Column, mod_b: Column, key: str, tweak: Column) -> Column:
    """A keyed permutation of the pairs (a, b) with a < mod_a and b < mod_b, as a struct with a and b."""
    start = F.struct(a.cast("long").alias("a"), b.cast("long").alias("b"), mod_a.cast("long").alias("p"), mod_b.cast("long").alias("q"))

    def one(s: Column, i: Column) -> Column:
        seed = F.concat(F.lit(key + "|"), tweak, F.lit("|"), i.cast("string"), F.lit("|"), s["b"].cast("string"))
        shift = F.conv(F.substring(F.sha2(seed, 256), 1, 15), 16, 10).cast("long")
        return F.struct(s["b"].alias("a"), ((s["a"] + shift % s["p"]) % s["p"]).alias("b"), s["q"].alias("p"), s["p"].alias("q"))

    return F.aggregate(F.array(*map(F.lit, range(ROUNDS))), start, one)


def permute(s: Column, radix: int, key: str, tweak: Column) -> Column:
    """A permutation of the strings of s's length over the first `radix` of 0-9a-z; long ones go in chunks."""
    half = {10: 17, 16: 14, 36: 11}[radix]
    width = 2 * half

    def chunk(at: Column) -> Column:
        c = F.substr(s, at, F.lit(width))
        u, v = F.floor(F.length(c) / 2).cast("int"), (F.length(c) - F.floor(F.length(c) / 2)).cast("int")
        number = lambda x: F.coalesce(F.conv(F.when(x == "", "0").otherwise(x), radix, 10).cast("long"), F.lit(0))
        mods = powers(radix, half)
        both = feistel(number(F.substr(c, F.lit(1), u)), number(F.substr(c, u + 1, v)), F.element_at(mods, u + 1), F.element_at(mods, v + 1), key, F.concat(tweak, F.lit(":"), F.length(s).cast("string"), F.lit(":"), at.cast("string")))
        # A lambda over an array of one, so that the network runs once for both halves.
        cut = lambda x, n: F.when(n > 0, F.right(F.lpad(F.lower(F.conv(x.cast("string"), 10, radix)), half, "0"), n)).otherwise(F.lit(""))
        return F.element_at(F.transform(F.array(both), lambda r: F.concat(cut(r["a"], u), cut(r["b"], v))), 1)

    chunks = F.transform(F.sequence(F.lit(1), F.greatest(F.length(s), F.lit(1)), F.lit(width)), chunk)
    return F.when(F.length(s) > 0, F.array_join(chunks, "")).otherwise(s)


def cased(shape: Column, new: Column) -> Column:
    """new, in capitals if shape is."""
    return F.when(shape == F.upper(shape), F.upper(new)).otherwise(new)


def luhn(digits: Column) -> Column:
    return F.call_function("luhn_check", digits)


def refill(shape: Column, new: Column, cls: str) -> Column:
    """shape with its characters of the class replaced, in order, by those of new."""
    start = F.struct(F.lit("").alias("out"), F.lit(1).alias("i"))

    def one(s: Column, c: Column) -> Column:
        hit = c.rlike(cls)
        return F.struct(F.concat(s["out"], F.when(hit, F.substr(new, s["i"], F.lit(1))).otherwise(c)).alias("out"), (s["i"] + hit.cast("int")).alias("i"))

    return F.aggregate(F.split(shape, ""), start, one, lambda s: s["out"])


def only(s: Column, cls: str) -> Column:
    return F.regexp_replace(s, f"[^{cls}]", "")


def mod97(s: Column) -> Column:
    """The IBAN remainder of a string of digits and capital letters."""
    value = lambda c: F.conv(c, 36, 10).cast("int")
    return F.aggregate(F.split(s, ""), F.lit(0), lambda acc, c: F.when(c == "", acc).otherwise((acc * F.when(c.rlike("[A-Z]"), 100).otherwise(10) + value(c)) % 97))


def card_run(groups: Column, card_of) -> Column:
    """out (the digits, with cards replaced) and hits, for groups of four digits (the last may be shorter).

    From left to right: four groups and a shorter fifth, or four groups, or three and a shorter fourth, if they pass Luhn;
    else the first group stays and the next is tried.
    """
    start = F.struct(F.lit("").alias("out"), F.lit(0).alias("next"), F.lit(0).alias("hits"))

    def one(s: Column, i: Column) -> Column:
        joined = lambda n: F.array_join(F.slice(groups, i + 1, F.lit(n)), "")
        long_, short = joined(5), joined(4)
        picked = F.when(F.length(long_).between(17, 19) & luhn(long_), long_).when(F.length(short).between(13, 16) & luhn(short), short)
        took = lambda p: F.struct(
            F.concat(s["out"], F.when(p.isNotNull(), card_of(p)).otherwise(F.element_at(groups, i + 1))).alias("out"),
            (i + F.when(F.length(p) > 16, 5).when(p.isNotNull(), 4).otherwise(1)).cast("int").alias("next"),
            (s["hits"] + p.isNotNull().cast("int")).alias("hits"),
        )
        return F.when(i < s["next"], s).otherwise(F.element_at(F.transform(F.array(picked), took), 1))

    places = F.when(F.size(groups) > 0, F.sequence(F.lit(0), F.size(groups) - 1)).otherwise(F.array().cast("array<int>"))
    return F.aggregate(places, start, one)


def pseudonym(m: Column, key: str) -> Column:
    """A struct of kind and text for a candidate; kind is null, and the text its own, if it isn't valid."""
    digits = only(m, "0-9")

    def via(made: Column, f) -> Column:
        """f of made, evaluated once."""
        return F.element_at(F.transform(F.array(made), f), 1)

    at = F.instr(m, "@")
    local = F.substr(m, F.lit(1), at - 1)
    email = via(permute(F.lower(only(local, "A-Za-z0-9")), 36, key, F.lit("email")), lambda p: F.concat(refill(local, cased(local, p), "[A-Za-z0-9]"), F.substr(m, at)))

    n = F.length(digits)
    checked = lambda p: F.concat(p, F.element_at(F.filter(F.array(*(F.lit(str(i)) for i in range(10))), lambda c: luhn(F.concat(p, c))), 1))
    card_of = lambda d: F.element_at(F.transform(F.array(permute(F.substr(d, F.lit(1), F.length(d) - 1), 10, key, F.lit("card"))), checked), 1)
    card = via(card_of(digits), lambda p: refill(m, p, "[0-9]"))
    is_run = m.rlike(f"^{PATTERNS['cards']}$")
    run = card_run(F.when(is_run, F.split(m, "[ -]")).otherwise(F.array().cast("array<string>")), card_of)
    cards = F.when(run["hits"] > 0, refill(m, run["out"], "[0-9]"))
    phone = via(permute(F.right(digits, F.lit(10)), 10, key, F.lit("phone")), lambda p: refill(m, F.concat(F.substr(digits, F.lit(1), n - 10), p), "[0-9]"))
    ssn = via(permute(digits, 10, key, F.lit("ssn")), lambda p: refill(m, p, "[0-9]"))

    hexed = F.array_join(F.transform(F.split(m, r"\."), lambda o: F.lpad(F.conv(o, 10, 16), 2, "0")), "")
    ip = via(permute(F.lower(hexed), 16, key, F.lit("ip")), lambda p: F.array_join(F.transform(F.array(*map(F.lit, (1, 3, 5, 7))), lambda i: F.conv(F.substr(p, i, F.lit(2)), 16, 10)), "."))

    bare = F.replace(m, F.lit(" "), F.lit(""))
    country, account = F.substring(bare, 1, 2), F.substr(bare, F.lit(5))
    fresh = via(permute(only(account, "0-9"), 10, key, F.lit("iban")), lambda p: refill(account, p, "[0-9]"))
    iban = via(fresh, lambda p: refill(m, F.concat(country, F.lpad((98 - mod97(F.concat(p, country, F.lit("00")))).cast("string"), 2, "0"), p), "[A-Z0-9]"))
    iban_ok = (F.length(bare).between(15, 34)) & (mod97(F.concat(account, F.substring(bare, 1, 4))) == 1)

    sep = F.when(m.rlike("^[0-9]{4}"), "-").otherwise(F.substring(m, 3, 1))
    day = F.when(sep == "-", F.to_date(F.try_to_timestamp(m, F.lit("yyyy-MM-dd")))).otherwise(F.to_date(F.try_to_timestamp(F.translate(m, "./", "--"), F.lit("dd-MM-yyyy"))))
    off = F.date_diff(day, F.lit("1900-01-01").cast("date"))
    moved = lambda r: F.date_add(F.lit("1900-01-01").cast("date"), (r["a"] * DAYS[1] + r["b"]).cast("int"))
    shown = lambda r: F.when(sep == "-", F.date_format(moved(r), "yyyy-MM-dd")).otherwise(F.replace(F.date_format(moved(r), "dd-MM-yyyy"), F.lit("-"), sep))
    date = via(feistel(F.floor(off / DAYS[1]), off % DAYS[1], F.lit(DAYS[0]), F.lit(DAYS[1]), key, F.lit("date")), shown)

    name = F.when(m.rlike("^AKIA"), F.lit("AKIA")).otherwise(F.regexp_extract(m, r'^([^=:]*[=:] ?"?)', 1))
    body = F.substr(m, F.length(name) + 1)
    secret = F.when(name == "AKIA", F.concat(name, F.upper(permute(F.lower(body), 36, key, F.lit("secret"))))).otherwise(F.concat(name, cased(body, permute(F.lower(body), 16, key, F.lit("secret")))))

    is_ = lambda kind: m.rlike(f"^(?:{PATTERNS[kind]})$")
    made = lambda kind, text: F.struct(F.lit(kind).alias("kind"), text.alias("text"))
    return (
        F.when(at > 0, made("email", email))
        .when(m.rlike("^(?:AKIA|[A-Za-z_]+-?[A-Za-z]* ?[=:]|[0-9A-Fa-f]{20,}$)"), made("secret", secret))
        .when(m.rlike("^[A-Z]{2}") & iban_ok, made("iban", iban))
        .when(m.rlike("^[+(0-9]") & is_("phone"), made("phone", phone))
        .when(is_("date") & off.between(0, DAYS[0] * DAYS[1] - 1), made("date", date))
        .when(is_("ssn"), made("ssn", ssn))
        .when(is_("ip"), made("ip", ip))
        .when(is_run & cards.isNotNull(), made("card", cards))
        .when(~is_run & m.rlike("^[0-9]") & n.between(13, 19) & luhn(digits), made("card", card))
        .otherwise(F.struct(F.lit(None).cast("string").alias("kind"), m.alias("text")))
    )


def pseudonymise(docs: DataFrame, key: str, text: str = "text", found: str | None = None) -> DataFrame:
    """docs with the text rewritten and, if found names it, a column of the kinds of the matches that were replaced, in order."""
    if found in docs.columns:
        raise ValueError(f"documents have a column {found}: choose another name")
    t, m, p = F.col(text), unused("m", docs), unused("p", docs)
    looked = docs.withColumn(m, F.when(t.rlike(SIGNS), F.regexp_extract_all(t, F.lit(ANY), 0)).otherwise(F.array().cast("array<string>")))
    made = looked.withColumn(p, F.transform(m, lambda x: pseudonym(x, key)))
    ends = F.concat(F.transform(p, lambda x: x["text"]), F.array(F.lit("")))
    whole = F.array_join(F.flatten(F.zip_with(F.split(t, ANY, -1), ends, lambda g, x: F.array(g, x))), "")
    new = F.when(F.size(m) > 0, whole).otherwise(t)
    kinds = F.coalesce(F.array_compact(F.transform(p, lambda x: x["kind"])), F.array().cast("array<string>"))
    return made.select(*(new.alias(c) if c == text else F.col(c) for c in docs.columns), *([kinds.alias(found)] if found else []))


def pseudonymise_documents(docs: DataFrame, key: str) -> DataFrame:
    """doc_id, text (rewritten), n_pii (a run of card numbers counts once) and kinds (sorted, comma-joined) of all documents."""
    done = pseudonymise(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), key, found="found")
    return done.select("doc_id", "text", F.size("found").cast("long").alias("n_pii"), F.array_join(F.array_sort(F.array_distinct("found")), ",").alias("kinds"))
