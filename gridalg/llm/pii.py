"""Format-preserving pseudonyms for personal data, in DataFrame functions only.

Each match is validated (checksums, octets, calendar) and then permuted inside the values of its own format by
a keyed Feistel network over Z_a x Z_b, whose round function is a prefix of SHA-256. A permutation keeps equal
values equal and distinct values distinct in all documents, and needs no table of seen values: the same key
gives the same pseudonym on every executor and in every run. No expression repeats a group without a bound, so
that matching takes neither deep stacks nor more than linear time on hostile texts.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from gridalg.llm.native import fold, fresh, let

ROUNDS = 10
#: Candidate formats in order of preference.
#: Domains have 127 labels at most, and a repeated group takes stack for each.
EMAIL = r"(?<![\p{L}\p{M}0-9._%+-])[\p{L}\p{M}0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++){0,126}\.[A-Za-z]{2,}"
IPV4 = r"(?<![0-9.])[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?!\.?[0-9])"
ISO_DATE = r"(?<![0-9-])[0-9]{4}-[0-9]{2}-[0-9]{2}(?![0-9-])"
DAY_DATE = r"(?<![0-9/.])[0-9]{2}[/.][0-9]{2}[/.][0-9]{4}(?![0-9/])"
PHONE = r"(?<![0-9A-Za-z])(?:\+[0-9]{1,3}[ -]?)?(?:\([0-9]{3}\) ?|[0-9]{3}[ -])[0-9]{3}-[0-9]{4}(?![0-9A-Za-z-])"
ABROAD = r"(?<![0-9A-Za-z+])\+[0-9]{1,3}(?:[ .-][0-9]{2,4}){2,5}(?![0-9A-Za-z-])"
SSN = r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])"
IBAN = r"(?<![0-9A-Za-z])[A-Z]{2}[0-9]{2}[A-Z0-9]{11,30}(?![0-9A-Za-z])"
COMPACT = r"(?<![0-9A-Za-z+])\+[0-9]{8,15}(?![0-9A-Za-z])"
#: Countries by the length of their IBANs, which ends one printed in groups of four.
LENGTHS = {15: "NO", 16: "BE", 18: "DK FI FO GL NL", 19: "MK SI", 20: "AT BA EE KZ LT LU XK", 21: "CH HR LI LV", 22: "BG BH CR DE GB GE IE ME RS VA", 23: "AE GI IL IQ TL", 24: "AD CZ ES MD PK SA SE SK TN VG", 25: "LY PT", 26: "IS TR", 27: "FR GR IT MC MR SM", 28: "AL AZ BY CY DO GT HU LB PL", 29: "BR EG PS QA UA", 30: "JO KW MU", 31: "MT SC", 32: "LC"}
GROUPED = r"(?<![0-9A-Za-z])(?:" + "|".join(f"(?:{c.replace(' ', '|')})[0-9]{{2}}(?: [A-Z0-9]{{4}}){{{n // 4 - 1}}}" + (f" [A-Z0-9]{{{n % 4}}}" if n % 4 else "") for n, c in LENGTHS.items()) + ")(?![0-9A-Za-z])"
#: One group of digits, if as many follow as a card has or another group comes before: groups are joined by _join.
DIGITS = r"(?<![0-9A-Za-z-])(?=[0-9](?:[ -]?[0-9]){12})[0-9]{1,19}(?![0-9A-Za-z])|(?<=[0-9][ -])[0-9]{1,19}(?![0-9A-Za-z])"
#: Printed groupings of cards, longer ones first; any other grouping counts if no group of digits is next to it.
CARDS = [r"^[0-9]{4}(?:[ -][0-9]{4}){3}[ -][0-9]{3}(?![0-9])", r"^[0-9]{4}(?:[ -][0-9]{4}){3}(?![0-9])", r"^[0-9]{4}[ -][0-9]{6}[ -][0-9]{5}(?![0-9])", r"^[0-9]{4}[ -][0-9]{6}[ -][0-9]{4}(?![0-9])", r"^[0-9]{4}(?:[ -][0-9]{3}){3}(?![0-9])"]
OTHER = r"^[0-9](?:[ -]?[0-9]){12,18}(?![ -]?[0-9])"
PATTERN = "|".join([EMAIL, IPV4, ISO_DATE, DAY_DATE, PHONE, ABROAD, COMPACT, SSN, IBAN, GROUPED, DIGITS])
#: Country codes of phones without separators.
CODE = r"^[+]([17]|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|[0-9]{3})"
#: Days of any 28 years from 1901 to 2096, which is 21 * 487.
CYCLE = 10227


#: What every match holds; cheap to look for.
HINT = r"@|[0-9][0-9 .()/-]{5}|[A-Z]{2}[0-9]{2}"


def _long(x) -> Column:
    return F.lit(x).cast("long") if isinstance(x, int) else x.cast("long")


def feistel(a: Column, b: Column, size_a, size_b, key: str, tweak: Column, use) -> Column:
    """use(a', b') of a keyed permutation of the pairs (a, b) with a < size_a and b < size_b."""
    size_a, size_b = _long(size_a), _long(size_b)

    def step(acc: Column, i: Column) -> Column:
        secret = F.sha2(F.concat_ws("|", F.lit(key), tweak, i.cast("string"), acc["b"].cast("string")), 256)
        word = F.conv(F.substring(secret, 1, 15), 16, 10).cast("long")
        size = F.when(i % 2 == 0, size_a).otherwise(size_b)
        return F.struct(acc["b"].alias("a"), ((acc["a"] + F.pmod(word, size)) % size).alias("b"))

    out = F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), F.struct(_long(a).alias("a"), _long(b).alias("b")), step)
    return let(out, lambda x: use(x["a"], x["b"]))


def _power(base: int, n: Column) -> Column:
    """base ** n, exactly, for n up to 18."""
    table = F.array(*[F.lit(base**k).cast("long") for k in range(19) if base**k < 1 << 62])
    return F.element_at(table, n + 1)


def permute_digits(s: Column, key: str, kind: str) -> Column:
    """Up to 18 digits to as many digits."""


    def run(s: Column) -> Column:
        n = F.length(s)
        u = F.floor(n / 2).cast("int")
        left, right = F.substring(s, F.lit(1), u), F.substring(s, u + 1, n - u)
        text = lambda a, b: F.concat(F.when(u > 0, F.lpad(a.cast("string"), u, "0")).otherwise(""), F.lpad(b.cast("string"), n - u, "0"))
        return feistel(F.when(u > 0, left).otherwise("0"), right, _power(10, u), _power(10, n - u), key, F.concat(F.lit(kind), n.cast("string")), text)

    return let(s, run)


#: First and last code point of runs of letters that are permuted among themselves; capitals lie as their small letters do.
ALPHABETS = (
    *((48, 57), (65, 90), (97, 122)),  # digits, Latin
    *((0xC0, 0xD6), (0xD8, 0xDF), (0xE0, 0xF6), (0xF8, 0xFF), (0x100, 0x17F), (0x180, 0x24F)),  # Latin with accents
    *((0x391, 0x3A1), (0x3A3, 0x3A9), (0x3B1, 0x3C1), (0x3C3, 0x3C9), (0x410, 0x42F), (0x430, 0x44F), (0x450, 0x45F)),  # Greek, Cyrillic
    *((0x5D0, 0x5EA), (0x621, 0x63A), (0x641, 0x64A), (0x904, 0x939), (0xE01, 0xE30)),  # Hebrew, Arabic, Devanagari, Thai
    *((0x3041, 0x3096), (0x30A1, 0x30FA), (0x3400, 0x4DBF), (0x4E00, 0x9FFF), (0xAC00, 0xD7A3)),  # Kana, Han, Hangul
)
#: Characters that one network permutes together.
CHUNK = 16


def _symbol(c: Column) -> Column:
    """struct(lo, n, v): the character is the v-th of n from code point lo on. Signs and marks are alone in theirs.

    Letters outside ALPHABETS are permuted within their 128 code points.
    """
    code = F.ascii(c)
    none = F.struct(code.alias("lo"), F.lit(1).alias("n"), F.lit(0).alias("v"))

    def place(code: Column) -> Column:
        out = F.when(~c.rlike(r"[\p{L}0-9]"), none)
        for lo, hi in ALPHABETS:
            out = out.when(code.between(lo, hi), F.struct(F.lit(lo).alias("lo"), F.lit(hi - lo + 1).alias("n"), (code - lo).alias("v")))
        return out.otherwise(F.struct((code - code % 128).alias("lo"), F.lit(128).alias("n"), (code % 128).alias("v")))

    return let(code, place)


def _character(code: Column) -> Column:
    return F.when(code < 128, F.chr(code.cast("long"))).otherwise(F.decode(F.unhex(F.lpad(F.hex(code), 8, "0")), "UTF-32"))


def _permute_chunk(s: Column, key: str, kind: str) -> Column:
    """Up to CHUNK characters to as many of the same alphabets at the same places.

    A Feistel network over Z_a x Z_b, where a half is the product of its characters' alphabets and is added to
    character by character. The round function sees values, not capitals, so capitals follow their small letters.
    """

    def halves(x: Column) -> Column:
        n = F.size(x)
        u = F.floor(n / 2).cast("int")
        start = F.struct(F.slice(x, F.lit(1), u).alias("a"), F.slice(x, u + 1, n - u).alias("b"))

        def step(acc: Column, i: Column) -> Column:
            seen = F.array_join(F.transform(acc["b"], lambda y: y["v"].cast("string")), ",")
            secret = F.sha2(F.concat_ws("|", F.lit(key), F.concat(F.lit(kind), n.cast("string")), i.cast("string"), seen), 256)
            moved = lambda word: F.transform(acc["a"], lambda y, k: F.struct(y["lo"].alias("lo"), y["n"].alias("n"), ((y["v"] + F.conv(F.substring(word, k * 8 + 1, F.lit(8)), 16, 10).cast("long")) % y["n"]).cast("int").alias("v")))
            return F.struct(acc["b"].alias("a"), let(secret, moved).alias("b"))

        done = F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), start, step)  # an even number, so the halves are back in place
        return let(done, lambda y: F.array_join(F.transform(F.concat(y["a"], y["b"]), lambda z: _character(z["lo"] + z["v"])), ""))

    return let(F.transform(F.filter(F.split(s, ""), lambda c: c != ""), _symbol), halves)


def permute_text(s: Column, key: str, kind: str) -> Column:
    """Letters and digits permuted among those of their alphabets, other characters in place."""
    return F.array_join(F.transform(F.regexp_extract_all(s, F.lit(f"(?s).{{1,{CHUNK}}}"), F.lit(0)), lambda p: _permute_chunk(p, key, kind)), "")


def _refill(template: Column, digits: Column) -> Column:
    """The digits (a plain column or let variable) put where the template has digits."""
    step = lambda acc, c: F.when(c.rlike("[0-9]"), F.struct(F.concat(acc["s"], F.substring(digits, acc["i"], F.lit(1))).alias("s"), (acc["i"] + 1).alias("i"))).otherwise(F.struct(F.concat(acc["s"], c).alias("s"), acc["i"].alias("i")))
    return F.aggregate(F.split(template, ""), F.struct(F.lit("").alias("s"), F.lit(1).alias("i")), step)["s"]


def _luhn_sum(s: Column) -> Column:
    """Sum of the digits with every second from the right doubled, the last one not."""
    n = F.length(s)
    digit = lambda i: F.substring(s, i, F.lit(1)).cast("int")
    return F.aggregate(F.sequence(F.lit(1), n), F.lit(0), lambda acc, i: acc + F.when((n - i) % 2 == 0, digit(i)).when(digit(i) > 4, digit(i) * 2 - 9).otherwise(digit(i) * 2))


def _mod97(s: Column) -> Column:
    """IBAN remainder: letters count 10 to 35, the first four characters go last."""
    turned = F.concat(F.substring(s, F.lit(5), F.length(s)), F.substring(s, 1, 4))
    return F.aggregate(F.split(turned, ""), F.lit(0), lambda acc, c: F.when(c == "", acc).when(c.rlike("[0-9]"), (acc * 10 + F.ascii(c) - 48) % 97).otherwise((acc * 100 + F.ascii(c) - 55) % 97))


def _date(y: Column, m: Column, d: Column) -> Column:
    day = F.concat_ws("-", y, m, d).try_cast("date")
    return F.when(y.cast("int").between(1901, 2096), day)


def _moved(day: Column, key: str) -> Column:
    """Another day of the same 28 years; the key permutes the days of each such span."""
    n = F.datediff(day, F.lit("1901-01-01").cast("date")).cast("long")
    block, off = F.floor(n / CYCLE).cast("long"), n % CYCLE
    day_of = lambda a, b: F.date_add(F.lit("1901-01-01").cast("date"), (block * CYCLE + a * 487 + b).cast("int"))
    return feistel(F.floor(off / 487), off % 487, 21, 487, key, F.concat(F.lit("date"), block.cast("string")), day_of)


def _sub(m: Column, at: int, n: int) -> Column:
    return F.substring(m, at, n)


def pseudonym(m: Column, key: str) -> Column:
    """struct(kind, text) for a match; kind is null, and the text unchanged, if it fails its check."""
    digits = F.regexp_replace(m, "[^0-9]", "")
    octets = F.split(m, r"\.")
    octet = lambda i: F.element_at(octets, i).cast("int")
    ip_ok = F.forall(octets, lambda o: o.cast("int") < 256)
    dotted = lambda hi, lo: F.concat_ws(".", F.floor(hi / 256).cast("string"), (hi % 256).cast("string"), F.floor(lo / 256).cast("string"), (lo % 256).cast("string"))
    ip = feistel(octet(1) * 256 + octet(2), octet(3) * 256 + octet(4), 65536, 65536, key, F.lit("ipv4"), dotted)
    iso = _date(_sub(m, 1, 4), _sub(m, 6, 2), _sub(m, 9, 2))
    dmy = _date(_sub(m, 7, 4), _sub(m, 4, 2), _sub(m, 1, 2))
    mdy = _date(_sub(m, 7, 4), _sub(m, 1, 2), _sub(m, 4, 2))
    sep = _sub(m, 3, 1)
    day_text = lambda day, x, y: let(day, lambda t: F.concat(F.date_format(t, x), sep, F.date_format(t, y), sep, F.date_format(t, "yyyy")))
    area, group, serial = (_sub(m, *x).cast("long") for x in ((1, 3), (5, 2), (8, 4)))
    ssn_ok = (area > 0) & (area != 666) & (area < 900) & (group > 0) & (serial > 0)
    new_area = lambda a: F.when(a + 1 >= 666, a + 2).otherwise(a + 1)
    ssn_text = lambda a, b: F.format_string("%03d-%02d-%04d", new_area(a), F.floor(b / 9999).cast("long") + 1, b % 9999 + 1)
    ssn = feistel(F.when(area > 666, area - 2).otherwise(area - 1), (group - 1) * 9999 + serial - 1, 898, 99 * 9999, key, F.lit("ssn"), ssn_text)

    def card_text(d: Column) -> Column:
        inner = F.concat(F.substring(d, 1, 1), permute_digits(F.substring(d, F.lit(2), F.length(d) - 2), key, "card"))
        checked = let(F.concat(inner, F.lit("0")), lambda x: F.concat(F.substring(x, F.lit(1), F.length(x) - 1), ((10 - _luhn_sum(x) % 10) % 10).cast("string")))
        return let(checked, lambda x: _refill(m, x))

    def phone_text(d: Column) -> Column:
        n = F.length(d)
        national = permute_digits(F.substring(d, n - 9, F.lit(10)), key, "phone")
        return let(F.concat(F.substring(d, F.lit(1), n - 10), national), lambda x: _refill(m, x))

    def abroad_text(d: Column) -> Column:
        code = F.when(m.rlike("^[+][0-9]+$"), F.regexp_extract(m, CODE, 1)).otherwise(F.regexp_extract(m, "^[+]([0-9]+)", 1))
        return let(F.concat(code, permute_digits(F.substring(d, F.length(code) + 1, F.length(d)), key, "phone")), lambda x: _refill(m, x))

    def iban_text(bban: Column) -> Column:
        return F.concat(_sub(m, 1, 2), F.lpad((98 - _mod97(F.concat(_sub(m, 1, 2), F.lit("00"), bban))).cast("string"), 2, "0"), bban)

    card, phone, abroad = let(digits, card_text), let(digits, phone_text), let(digits, abroad_text)
    iban = let(permute_text(F.substring(m, F.lit(5), F.length(m)), key, "iban"), iban_text)
    plain = F.replace(m, F.lit(" "), F.lit(""))
    grouped = F.regexp_replace(let(permute_text(F.substring(plain, F.lit(5), F.length(plain)), key, "iban"), iban_text), "(.{4})(?=.)", "$1 ")
    at = F.instr(m, "@")
    email = F.concat(permute_text(F.substring(m, F.lit(1), at - 1), key, "email"), F.substring(m, at, F.length(m)))

    made = lambda kind, text: F.struct(F.lit(kind).alias("kind"), text.alias("text"))
    is_ = lambda p: m.rlike("^(?:" + p + ")$")
    return (
        F.when(at > 0, made("email", email))
        .when(is_(r"[0-9]{1,3}(?:\.[0-9]{1,3}){3}"), F.when(ip_ok, made("ipv4", ip)))
        .when(is_("[0-9]{4}-[0-9]{2}-[0-9]{2}"), F.when(iso.isNotNull(), made("date", F.date_format(_moved(iso, key), "yyyy-MM-dd"))))
        .when(is_("[0-9]{2}[/.][0-9]{2}[/.][0-9]{4}"), F.when(sep != _sub(m, 6, 1), F.lit(None)).when(dmy.isNotNull(), made("date", day_text(_moved(dmy, key), "dd", "MM"))).when(mdy.isNotNull(), made("date", day_text(_moved(mdy, key), "MM", "dd"))))
        .when(is_(r"[0-9]{3}-[0-9]{2}-[0-9]{4}"), F.when(ssn_ok, made("ssn", ssn)))
        .when(is_("[A-Z]{2}[0-9]{2}[A-Z0-9]+"), F.when(_mod97(m) == 1, made("iban", iban)))
        .when(is_("[A-Z]{2}[0-9]{2}(?: [A-Z0-9]{1,4})+"), F.when(_mod97(plain) == 1, made("iban", grouped)))
        .when(is_(r"\+[0-9]{8,15}"), made("phone", abroad))
        .when(is_(r"[0-9](?:[ -]?[0-9]){12,18}") & let(digits, lambda d: _luhn_sum(d) % 10 == 0), made("card", card))
        .when(is_(r"(?:\+[0-9]{1,3}[ -]?)?(?:\([0-9]{3}\) ?|[0-9]{3}[ -])[0-9]{3}-[0-9]{4}"), made("phone", phone))
        .when(is_(r"\+[0-9]{1,3}(?:[ .-][0-9]{2,4}){2,5}") & F.length(digits).between(8, 15), made("phone", abroad))
    )


def _join(found: Column, pieces: Column) -> Column:
    """Matches with the text before each, as struct(p, m), groups of digits that make one card joined.

    From each group the card groupings are tried one after another until a check digit is right, so that a number
    before or after a card takes nothing from it.
    """
    digits = lambda i: F.get(found, i).rlike("^[0-9]+$")
    follows = lambda i: F.get(pieces, i).rlike("^[ -]$") & digits(i - 1)

    def groups(i: Column) -> Column:
        near = F.sequence(i + 1, F.least(i + 19, F.size(found) - 1))
        more = F.when(i + 1 < F.size(found), near).otherwise(F.expr("cast(array() as array<int>)"))
        start = F.struct(F.get(found, i).alias("s"), F.lit(True).alias("on"))

        def add(acc: Column, j: Column) -> Column:
            on = acc["on"] & follows(j) & digits(j)
            return F.struct(F.when(on, F.concat(acc["s"], F.get(pieces, j), F.get(found, j))).otherwise(acc["s"]).alias("s"), on.alias("on"))

        def first(text: Column) -> Column:
            tries = F.array(*[F.regexp_extract(text, p, 0) for p in CARDS], F.when((i == 0) | ~F.coalesce(follows(i), F.lit(False)), F.regexp_extract(text, OTHER, 0)).otherwise(""))
            good = F.filter(tries, lambda t: (t != "") & (_luhn_sum(F.regexp_replace(t, "[^0-9]", "")) % 10 == 0))
            return F.coalesce(F.get(good, F.lit(0)), F.get(found, i))

        return F.when(digits(i), let(F.aggregate(more, start, add, lambda acc: acc["s"]), first)).otherwise(F.get(found, i))

    none = F.expr("cast(array() as array<struct<p:string,m:string>>)")

    def step(to: Column, i: Column) -> Column:
        def taken(m: Column) -> Column:
            after = i + F.when(digits(i), F.size(F.split(m, "[ -]"))).otherwise(1)
            return F.struct(after.alias("s"), F.array(F.struct(F.get(pieces, i).alias("p"), m.alias("m"))).alias("o"))

        return F.when(i < to, F.struct(to.alias("s"), none.alias("o"))).otherwise(let(groups(i), taken))

    return fold(F.size(found), F.lit(0), step, "struct<p:string,m:string>")


def find(docs: DataFrame, *, key: str, text_col: str, pieces: str, found: str, new: str) -> DataFrame:
    """docs with three more arrays: the text between matches, the matches, and struct(kind, text) or null for each; null where no pattern occurs."""
    has = F.col(text_col).rlike(HINT) & F.col(text_col).rlike(PATTERN)
    cut = docs.withColumn(found, F.when(has, F.regexp_extract_all(text_col, F.lit(PATTERN), F.lit(0)))).withColumn(pieces, F.when(F.col(found).isNotNull(), F.split(text_col, PATTERN, -1)))
    several = F.exists(found, lambda m: m.rlike("^[0-9]{1,12}$"))
    (whole,) = fresh(cut.columns, "joined")
    joined = cut.withColumn(whole, F.when(several, _join(F.col(found), F.col(pieces))))
    joined = joined.withColumn(pieces, F.when(several, F.concat(F.transform(whole, lambda x: x["p"]), F.array(F.element_at(pieces, -1)))).otherwise(F.col(pieces)))
    joined = joined.withColumn(found, F.when(F.col(whole).isNotNull(), F.transform(whole, lambda x: x["m"])).otherwise(F.col(found))).drop(whole)
    return joined.withColumn(new, F.transform(found, lambda m: pseudonym(m, key)))


def pseudonymise(docs: DataFrame, *, key: str, text_col: str = "text", spans: bool = False) -> DataFrame:
    """The documents with pseudonyms in place of personal data, and array<struct<kind, start, end>> pii_spans if asked for.

    Whoever has the key can undo every pseudonym, so it has no default. Emails keep their domain, the signs of
    their local part and which letters are capitals; phones keep their country code, cards their first digit and
    a right check digit, IBANs their country and right check digits, dates their form and 28-year span,
    addresses stay dotted quads. A mail domain has 127 labels at most, and of more the first ones that make a
    domain count. A candidate that fails its check stays as it is, and so do null and empty texts and all other
    columns, null ids among them; repeated rows stay, each with the same result; an empty table gives an empty
    one. n_chars follows the text if there is such a column; a column pii_spans that the table has is replaced
    if spans are asked for. A match of several formats counts as the first one listed. Day-first dates are
    preferred where both readings are dates. Spans count code points of the input, end exclusive.
    """
    if not key:
        raise ValueError("a key is needed")
    pieces_, found_, new_ = fresh(docs.columns, "pii_pieces", "pii_found", "pii_new")
    found = find(docs, key=key, text_col=text_col, pieces=pieces_, found=found_, new=new_)
    value = F.zip_with(found_, new_, lambda m, x: F.coalesce(x["text"], m))
    text = F.array_join(F.flatten(F.zip_with(pieces_, F.concat(value, F.array(F.lit(""))), lambda p, m: F.array(p, m))), "")
    out = found.withColumn(text_col, F.when(F.col(found_).isNull(), F.col(text_col)).otherwise(text))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col(found_).isNull(), F.col("n_chars")).otherwise(F.char_length(text_col).cast(dict(docs.dtypes)["n_chars"])))
    names = [c for c in docs.columns if not spans or c != "pii_spans"]
    if spans:
        kind = "struct<kind:string,start:long,end:long>"
        none = F.expr(f"cast(array() as array<{kind}>)")

        def step(at: Column, i: Column) -> Column:
            start = at + F.length(F.get(pieces_, i))
            end = start + F.length(F.get(found_, i))
            hit = F.get(new_, i)
            one = F.array(F.struct(hit["kind"].alias("kind"), start.alias("start"), end.alias("end")))
            return F.struct(end.alias("s"), F.when(hit.isNull(), none).otherwise(one).alias("o"))

        spans_at = fold(F.size(found_), F.lit(0).cast("long"), step, kind)
        out = out.withColumn("pii_spans", F.when(F.col(found_).isNull(), none).otherwise(spans_at))
        names.append("pii_spans")
    return out.select(names)
