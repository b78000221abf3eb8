"""Format-preserving pseudonyms for personal data, with SQL functions only.

Numbers and dates are validated and then permuted within their format by a keyed Feistel network: equal values stay
equal everywhere, different ones stay different, and lengths, separators, check digits and calendar validity hold.

* card and account numbers: 9 digits or more, single spaces or hyphens between them, always the whole group; one of at
  most 19 with a valid Luhn digit gets one again (its other digits are permuted), any other of at most 19 is permuted
  and walked until it comes to one without; longer ones have all digits permuted, beyond 34 in pieces of 17 and a last
  one of 17 to 33;
* phone numbers: ten digits behind an optional country code, which stays;
* social security numbers: nine digits as 3-2-4;
* IPv4 addresses: their 32 bits;
* dates (year-month-day; day.month.year or day/month/year): the day's number in the 400-year cycle 1800 to 2199;
* dates with a day or month of one digit: the same network, walked until it comes to another date with such a part;
* dates that are only valid as month/day/year: the same network, walked until it comes to another date of this kind;
* e-mail addresses: the local part and the host below its last two labels, in lower case; letters a-z, digits and
  accented letters are each permuted among their kind, in pieces of 7 and a last one of up to 13, whose network is keyed by
  the piece before as well.  A local part may have any length (64 characters if it touches the match before it); a host
  has at most 127 labels, as mail rules have it (255 characters).

A network's domain is Z_a x Z_b with a * b elements exactly, so no value leaves it, and different ones stay different.
Hexadecimal secrets of 32 to 64 digits get keyed hashes of their length instead (128 bits or more).  The patterns take
time in proportion to a text's length, whatever it holds: what may repeat without bound never gives back what it took.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ROUNDS = 4
#: Steps of a walk among month-first dates or those with a part of one digit; each ends it with odds of a fifth or more.
WALK = 256
#: Steps of a walk among numbers without a Luhn digit; each ends it with odds of nine tenths.
NUMBER_WALK = 40
CYCLE_START, CYCLE_A, CYCLE_B = "1800-01-01", 189, 773  # 189 * 773 days are 400 years

#: A local part begins where none of its characters stands before it, or right behind the last match.
EMAIL = r"(?:(?<![A-Za-z0-9._%+\-À-ɏ])[A-Za-z0-9._%+\-À-ɏ]++|\G[A-Za-z0-9._%+\-À-ɏ]{1,64}+)@(?:[A-Za-z0-9\-]++\.){1,126}[A-Za-z]{2,}"
SECRET = r"(?<![0-9A-Za-z])(?=[0-9A-Fa-f]*[0-9])[0-9A-Fa-f]{32,64}(?![0-9A-Za-z])"
ADDRESS = r"(?<![0-9.])(?:[0-9]{1,3}\.){3}[0-9]{1,3}(?![0-9]|\.[0-9])"
PHONE = r"(?<![0-9])(?:\+[0-9]{1,3}[ \-.]?)?(?:\([0-9]{3}\) ?|[0-9]{3}[\-. ])[0-9]{3}[\-. ][0-9]{4}(?![0-9])"
SOCIAL = r"(?<![0-9\-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9\-])"
DATE = r"(?<![0-9])(?:[0-9]{4}-[0-9]{2}-[0-9]{2}|[0-9]{1,2}([./])[0-9]{1,2}\1[0-9]{4})(?![0-9])"
NUMBER = r"(?<![0-9])[0-9](?:[ \-]?[0-9]){8,}+"
#: Parts of a longer number: 17 digits with 17 more behind them, and the rest.
PART = r"[0-9]{17}(?=[0-9]{17})|.+"
#: Holds in every text that ``ANY`` matches in.
SUSPECT = "@|[0-9][^A-Za-z]{0,3}[0-9]|[0-9A-Fa-f]{32}"
ANY = "|".join((EMAIL, SECRET, ADDRESS, DATE, SOCIAL, PHONE, NUMBER))


def keyed(key: Column, what: str, *parts: Column) -> Column:
    """60 pseudorandom bits of the parts under the key."""
    return F.conv(F.substring(F.sha2(F.concat_ws(":", key, F.lit(what), *[p.cast("string") for p in parts]), 256), 1, 15), 16, 10).cast("long")


def network(left: Column, right: Column, a: Column, b: Column, key: Column, what: str | Column) -> Column:
    """Permutes pairs (l, r) of Z_a x Z_b: each half is shifted in turn by a keyed value of the other."""
    what = F.lit(what) if isinstance(what, str) else what

    def turn(h: Column, i: Column) -> Column:
        moved = F.pmod(h["l"] + F.pmod(keyed(key, what, i, F.lit("r"), h["r"]), a), a).cast("long")
        return F.struct(moved.alias("l"), h["r"].alias("r"))

    def back(h: Column, i: Column) -> Column:
        moved = F.pmod(h["r"] + F.pmod(keyed(key, what, i, F.lit("l"), h["l"]), b), b).cast("long")
        return F.struct(h["l"].alias("l"), moved.alias("r"))

    return F.aggregate(F.sequence(F.lit(1), F.lit(2 * ROUNDS)), F.struct(left.cast("long").alias("l"), right.cast("long").alias("r")), lambda h, i: F.when(i % 2 == 1, turn(h, i)).otherwise(back(h, i)))


def bound(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use`` of a value that is worked out once."""
    return F.transform(F.array(value), use)[0]


def feistel(x: Column, a: int, b: int, key: Column, what: str) -> Column:
    """Permutes 0 .. a*b-1."""
    return bound(network(F.floor(x / F.lit(b)), F.pmod(x, F.lit(b)), F.lit(a), F.lit(b), key, what), lambda h: h["l"] * F.lit(b) + h["r"])


def digits_of(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def permuted_digits(digits: Column, key: Column, what: str) -> Column:
    """A string of 2 to 34 digits, permuted among all such strings of its length."""
    # Halves as longs keep all digits exact.
    high = F.floor(F.length(digits) / 2).cast("int")
    low = F.length(digits) - high
    size = lambda n: F.element_at(F.array(*[F.lit(10**k).cast("long") for k in range(18)]), n + 1)
    moved = network(F.left(digits, high).cast("long"), F.right(digits, low).cast("long"), size(high), size(low), key, what)
    return bound(moved, lambda h: F.concat(F.lpad(h["l"].cast("string"), high, F.lit("0")), F.lpad(h["r"].cast("string"), low, F.lit("0"))))


def check_digit(digits: Column) -> Column:
    """The Luhn digit behind ``digits``."""
    d = lambda c: c.cast("int")
    added = F.transform(F.reverse(F.split(digits, "")), lambda c, i: F.when(i % 2 == 1, d(c)).otherwise(d(c) * 2 - F.when(d(c) > 4, 9).otherwise(0)))
    return F.pmod(-F.aggregate(added, F.lit(0), lambda s, x: s + x), F.lit(10)).cast("string")


def has_check(digits: Column) -> Column:
    return F.right(digits, F.lit(1)) == check_digit(F.left(digits, F.length(digits) - 1))


def unchecked_digits(digits: Column, key: Column) -> Column:
    """A string of digits without a Luhn digit, permuted among all such strings of its length."""
    told = lambda d, done: F.struct(d.alias("d"), done.alias("done"))
    step = lambda s: bound(permuted_digits(s["d"], key, "account"), lambda d: told(d, ~has_check(d)))
    return F.aggregate(F.sequence(F.lit(1), F.lit(NUMBER_WALK)), told(digits, F.lit(False)), lambda s, i: F.when(s["done"], s).otherwise(step(s)), lambda s: s["d"])


#: Kinds of characters in a name, as runs of code points.
KINDS = tuple("".join(map(chr, range(first, first + size))) for first, size in ((0x61, 26), (0x30, 10), (0xC0, 400)))
#: Parts of a name: 7 characters with 7 more behind them, and the rest.
NAME_PART = r".{7}(?=.{7})|.+"


def _permuted_part(part: Column, key: Column, what: Column) -> Column:
    """At most 13 characters; each half is a number whose digits are characters (400^7 < 2^63)."""
    value = lambda half: F.aggregate(half, F.lit(0).cast("long"), lambda v, c: v * c["many"] + c["place"])
    volume = lambda half: F.aggregate(half, F.lit(1).cast("long"), lambda v, c: v * c["many"])
    names = F.array(*map(F.lit, KINDS))

    def spelled(half: Column, number: Column) -> Column:
        new = lambda s, c: F.when(c["kind"] < 0, c["c"]).otherwise(F.substr(names[c["kind"]], (s["rest"] % c["many"]).cast("int") + 1, F.lit(1)))
        put = lambda s, c: F.struct(F.call_function("div", s["rest"], c["many"]).alias("rest"), F.concat(new(s, c), s["out"]).alias("out"))
        return F.aggregate(F.reverse(half), F.struct(number.alias("rest"), F.lit("").alias("out")), put, lambda s: s["out"])

    def permuted(h: Column) -> Column:
        moved = network(value(h["l"]), value(h["r"]), volume(h["l"]), volume(h["r"]), key, what)
        return bound(moved, lambda m: F.concat(spelled(h["l"], m["l"]), spelled(h["r"], m["r"])))

    marked = bound(part, lambda part: F.transform(F.split(part, ""), _marked))
    return bound(marked, lambda m: bound(F.struct(F.slice(m, F.lit(1), F.floor(F.size(m) / 2).cast("int")).alias("l"), F.slice(m, F.floor(F.size(m) / 2).cast("int") + 1, F.size(m)).alias("r")), permuted))


def _marked(c: Column) -> Column:
    """A character with its kind (-1: none), how many there are of it, and its place among them."""
    told = lambda kind, many, place: F.struct(F.lit(kind).alias("kind"), F.lit(many).cast("long").alias("many"), place.cast("long").alias("place"), c.alias("c"))
    out = F
    for i, k in enumerate(KINDS):
        out = out.when(F.ascii(c).between(ord(k[0]), ord(k[-1])), told(i, len(k), F.ascii(c) - ord(k[0])))
    return out.otherwise(told(-1, 1, F.lit(0)))


def permuted_names(names: list[Column], key: Column) -> Column:
    """Names in lower case with each character permuted among its kind; parts are keyed by the one before as well."""
    before = lambda parts, i: F.when(i > 0, parts[F.greatest(i - 1, F.lit(0))]).otherwise("")
    parts = lambda name: F.regexp_extract_all(F.lower(name), F.lit(NAME_PART), F.lit(0))
    return F.transform(F.array(*names), lambda name, at: F.array_join(bound(parts(name), lambda p: F.transform(p, lambda x, i: _permuted_part(x, key, F.concat_ws(":", F.when(at == 0, "local").otherwise("host"), before(p, i))))), ""))


def poured(form: Column, digits: Column) -> Column:
    """``form`` with its digits replaced by others, in order."""
    runs = F.regexp_extract_all(form, F.lit("[0-9]+|[^0-9]+"), F.lit(0))
    put = lambda s, run: F.when(run.rlike("^[0-9]"), F.struct(F.concat(s["out"], F.array(F.substr(digits, s["at"], F.length(run)))).alias("out"), (s["at"] + F.length(run)).alias("at"))).otherwise(F.struct(F.concat(s["out"], F.array(run)).alias("out"), s["at"].alias("at")))
    whole = F.aggregate(runs, F.struct(F.expr("cast(array() as array<string>)").alias("out"), F.lit(1).alias("at")), put, lambda s: F.array_join(s["out"], ""))
    return F.when(form.rlike("^[0-9]*$"), digits).otherwise(whole)


def hashed_like(value: Column, key: Column, what: str) -> Column:
    """Lower-case hexadecimal digits of the value's length (64 at most)."""
    return F.substr(F.sha2(F.concat_ws(":", key, F.lit(what), F.lower(value)), 256), F.lit(1), F.length(value))


def _cycle_day(value: Column) -> tuple[Column, Column]:
    """Whether a year-month-day is a date of the cycle, and its number there (else 0)."""
    form = "yyyy-MM-dd"
    day = F.datediff(F.try_to_date(value, form) if hasattr(F, "try_to_date") else F.to_date(F.try_to_timestamp(value, F.lit(form))), F.lit(CYCLE_START).cast("date")).cast("long")
    valid = day.between(0, CYCLE_A * CYCLE_B - 1)
    return valid, F.when(valid, day).otherwise(F.lit(0).cast("long"))


def _told(day: Column) -> Column:
    return F.date_add(F.lit(CYCLE_START).cast("date"), day.cast("int"))


def _iso_date(value: Column, key: Column) -> Column:
    """Null if the value is no date of the cycle."""
    valid, start = _cycle_day(value)
    return F.when(valid, F.date_format(_told(feistel(start, CYCLE_A, CYCLE_B, key, "date")), "yyyy-MM-dd"))


def _local_date(value: Column, key: Column, month_first: bool = False) -> Column:
    """Null if the value, with day and month before the year, is no date of the cycle.

    Days and months of one digit stay such.  month_first: days after the 12th stay such days, so a month-first date
    that can't be read day first becomes one that can't either, and never equals a pseudonym of the other kind.
    """
    sep = F.when(F.contains(value, F.lit(".")), F.lit(".")).otherwise(F.lit("/"))
    part = F.split(value, "[./]")
    day, month, year = (part[1], part[0], part[2]) if month_first else (part[0], part[1], part[2])
    valid, start = _cycle_day(F.concat_ws("-", year, F.lpad(month, 2, "0"), F.lpad(day, 2, "0")))
    short_day, short_month = F.length(day) == 1, F.length(month) == 1
    step = lambda d: feistel(d, CYCLE_A, CYCLE_B, key, "date")
    fits = lambda d: (~short_day | (F.dayofmonth(_told(d)) < 10)) & (~short_month | (F.month(_told(d)) < 10)) & ((F.dayofmonth(_told(d)) > 12) if month_first else F.lit(True))
    most = F.lit(WALK) if month_first else F.when(short_day | short_month, F.lit(WALK)).otherwise(F.lit(1))
    moved = _told(F.aggregate(F.sequence(F.lit(1), most), start, lambda d, i: F.when((i > 1) & fits(d), d).otherwise(step(d))))
    written = [F.lpad(F.dayofmonth(moved).cast("string"), F.length(day), F.lit("0")), F.lpad(F.month(moved).cast("string"), F.length(month), F.lit("0"))]
    first, second = reversed(written) if month_first else written
    return F.when(valid, F.concat(first, sep, second, sep, F.date_format(moved, "yyyy")))


def kind_of(value: Column) -> Column:
    whole = lambda p: value.rlike(f"^(?:{p})$")
    return F.when(F.contains(value, F.lit("@")), "email").when(whole(SECRET), "secret").when(whole(ADDRESS), "address").when(whole(DATE), "date").when(whole(SOCIAL), "social").when(whole(PHONE), "phone").otherwise("number")


def pseudonym(value: Column, key: Column) -> Column:
    """What stands for a match of ``ANY``; the value itself if it doesn't validate."""
    digits = digits_of(value)
    local, host = F.substring_index(value, "@", 1), F.substring_index(value, "@", -1)
    domain = F.substring_index(host, ".", -2)
    below = F.left(host, F.greatest(F.length(host) - F.length(domain) - 1, F.lit(0)))
    email = bound(permuted_names([local, below], key), lambda n: F.concat(n[0], F.lit("@"), n[1], F.when(below == "", "").otherwise("."), domain))
    secret = F.when(value == F.upper(value), F.upper(hashed_like(value, key, "secret"))).otherwise(hashed_like(value, key, "secret"))
    octets = F.transform(F.split(value, r"\."), lambda o: o.cast("long"))
    number = octets[0] * 16777216 + octets[1] * 65536 + octets[2] * 256 + octets[3]
    moved = F.transform(F.array(feistel(number, 65536, 65536, key, "address")), lambda m: F.concat_ws(".", F.shiftright(m, 24), F.shiftright(m, 16) % 256, F.shiftright(m, 8) % 256, m % 256))[0]
    address = F.when(F.array_max(octets) <= 255, moved).otherwise(value)
    local_date = _local_date(value, key)
    date = F.coalesce(F.when(F.contains(value, F.lit("-")), _iso_date(value, key)).when(F.contains(value, F.lit(".")), local_date).otherwise(F.coalesce(local_date, _local_date(value, key, month_first=True))), value)
    social = permuted_digits(digits, key, "social")
    phone = F.concat(F.left(digits, F.length(digits) - 10), permuted_digits(F.right(digits, F.lit(10)), key, "phone"))
    with_check = bound(permuted_digits(F.left(digits, F.length(digits) - 1), key, "card"), lambda d: F.concat(d, check_digit(d)))
    longer = F.array_join(F.transform(F.regexp_extract_all(digits, F.lit(PART), F.lit(0)), lambda p: permuted_digits(p, key, "part")), "")
    account = F.when(F.length(digits) > 34, longer).when(F.length(digits) > 19, permuted_digits(digits, key, "account")).when(has_check(digits), with_check).otherwise(unchecked_digits(digits, key))
    kind = kind_of(value)
    other = F.when(kind == "social", social).when(kind == "phone", phone).otherwise(account)
    return F.when(kind == "email", email).when(kind == "secret", secret).when(kind == "address", address).when(kind == "date", date).otherwise(poured(value, other))


def pseudonymised(docs: DataFrame, key: str = "change-this-key") -> DataFrame:
    """``docs`` with every match in ``text`` replaced; all columns and rows stay, and n_private counts the replacements.

    Null texts stay null, with 0.  A column n_private in ``docs`` is replaced.
    """
    secret = F.lit(key)
    suspect = F.col("text").cast("string").rlike(SUSPECT)
    found = F.when(suspect, F.regexp_extract_all(F.col("text").cast("string"), F.lit(ANY), F.lit(0)))
    pieces = F.split(F.col("text").cast("string"), ANY, -1)
    names = [c for c in docs.columns if c not in ("n_private", "__found", "__new")]
    marked = docs.withColumn("__found", F.coalesce(found, F.expr("cast(array() as array<string>)")))
    marked = marked.withColumn("__new", F.when(F.size("__found") > 0, F.transform("__found", lambda m: pseudonym(m, secret))))
    rebuilt = F.concat(pieces[0], F.array_join(F.zip_with(F.slice(pieces, F.lit(2), F.size(pieces)), F.col("__new"), lambda p, m: F.concat(m, p)), ""))
    changed = F.when(F.size("__found") > 0, rebuilt).otherwise(F.col("text").cast("string"))
    moved = F.when(F.size("__found") > 0, F.size(F.filter(F.zip_with("__found", "__new", lambda a, b: a != b), lambda x: x))).otherwise(0).cast("long")
    return marked.select(*[changed.alias("text") if c == "text" else F.col(c) for c in names], moved.alias("n_private"))
