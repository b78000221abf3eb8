"""Plain Python versions of the contracts, for comparison on small tables."""

import hashlib
import math
import re
import zlib
from collections import Counter

UP = bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))


def spaced(text):
    return (text or "").encode().translate(UP).split()


def plain(text):
    return [w.decode() for w in re.findall(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (text or "").encode().translate(UP))]


BASE = {"mit": "under the mit license", "apache-2": "apache license version 2", "cc-by-nc": "cc by nc"}


def licence(text):
    w = plain(text)
    at = [(i, k) for k, p in BASE.items() for p in [p.split()] for i in range(len(w) - len(p) + 1) if w[i : i + len(p)] == p]
    return len(w), len(at), min((i for i, _ in at), default=None), max((i for i, _ in at), default=None), ",".join(sorted({k for _, k in at}))


def shingles(text):
    w = spaced(text)
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def near(rows):
    """rows: (doc_id, text) -> {doc_id: (n, component)}"""
    sets = {d: shingles(t) for d, t in rows}
    root = {d: d for d in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(d for d in sets if sets[d])
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            if 100 * len(sets[a] & sets[b]) >= 85 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {d: (len(s), find(d)) for d, s in sets.items()}


def unigram(rows):
    train = Counter()
    for d, t in rows:
        if zlib.crc32(str(d).encode()) % 7 != 2:
            train.update([*spaced(t), None])
    n, v = sum(train.values()), len(train)
    out = {}
    for d, t in rows:
        tokens = [*spaced(t), None]
        out[d] = (zlib.crc32(str(d).encode()) % 7 == 2, len(tokens), sum(train[x] > 0 for x in tokens), n, sum(math.log10((train[x] + 1) / (n + v + 1)) for x in tokens))
    return out


def lines(text):
    text = text or ""
    w = re.findall(r"[^\x20\x09-\x0D]+", text)
    seen, dup = set(), 0
    for x in text.split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", x):
            dup += x in seen
            seen.add(x)
    runs = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    hit = {i + k for i in range(len(w) - 4) if runs[tuple(w[i : i + 5])] > 1 for k in range(5)}
    failed = len(w) < 10 or 100 * len(hit) > 20 * len(w)
    return len(w), sum(map(len, w)), sum(text.count(c) for c in "#*$%&|<>"), dup, len(hit), failed


def passages(docs, items):
    """{doc_id: (n_words, n_hit, n_items, sha, contaminated)}"""
    found = {}
    for i, t in items:
        w = plain(t)
        for k in range(max(1, len(w) - 12) if w else 0):
            found.setdefault(tuple(w[k : k + 13]), set()).add(str(i))
    sizes = {len(k) for k in found}
    out = {}
    for d, t in docs:
        w = plain(t)
        hit, names = set(), set()
        for n in sizes:
            for i in range(len(w) - n + 1):
                if (x := tuple(w[i : i + n])) in found:
                    hit.update(range(i, i + n))
                    names |= found[x]
        out[d] = (len(w), len(hit), len(names), hashlib.sha256(",".join(sorted(names)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w))
    return out


def shift_network(left, right, a, b, key, what):
    def keyed(*parts):
        return int(hashlib.sha256(":".join([key, what, *map(str, parts)]).encode()).hexdigest()[:15], 16)

    for i in range(1, 9):
        if i % 2:
            left = (left + keyed(i, "r", right) % a) % a
        else:
            right = (right + keyed(i, "l", left) % b) % b
    return left, right


def moved_digits(d, key, what):
    h = len(d) // 2
    left, right = shift_network(int(d[:h]), int(d[h:]), 10**h, 10 ** (len(d) - h), key, what)
    return f"{left:0{h}d}{right:0{len(d) - h}d}"


def luhn(s):
    d = [int(c) for c in s if c.isdigit()][::-1]
    return sum(x if i % 2 == 0 else sum(divmod(2 * x, 10)) for i, x in enumerate(d)) % 10 == 0


def moved_name(name, key, what):
    kinds = [(97, 26), (48, 10), (192, 400)]
    kind = lambda c: next(((f, n) for f, n in kinds if f <= ord(c) < f + n), None)
    out, before = "", ""
    for part in re.findall(".{7}(?=.{7})|.+", name.lower()):
        halves = part[: len(part) // 2], part[len(part) // 2 :]
        size = [math.prod(kind(c)[1] for c in h if kind(c)) for h in halves]
        value = [0, 0]
        for k, h in enumerate(halves):
            for c in h:
                if kind(c):
                    value[k] = value[k] * kind(c)[1] + ord(c) - kind(c)[0]
        for h, v in zip(halves, shift_network(*value, *size, key, f"{what}:{before}"), strict=True):
            new = []
            for c in reversed(h):
                if kind(c):
                    v, rest = divmod(v, kind(c)[1])
                    c = chr(kind(c)[0] + rest)
                new.append(c)
            out += "".join(reversed(new))
        before = part
    return out


def poured(form, digits):
    left = iter(digits)
    return re.sub("[0-9]", lambda _: next(left), form)


def moved_date(y, m, d, key, fits=lambda day: True):
    from datetime import date, timedelta

    start = date(1800, 1, 1)
    x = (date(y, m, d) - start).days
    if not 0 <= x < 189 * 773:
        raise ValueError
    while True:
        left, right = shift_network(x // 773, x % 773, 189, 773, key, "date")
        x = left * 773 + right
        if fits(start + timedelta(x)):
            return start + timedelta(x)


def pseudonym(v, key):
    """By the formats of the module's docstring."""
    digits = re.sub("[^0-9]", "", v)
    hashed = lambda x, what: hashlib.sha256(f"{key}:{what}:{x.lower()}".encode()).hexdigest()[: len(x)]
    if "@" in v:
        local, host = v.split("@")
        labels = host.split(".")
        below = ".".join(labels[:-2])
        return moved_name(local, key, "local") + "@" + (moved_name(below, key, "host") + "." if below else "") + ".".join(labels[-2:])
    if re.fullmatch("(?=.*[0-9])[0-9A-Fa-f]{32,64}", v):
        return hashed(v, "secret").upper() if v == v.upper() else hashed(v, "secret")
    if re.fullmatch(r"(?:[0-9]{1,3}\.){3}[0-9]{1,3}", v):
        o = list(map(int, v.split(".")))
        if max(o) > 255:
            return v
        left, right = shift_network(o[0] * 256 + o[1], o[2] * 256 + o[3], 65536, 65536, key, "address")
        return f"{left >> 8}.{left & 255}.{right >> 8}.{right & 255}"
    try:
        if re.fullmatch("[0-9]{4}-[0-9]{2}-[0-9]{2}", v):
            return moved_date(*map(int, v.split("-")), key).isoformat()
    except ValueError:
        return v
    if m := re.fullmatch(r"([0-9]{1,2})([./])([0-9]{1,2})\2([0-9]{4})", v):
        a, sep, b, y = m.groups()
        for d, mo, month_first in ((a, b, False), (b, a, True))[: 1 if sep == "." else 2]:
            fits = lambda x: (len(d) > 1 or x.day < 10) and (len(mo) > 1 or x.month < 10) and (not month_first or x.day > 12)  # noqa: B023, E731
            try:
                x = moved_date(int(y), int(mo), int(d), key, fits)
            except ValueError:
                continue
            day, month = f"{x.day:0{len(d)}d}", f"{x.month:0{len(mo)}d}"
            return sep.join([month, day, f"{x.year:04d}"] if month_first else [day, month, f"{x.year:04d}"])
        return v
    if re.fullmatch("[0-9]{3}-[0-9]{2}-[0-9]{4}", v):
        return poured(v, moved_digits(digits, key, "social"))
    if re.fullmatch(r"(?:\+[0-9]{1,3}[ \-.]?)?(?:\([0-9]{3}\) ?|[0-9]{3}[\-. ])[0-9]{3}[\-. ][0-9]{4}", v):
        return poured(v, digits[:-10] + moved_digits(digits[-10:], key, "phone"))
    if len(digits) > 34:
        parts = re.findall("(?:[0-9]){17}(?=(?:[0-9]){17})|.+", digits)
        return poured(v, "".join(moved_digits(p, key, "part") for p in parts))
    if len(digits) < 20 and luhn(digits):
        d = moved_digits(digits[:-1], key, "card")
        return poured(v, d + next(c for c in "0123456789" if luhn(d + c)))
    d = moved_digits(digits, key, "account")
    while len(d) < 20 and luhn(d):
        d = moved_digits(d, key, "account")
    return poured(v, d)
