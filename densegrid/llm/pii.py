"""Format-preserving pseudonyms for personal data, by keyed Feistel permutations.

Values are found by their shape and validated (check digits, calendar, address
ranges). Each is permuted, under a secret key, within the set of values of the
same format, so that the pseudonym looks alike and equal values stay linked
across documents, with nothing stored and nothing shuffled.
"""

from __future__ import annotations

import datetime
import hashlib
import math
import re
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame

from densegrid.llm._text import column, of_columns

ROUNDS = 10
#: Longer words and hex runs are permuted in blocks of so many characters.
BLOCK = 64


def permute(value: int, size: int, key: bytes, tweak: str) -> int:
    """A keyed bijection on 0..size-1: an alternating Feistel network, walked until inside.

    The domain is the smallest a*b >= size with a and b near its root; the walk
    stays in the cycle of ``value``, so it ends, after two steps on average at most.
    """
    if size < 2:
        return value
    a = math.isqrt(size - 1) + 1  # not by floats, whose error is astronomical for long words
    b = -(-size // a)
    wide = 16 if a < 1 << 64 else 64
    while True:
        left, right = divmod(value, b)
        for r in range(ROUNDS):
            side, other = (a, right) if r % 2 == 0 else (b, left)
            f = int.from_bytes(hashlib.blake2b(f"{tweak}|{size}|{r}|{other}".encode(), key=key[:64], digest_size=wide).digest(), "big")
            if r % 2 == 0:
                left = (left + f) % side
            else:
                right = (right + f) % side
        value = left * b + right
        if value < size:
            return value


def luhn_digit(payload: str) -> str:
    total = 0
    for i, c in enumerate(reversed(payload)):
        n = int(c) * (2 if i % 2 == 0 else 1)
        total += n - 9 if n > 9 else n
    return str(-total % 10)


def is_luhn(digits: str) -> bool:
    return luhn_digit(digits[:-1]) == digits[-1]


def _refill(text: str, digits: str) -> str:
    """``text`` with its digits replaced in order."""
    it = iter(digits)
    return "".join(next(it) if c.isdigit() else c for c in text)


def _digits(text: str) -> str:
    return "".join(c for c in text if c.isdigit())


def _number(text: str, key: bytes, kind: str, keep: int = 0) -> str:
    """Digits after the first ``keep`` permuted among all strings of as many digits."""
    d = _digits(text)
    n = len(d) - keep
    return _refill(text, d[:keep] + str(permute(int(d[keep:]), 10**n, key, f"{kind}{n}")).zfill(n)) if n > 0 else text


def _card(text: str, key: bytes) -> str:
    d = _digits(text)
    body = str(permute(int(d[:-1]), 10 ** (len(d) - 1), key, f"card{len(d)}")).zfill(len(d) - 1)
    return _refill(text, body + luhn_digit(body))


def _ip(text: str, key: bytes) -> str:
    """Unicast, reserved and zero first octets each permute among themselves."""
    n = int.from_bytes(bytes(int(x) for x in text.split(".")), "big")
    low, high = next(r for r in ((0, 1), (1, 224), (224, 256)) if n < r[1] << 24)
    base, size = low << 24, (high - low) << 24
    return ".".join(str(x) for x in (base + permute(n - base, size, key, f"ip{low}")).to_bytes(4, "big"))


_FIRST, _LAST = datetime.date(1900, 1, 1).toordinal(), datetime.date(2099, 12, 31).toordinal()


def _day(y: int, m: int, d: int) -> int | None:
    try:
        n = datetime.date(y, m, d).toordinal()
    except ValueError:
        return None
    return n if _FIRST <= n <= _LAST else None


def _width(field: str, padded: bool) -> tuple[int, int]:
    """The values that a day or month field can take without changing its look: fields of two digits are filled with zeros if all are."""
    if len(field) == 1:
        return 1, 9
    return (1, 31) if padded else (10, 31) if field[0] != "0" else (1, 9)


@lru_cache(maxsize=64)
def _days(month: tuple[int, int], day: tuple[int, int], late: bool) -> tuple[list[int], dict[int, int]]:
    """The dates of a look, and their places; ``late``: only those whose day can be no month."""
    low = max(day[0], 13) if late else day[0]
    found = [n for n in range(_FIRST, _LAST + 1) if month[0] <= (t := datetime.date.fromordinal(n)).month <= month[1] and low <= t.day <= day[1]]
    return found, {n: i for i, n in enumerate(found)}


def _date(m: re.Match, key: bytes) -> str | None:
    """Year first, or day and month in the order that makes a valid date (day first if both do).

    The date is permuted among those that look alike: in the same order, with as
    many digits in each field. So equal looks go to equal looks, one to one.
    """
    sep, parts = m[2], [m[1], m[3], m[4]]
    for order in ((0, 1, 2),) if len(m[1]) == 4 else ((2, 1, 0), (2, 0, 1)):
        n = _day(*(int(parts[i]) for i in order))
        if n is not None:
            month, day = parts[order[1]], parts[order[2]]
            padded = len(month) == len(day) == 2
            look = (_width(month, padded), _width(day, padded), order == (2, 0, 1))
            found, place = _days(*look)
            t = datetime.date.fromordinal(found[permute(place[n], len(found), key, f"date{look}")])
            new = {order[0]: f"{t.year:04}", order[1]: f"{t.month:0{len(month)}}", order[2]: f"{t.day:0{len(day)}}"}
            return sep.join(new[i] for i in range(3))
    return None


_VOWELS, _OTHERS = "aeiou", "bcdfghjklmnpqrstvwxyz"


def _chained(text: str, one) -> str:
    """``one`` (a block, a tweak) block by block; a block's tweak depends on all before it, so the whole stays one to one."""
    out, tweak = [], ""
    for at in range(0, len(text), BLOCK):
        part = text[at : at + BLOCK]
        out.append(one(part, tweak))
        tweak = hashlib.blake2b((tweak + part).encode(), digest_size=16).hexdigest()
    return "".join(out)


def _word(text: str, key: bytes, kind: str) -> str:
    """Letters and digits permuted in their classes, as one mixed-radix number a block; the rest stays."""
    return _chained(text, lambda part, tweak: _word_block(part, key, kind + tweak))


def _word_block(text: str, key: bytes, kind: str) -> str:
    sets = [_VOWELS if c.lower() in _VOWELS else _OTHERS if c.lower() in _OTHERS else "0123456789" if c.isdigit() and c.isascii() else "" for c in text]
    n, size = 0, 1
    for c, s in zip(text, sets, strict=True):
        if s:
            n, size = n * len(s) + s.index(c.lower()), size * len(s)
    n, out = permute(n, size, key, kind + "".join(str(len(s)) for s in sets)), []
    for c, s in zip(reversed(text), reversed(sets), strict=True):
        if s:
            n, k = divmod(n, len(s))
            out.append(s[k].upper() if c.isupper() else s[k])
        else:
            out.append(c)
    return "".join(reversed(out))


def _hex(text: str, key: bytes) -> str:
    case = "X" if text.upper() == text else "x"
    return _chained(text, lambda part, tweak: format(permute(int(part, 16), 16 ** len(part), key, f"hex{len(part)}{tweak}"), f"0{len(part)}{case}"))


def _email(local: str, domain: str, key: bytes) -> str:
    """The local part and every label but the last two are permuted; non-ASCII letters become ASCII ones."""
    plain = "".join(c if c.isascii() else _OTHERS[ord(c) % len(_OTHERS)] for c in local)
    labels = domain.split(".")
    return _word(plain, key, "mail") + "@" + ".".join([_word(x, key, "host") for x in labels[:-2]] + labels[-2:])


def _iban_ok(s: str) -> bool:
    s = s.replace(" ", "").upper()
    return 15 <= len(s) <= 34 and int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


def _iban(text: str, key: bytes) -> str:
    s = text.replace(" ", "")
    body = _word(s[4:], key, "iban" + s[:2])
    check = 98 - int("".join(str(int(c, 36)) for c in body + s[:2] + "00")) % 97
    new, it = f"{s[:2]}{check:02}{body}", 0
    out = []
    for c in text:
        out.append(c if c == " " else new[it])
        it += c != " "
    return "".join(out)


@lru_cache(maxsize=1 << 16)
def _cached(kind: str, text: str, key: bytes) -> str:
    return {"card": _card, "ip": _ip, "iban": _iban, "hex": _hex}[kind](text, key) if kind in ("card", "ip", "iban", "hex") else _number(text, key, kind)


# Shapes of the personal data that this operator knows, in the order in which they are tried.
_IP = re.compile(r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?![\d]|\.\d)", re.A)
_DATE = re.compile(r"(?<![\d/.-])(\d{4}|\d{1,2})([-/.])(\d{1,2})\2(\d{4}|\d{1,2})(?!\d|[/-]\d)", re.A)
_PHONE = re.compile(r"(?:\+\d{1,3}[ .-]?)?(?:\(\d{2,4}\)[ .-]?|\d{2,4}[ .-])\d{2,4}(?:[ .-]\d{2,4}){1,3}(?![\d])|\+\d{8,15}(?!\d)", re.A)
_CARD = re.compile(r"\d(?:[ -]?\d){12,18}(?![\d])", re.A)
_SSN = re.compile(r"(?!000|666|9\d\d)\d{3}-(?!00)\d{2}-(?!0000)\d{4}(?!\d)", re.A)
_IBAN = re.compile(r"[A-Za-z]{2}\d{2}(?: ?[A-Za-z0-9]{4}){2,7}(?: ?[A-Za-z0-9]{1,4})?(?![A-Za-z0-9])", re.A)
_HEXRUN = re.compile(r"[0-9a-f]{24,}(?![0-9A-Za-z])|[0-9A-F]{24,}(?![0-9A-Za-z])", re.A)
_KEYRUN = re.compile(r"[A-Za-z0-9_\-]{20,}(?![A-Za-z0-9])", re.A)
_LOCAL = re.compile(r"[^\s@<>\"'(),;:\[\]\\|=]{1,64}\Z")
_DOMAIN = re.compile(r"(?:[A-Za-z0-9](?:[A-Za-z0-9-]{0,62})\.)+[A-Za-z]{2,24}", re.A)
_DIGIT = re.compile(r"[0-9]")
_RUN = re.compile(r"[A-Za-z0-9_\-]*", re.A)
_IN_RUN = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789_-")


def _emails(text: str) -> list[tuple[int, int, str, str]]:
    out, at = [], text.find("@")
    while at >= 0:
        local, domain = _LOCAL.search(text, max(0, at - 64), at), _DOMAIN.match(text, at + 1)
        if local and domain:
            part = local[0].lstrip(".!#$%&*+/?^`{}~-")
            if part:
                out.append((at - len(part), domain.end(), part, domain[0]))
        at = text.find("@", at + 1)
    return out


def _is_phone(text: str, before: str) -> bool:
    """Digit groups alone are any numbers: a phone number has a plus sign, an area code in brackets, a leading zero, or hyphens or dots in threes and fours.

    ``before`` is the two characters to its left: groups of three that go on after
    a digit and their own separator are the thousands of a longer number.
    """
    if text[0] in "+(" or "(" in text:
        return True
    if text[0] == "0":
        goes_on = len(before) == 2 and before[0] in "0123456789"
        return not (goes_on and re.fullmatch(rf"\d{{3}}(?:{re.escape(before[1])}\d{{3}})+", text))
    groups = re.split(r"[-.]", text)
    return " " not in text and len(set(re.findall(r"[-.]", text))) == 1 and len(groups) == 3 and [len(g) for g in groups] in ([3, 3, 4], [3, 4, 4])


def _secrets(text: str, run: int) -> list[tuple[int, int, str]]:
    """Account numbers and secrets that begin at ``run``, in the order of preference."""
    found = []
    for shape, kind in ((_IBAN, "iban"), (_HEXRUN, "hex")):
        m = shape.match(text, run)
        if m and (kind != "iban" or _iban_ok(m[0])) and (run == 0 or not text[run - 1].isalnum()):
            found.append((run, m.end(), kind))
    m = _KEYRUN.match(text, run)
    if m and sum(c.isdigit() for c in m[0]) >= 4 and any(c.isalpha() for c in m[0]):
        found.append((run, m.end(), "key"))
    return found


def _at_digit(text: str, at: int, low: int, seen: list) -> tuple[int, int, str] | None:
    """The value whose first digit stands at ``at``: start, end, kind. ``low``: what is free to its left.

    ``seen`` keeps the last run of word characters, its end and its secrets by start,
    so that a long run is gone over once, however many digits it has.
    """
    if not seen or not seen[0] <= at < seen[1]:
        start = at
        while start and text[start - 1] in _IN_RUN:
            start -= 1
        seen[:] = start, _RUN.match(text, at).end(), {}
    run = max(low, seen[0])
    alone = run == at or not text[at - 1].isalnum()
    if alone:
        for kind, shape in (("ip", _IP), ("date", _DATE), ("ssn", _SSN), ("card", _CARD), ("phone", _PHONE)):
            m = shape.match(text, at)
            if kind == "phone":  # it may begin with a plus sign or a bracket
                for before in (2, 1):
                    if at - before >= low and not text[at - before : at].strip("+("):
                        m = shape.match(text, at - before) or m
                        if m and m.start() < at:
                            break
            if not m:
                continue
            d = _digits(m[0])
            if kind == "card" and (not is_luhn(d) or (at > low and text[at - 1] == "+")):  # a plus sign begins a phone number, whatever its last digit
                continue
            if kind == "phone" and not (8 <= len(d) <= 15 and _is_phone(m[0], text[max(0, m.start() - 2) : m.start()])):
                continue
            if kind == "date" and (len(m[1]) == 4) == (len(m[4]) == 4):
                continue
            return m.start(), m.end(), kind
    if run not in seen[2]:
        seen[2][run] = _secrets(text, run)
    return next((value for value in seen[2][run] if value[1] > at), None)


def pseudonymise(text: str | None, key: bytes) -> tuple[str | None, dict[str, int]]:
    """The text with every value found replaced, and how many of each kind.

    Kinds: email, ip, date, ssn, card (valid check digit), phone, iban (valid
    check), hex and key (secrets). Numbers that fail their check are no card and
    stay. Each kind is permuted one to one among the values of its look, so different
    values stay different (and one in as many as there are may map to itself).
    Mapping a value again gives another pseudonym: apply once.
    """
    if not text or not (_DIGIT.search(text) or "@" in text):
        return text, {}
    found = [(s, e, "email", (a, b)) for s, e, a, b in _emails(text)]
    out, done, counts, spans, seen = [], 0, {}, iter(found), []
    mail = next(spans, None)
    at = 0
    while True:
        m = _DIGIT.search(text, at)
        place = m.start() if m else len(text)
        if mail and mail[0] <= place:
            s, e, kind, value = mail
            mail = next(spans, None)
            if s < done:
                continue
            new = _email(*value, key)
        elif not m:
            break
        else:
            hit = _at_digit(text, place, done, seen)
            if hit is None or hit[0] < done:
                end = place + 1
                while end < len(text) and text[end] in "0123456789":
                    end += 1
                at = end
                continue
            s, e, kind = hit
            if mail and e > mail[0]:  # an address begins with digits
                s, e, kind, value = mail
                mail = next(spans, None)
                new = _email(*value, key)
            elif kind == "date":
                new = _date(_DATE.match(text, s), key)
                if new is None:
                    at = e
                    continue
            elif kind == "key":
                new = _word(text[s:e], key, "key")
            else:
                new = (_cached if e - s <= BLOCK else _cached.__wrapped__)(kind, text[s:e], key)
        out += [text[done:s], new]
        counts[kind] = counts.get(kind, 0) + 1
        done = at = e
    return "".join([*out, text[done:]]), counts


def mask_documents(docs: DataFrame, key: bytes) -> DataFrame:
    """``key``: the caller's secret, at least eight bytes; equal keys link pseudonyms across runs. (doc_id, text, n_found, kinds) for every row: pseudonyms in place, kinds as a sorted list.

    Null texts stay null, empty ones empty. Null and repeated ids are carried
    along; other columns are ignored. No rows give no rows.
    """
    if len(key) < 8:
        raise ValueError("a key of at least eight bytes is needed")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [pseudonymise(t, key) for t in column(batch, "text")]
            n = pa.array([sum(c.values()) for _, c in rows], pa.int64())
            kinds = pa.array([sorted(c) for _, c in rows], pa.list_(pa.string()))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([t for t, _ in rows], pa.string()), n, kinds], ["doc_id", "text", "n_found", "kinds"])

    return of_columns(docs, doc_id="long", text="string").mapInArrow(run, "doc_id long, text string, n_found long, kinds array<string>")
