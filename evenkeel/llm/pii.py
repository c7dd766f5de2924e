"""Format-preserving pseudonyms for personal data.

Card numbers (Luhn), phone numbers, social security numbers, IBANs (mod 97), IPv4
addresses, dates and the local parts of e-mail addresses are validated and then
permuted among all values of their own format by a keyed Feistel network with cycle
walking.  A pseudonym is as long as its value, has its layout and passes the same
validation; equal values get equal pseudonyms in every document, also where they are
written with other separators.  Without the key the values can't be told.
"""

from __future__ import annotations

import datetime as dt
import hashlib
import math
import re
import secrets
from collections.abc import Callable
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenkeel.llm import _bytes, _store

ROUNDS = 8


@dataclass(frozen=True)
class Settings:
    #: Secret. Pseudonyms of different keys don't match.
    key: bytes


_keys: dict[str, bytes] = {}


def key_of(spark: SparkSession) -> bytes:
    """The key in ``spark.evenkeel.pii.key``.  Without that setting one is drawn for the
    application: pseudonyms are linked within it, and nobody can undo them afterwards."""
    given = spark.conf.get("spark.evenkeel.pii.key", None)
    return given.encode() if given else _keys.setdefault(spark.sparkContext.applicationId, secrets.token_bytes(32))


class Feistel:
    """A keyed permutation of ``range(size)`` for each tweak."""

    def __init__(self, key: bytes):
        self.key = hashlib.sha256(key).digest()

    def __call__(self, value: int, size: int, tweak: str) -> int:
        if size < 2:
            return value
        a = math.isqrt(size - 1) + 1
        b = -(-size // a)
        while True:
            left, right = divmod(value, b)  # left < a, right < b
            for r in range(ROUNDS):
                if r % 2:
                    right = (right + self._mix(left, r, size, tweak)) % b
                else:
                    left = (left + self._mix(right, r, size, tweak)) % a
            value = left * b + right
            if value < size:
                return value

    def _mix(self, half: int, r: int, size: int, tweak: str) -> int:
        said = f"{tweak}|{size}|{r}|{half}".encode()
        return int.from_bytes(hashlib.blake2b(said, key=self.key, digest_size=16).digest(), "big")


def luhn_digit(payload: str) -> str:
    total = 0
    for i, c in enumerate(reversed(payload)):
        d = int(c) * (2 if i % 2 == 0 else 1)
        total += d - 9 if d > 9 else d
    return str(-total % 10)


def _refill(layout: str, new: str) -> str:
    """``layout`` with its letters and digits replaced by those of ``new`` in order."""
    it = iter(new)
    return "".join(next(it) if c.isalnum() else c for c in layout)


def _card(m: str, f: Feistel) -> str | None:
    d = re.sub(r"[ -]", "", m)
    if not 13 <= len(d) <= 19 or luhn_digit(d[:-1]) != d[-1] or d[0] == "0":
        return None
    n = len(d) - 2
    body = d[0] + str(f(int(d[1:-1]), 10**n, f"card{d[0]}")).zfill(n)
    return _refill(m, body + luhn_digit(body))


#: Ten digits in the usual three groups, or in one.
_SHAPED = re.compile(r"(?:1[ .-]?)?(?:\(\d{3}\)[ .-]?|\d{3}[ .-])\d{3}[ .-]\d{4}")
_UNDIVIDED = re.compile(r"1?\d{10}")
#: An area code that begins with 0, and a number.
_NATIONAL = re.compile(r"0[1-9]\d{1,3}[ /-]\d{5,8}")
#: Country code: digits that may follow it.
_LENGTHS = {
    "1": (10,), "7": (10,), "20": (9, 10), "27": (9,), "30": (10,), "31": (9,), "32": (8, 9), "33": (9,), "34": (9,), "36": (8, 9), "39": (9, 10), "41": (9,), "44": (9, 10), "45": (8,), "46": (8, 9), "47": (8,), "48": (9,), "49": (10, 11),
    "52": (10,), "54": (10, 11), "55": (10, 11), "61": (9,), "64": (8, 9), "65": (8,), "81": (9, 10), "82": (9, 10), "86": (10, 11), "90": (10,), "91": (10,), "351": (9,), "353": (8, 9), "380": (9,), "420": (9,), "852": (8,), "886": (8, 9), "971": (8, 9), "972": (8, 9),
}


def _phone(m: str, f: Feistel) -> str | None:
    d = re.sub(r"\D", "", m)
    if _NATIONAL.fullmatch(m) and 9 <= len(d) <= 12:
        n = len(d) - 2
        v = f((int(d[1]) - 1) * 10**n + int(d[2:]), 9 * 10**n, "national")
        return _refill(m, "0" + str(v // 10**n + 1) + str(v % 10**n).zfill(n))
    national = d[1:] if m.startswith("+1") or len(d) == 11 and d[0] == "1" else d
    if (m.startswith("+1") or not m.startswith("+")) and len(national) == 10:
        a, x, line = int(national[:3]), int(national[3:6]), int(national[6:])
        low = a < 200 or x < 200  # not given out, but what is written as a number is taken for one
        if low and not m.startswith("+1") and not _SHAPED.fullmatch(m):
            return None
        a0, x0 = (200 if a >= 200 else 0), (200 if x >= 200 else 0)
        many, each = (800 if a0 else 200), (800 if x0 else 200)
        v = f(((a - a0) * each + x - x0) * 10000 + line, many * each * 10000, f"nanp{a0}-{x0}" if low else "nanp")
        v, line = divmod(v, 10000)
        a, x = divmod(v, each)
        return _refill(m, d[: len(d) - 10] + f"{a + a0:03}{x + x0:03}{line:04}")
    if m.startswith("+") and 8 <= len(d) <= 15:
        head, trunk, tail = m.partition("(0)")  # a zero that is dialled at home only: it stays
        d = re.sub(r"\D", "", head + tail)
        n = len(d) - 2
        new = d[:2] + str(f(int(d[2:]), 10**n, f"phone{d[:2]}")).zfill(n)
        k = sum(c.isdigit() for c in head)
        return _refill(head, new[:k]) + trunk + _refill(tail, new[k:])
    return None


def _ssn(m: str, f: Feistel) -> str | None:
    a, g, s = int(m[:3]), int(m[4:6]), int(m[7:])
    if a in (0, 666) or a >= 900 or not g or not s:
        return None
    v = (((a - 1 if a < 666 else a - 2) * 99) + g - 1) * 9999 + s - 1
    v, s = divmod(f(v, 898 * 99 * 9999, "ssn"), 9999)
    a, g = divmod(v, 99)
    a = a + 1 if a + 1 < 666 else a + 2
    return f"{a:03}-{g + 1:02}-{s + 1:04}"


def _permute_classes(s: str, f: Feistel, tweak: str) -> str:
    """Digits stay digits, small letters small, capitals capital; all permuted jointly."""
    value, size, classes = 0, 1, []
    for c in s:
        base, n = ("0", 10) if c.isdigit() else ("a", 26) if c.islower() else ("A", 26)
        classes.append((base, n))
        value, size = value * n + ord(c) - ord(base), size * n
    value, out = f(value, size, tweak), []
    for base, n in reversed(classes):
        value, k = divmod(value, n)
        out.append(chr(ord(base) + k))
    return "".join(reversed(out))


def _mod97(s: str) -> int:
    return int("".join(str(int(c, 36)) for c in s)) % 97


def _iban(m: str, f: Feistel) -> str | None:
    s = m.replace(" ", "")
    if not 15 <= len(s) <= 34 or _mod97(s[4:] + s[:4]) != 1:
        return None
    body = _permute_classes(s[4:], f, f"iban{s[:2]}")
    return _refill(m, s[:2] + f"{98 - _mod97(body + s[:2] + '00'):02}" + body)


def _ip(m: str, f: Feistel) -> str | None:
    parts = m.split(".")
    if any(int(p) > 255 or len(p) > 1 and p[0] == "0" for p in parts):
        return None
    low, many = {1: 0, 2: 10, 3: 100}, {1: 10, 2: 90, 3: 156}
    value, size = 0, 1
    for p in parts:
        value, size = value * many[len(p)] + int(p) - low[len(p)], size * many[len(p)]
    value, out = f(value, size, "ip" + "".join(str(len(p)) for p in parts)), []
    for p in reversed(parts):
        value, k = divmod(value, many[len(p)])
        out.append(str(k + low[len(p)]))
    return ".".join(reversed(out))


_FIRST_DAY, _LAST_DAY = dt.date(1900, 1, 1).toordinal(), dt.date(2099, 12, 31).toordinal()


def _date(m: str, f: Feistel) -> str | None:
    a, b, c = (p for p in re.split(r"[-/.]", m))
    seps = re.findall(r"[-/.]", m)
    if seps[0] != seps[1]:
        return None
    order = "ymd" if len(a) == 4 else "dmy" if int(b) <= 12 else "mdy"
    try:
        part = dict(zip(order, (a, b, c), strict=True))
        day = dt.date(int(part["y"]), int(part["m"]), int(part["d"]))
    except ValueError:
        return None
    if not 1900 <= day.year <= 2099:
        return None
    ordinal = day.toordinal()
    while True:  # until it can be written in the same layout and is read the same way
        ordinal = _FIRST_DAY + f(ordinal - _FIRST_DAY, _LAST_DAY - _FIRST_DAY + 1, "date")
        new = dt.date.fromordinal(ordinal)
        padded = {k: str(v).zfill(len(part[k])) for k, v in (("y", new.year), ("m", new.month), ("d", new.day))}
        same = all(len(padded[k]) == len(part[k]) and (part[k][0] == "0" or padded[k][0] != "0" or len(padded[k]) == 1) for k in "md") if len(a) != 4 and min(len(part["d"]), len(part["m"])) == 1 else all(len(padded[k]) == len(part[k]) for k in "ymd")
        if same and (order != "mdy" or new.day > 12):
            return seps[0].join(padded[k] for k in order)


def _email(m: str, f: Feistel) -> str | None:
    local, _, domain = m.rpartition("@")
    plain = re.sub(r"[^A-Za-z0-9]", "", local)
    return _refill(local, _permute_classes(plain, f, f"mail{domain.lower()}")) + "@" + domain


#: name: (pattern, pseudonym or None if the value is not valid). The first that is valid wins.
KINDS: dict[str, tuple[str, Callable[[str, Feistel], str | None]]] = {
    "email": (r"(?<![\w.+@-])[A-Za-z0-9][A-Za-z0-9._%+-]{0,63}@[A-Za-z0-9-]{1,63}(?:\.[A-Za-z0-9-]{1,63}){0,8}\.[A-Za-z]{2,24}(?![\w@])", _email),
    "iban": (r"(?<!\w)[A-Z]{2}\d\d(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?!\w)", _iban),
    "date": (r"(?<![\w./-])(?:\d{4}[-/.]\d{1,2}[-/.]\d{1,2}|\d{1,2}[-/.]\d{1,2}[-/.]\d{4})(?=[T\s,;:!?)\]\"']|\.?(?:\s|$))", _date),
    "ip": (r"(?<![\w.])\d{1,3}(?:\.\d{1,3}){3}(?![\w]|\.\d)", _ip),
    "ssn": (r"(?<![\w-])\d{3}-\d\d-\d{4}(?![\w]|-\d)", _ssn),
    "card": (r"(?<![\w+.-])\d(?:[ -]?\d){12,18}(?![\w]|-\d)", _card),
    "phone": (r"(?<![\w+.])(?:\+\d{1,3}[ .-]?(?:\d[ .-])?)?(?:\(\d{1,4}\)[ .-]?)?\d{2,5}(?:[ ./-]?\d{2,5}){1,4}(?![\w]|[-.]\d)", _phone),
}
_PATTERN = re.compile("|".join(f"(?P<{k}>{p})" for k, (p, _) in KINDS.items()))
_EACH = {k: re.compile(p) for k, (p, _) in KINDS.items()}


#: Kinds whose pattern may run on into digits or words that follow a value.
_MAY_RUN_ON = ("iban", "card", "phone")


def _usual(kind: str, m: str) -> bool:
    """Whether a value is as long as such values mostly are."""
    d = re.sub(r"\D", "", m.replace("(0", "("))
    if kind == "card":
        return len(d) == (15 if d[:2] in ("34", "37") else 16)
    if kind == "phone" and m.startswith("+"):
        known = [k for k in (1, 2, 3) if d[:k] in _LENGTHS]
        return not known or len(d) - known[0] in _LENGTHS[d[: known[0]]]
    return True


def _shorter(kind: str, m: str) -> list[str]:
    """What a match can be cut to at a separator, longest first."""
    out = []
    for i in range(len(m) - 1, 0, -1):
        if m[i] in " .-/" and _EACH[kind].fullmatch(m[:i]):
            if kind != "phone" or m[0] == "+" and m[i] == " " or _SHAPED.fullmatch(m[:i]) or m[i] == " " and _UNDIVIDED.fullmatch(m[:i]):
                out.append(m[:i])
    return out


def _value(kind: str, text: str, start: int, feistel: Feistel) -> tuple[str, int] | None:
    """Pseudonym and end of the value of a kind that starts there.  One of a usual length
    goes before others, a longer one before a shorter one."""
    own = _EACH[kind].match(text, start)
    if not own:
        return None
    give, whole = KINDS[kind][1], own.group()
    every = [whole, *_shorter(kind, whole)] if kind in _MAY_RUN_ON else [whole]
    for m in sorted(every, key=lambda m: not _usual(kind, m)):
        if (new := give(m, feistel)) is not None:
            return new, start + len(m)
    return None


def pseudonymise(text: str, feistel: Feistel) -> tuple[str, int]:
    """The text with pseudonyms, and how many values were replaced."""
    out, at, count = [], 0, 0
    while m := _PATTERN.search(text, at):
        start = m.start()
        for kind in KINDS:  # a value that fails one validation may be of another kind
            if found := _value(kind, text, start, feistel):
                out += [text[at:start], found[0]]
                at, count = found[1], count + 1
                break
        else:
            out.append(text[at : start + 1])
            at = start + 1
    out.append(text[at:])
    return "".join(out), count


def _udf(settings: Settings):
    @F.arrow_udf("text string, n int")
    def replace(texts: pa.Array) -> pa.Array:
        feistel = Feistel(settings.key)
        done = [(None, None) if t is None else pseudonymise(t, feistel) for t in texts.to_pylist()]
        made = pa.StructArray.from_arrays([pa.array([d[0] for d in done], pa.string()), pa.array([d[1] for d in done], pa.int32())], ["text", "n"])
        del done
        _bytes.give_back()
        return made

    return replace


def _replaced(docs: DataFrame, settings: Settings, name: str) -> DataFrame:
    # Only texts with a digit or an @ can hold a value: no others go to Python.
    some = F.when(F.col("text").rlike("[0-9@]"), F.col("text"))
    return docs.withColumn(name, _udf(settings)(some))


def detect(docs: DataFrame, settings: Settings | None = None) -> DataFrame:
    """doc_id, text with pseudonyms, n_pseudonyms for every row.  Null text: null and 0;
    empty text: empty and 0.  Repeated rows give equal rows.  Other columns are ignored.
    Without settings the key is ``key_of`` the session."""
    settings = settings or Settings(key_of(docs.sparkSession))
    d = _replaced(docs.select("doc_id", "text"), settings, "r")
    return d.select("doc_id", F.coalesce("r.text", "text").alias("text"), F.coalesce("r.n", F.lit(0)).alias("n_pseudonyms"))


def mask(docs: DataFrame, settings: Settings | None = None) -> DataFrame:
    """``docs`` with pseudonyms in ``text``, other columns as they are; lengths stay.
    Without settings the key is ``key_of`` the session."""
    settings = settings or Settings(key_of(docs.sparkSession))
    name = _store.fresh(docs.columns, "replaced")
    d = _replaced(docs, settings, name)
    return d.select(*[F.coalesce(F.col(f"{name}.text"), F.col("text")).alias("text") if c == "text" else F.col(f"`{c}`") for c in docs.columns])


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detect(_store.table(spark, sf_dir, "documents"))
