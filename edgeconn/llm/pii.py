"""Format-preserving pseudonyms by keyed Feistel permutations.

Values that pass their format's own validation are replaced by another valid
value of the same format: card numbers keep their Luhn digit, dates stay
calendar dates, addresses stay addresses, and separators and letter case stay
in place. A value's pseudonym depends on the key, the kind and the value
alone, so equal values stay linked across documents, and the permutation is a
bijection, so different values stay different.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeconn.llm.common import blocks, text_or_empty

ROUNDS = 10


@dataclass(frozen=True)
class Settings:
    """key: secret of the permutation. The default is public: it links equal
    values but hides nothing; give your own and keep it (``of_session``)."""

    key: bytes = b"change this key"
    kinds: tuple[str, ...] = ("secret", "email", "iban", "ip", "date", "card", "phone", "ssn")


def of_session(spark, conf: str = "spark.edgeconn.pii.key") -> Settings:
    """Settings with the key that the session's configuration holds, if any."""
    key = spark.conf.get(conf, None)
    return Settings(key=key.encode()) if key else Settings()


class Feistel:
    """Keyed permutation of 0..size-1: a balanced network on the least even
    number of bits that holds the domain, walked until it lands inside."""

    def __init__(self, key: bytes, tweak: str, size: int):
        from hashlib import blake2b

        self.size, self.half = size, max(1, ((size - 1).bit_length() + 1) // 2)
        self.mask = (1 << self.half) - 1
        self.seed = blake2b(key + b"|" + tweak.encode(), digest_size=32).digest()

    def _round(self, i: int, v: int) -> int:
        from hashlib import blake2b

        n = (self.half + 7) // 8
        out = b""
        while len(out) < n:
            out += blake2b(v.to_bytes(n, "big") + bytes([i, len(out) // 64]), key=self.seed, digest_size=64).digest()
        return int.from_bytes(out[:n], "big") & self.mask

    def _walk(self, x: int, back: bool) -> int:
        while True:
            a, b = x >> self.half, x & self.mask
            for i in reversed(range(ROUNDS)) if back else range(ROUNDS):
                a, b = (b ^ self._round(i, a), a) if back else (b, a ^ self._round(i, b))
            x = a << self.half | b
            if x < self.size:
                return x

    def apply(self, x: int) -> int:
        return self._walk(x, False)

    def invert(self, x: int) -> int:
        return self._walk(x, True)


def luhn_digit(digits: str) -> int:
    """The digit that makes ``digits`` + it a valid Luhn number."""
    total = 0
    for i, c in enumerate(reversed(digits)):
        v = int(c) * (2 - i % 2)
        total += v - 9 if v > 9 else v
    return -total % 10


def _refill(shape: str, fresh: str) -> str:
    """``shape`` with its digits taken from ``fresh``."""
    it = iter(fresh)
    return "".join(next(it) if c.isdigit() else c for c in shape)


def _only(text: str) -> str:
    return "".join(c for c in text if c.isdigit())


def _radix(values: list[int], sizes: list[int]) -> tuple[int, int]:
    x, n = 0, 1
    for v, s in zip(values, sizes, strict=True):
        x, n = x * s + v, n * s
    return x, n


def _digits(x: int, sizes: list[int]) -> list[int]:
    out = []
    for s in reversed(sizes):
        x, v = divmod(x, s)
        out.append(v)
    return out[::-1]


class Pseudonymiser:
    def __init__(self, s: Settings):
        import re

        self.s, self.made = s, {}
        sep = r"[ -]?"
        forms = {
            "secret": r"(?i:(?<![A-Za-z0-9])(?:token|secret|api_?key|password)[\"']?\s*[=:]\s*[\"']?)(?P<secret>[0-9a-f]{20,}|[0-9A-F]{20,})(?![0-9A-Za-z])",
            "email": r"(?<![A-Za-z0-9._%+-])(?P<email>[A-Za-z0-9._%+-]+)@(?:[A-Za-z0-9-]+\.)+[A-Za-z]{2,}",
            "iban": r"(?<![A-Za-z0-9])(?P<iban>[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?)(?![A-Za-z0-9])",
            "ip": r"(?<![\w.])(?P<ip>[0-9]{1,3}(?:\.[0-9]{1,3}){3})(?!\w|\.[0-9])",
            "date": r"(?<![\w./-])(?P<date>[0-9]{4}-[0-9]{2}-[0-9]{2}|[0-9]{4}/[0-9]{2}/[0-9]{2}|[0-9]{1,2}/[0-9]{1,2}/[0-9]{4}|[0-9]{1,2}\.[0-9]{1,2}\.[0-9]{4})(?![\w/-]|\.[0-9])",
            "card": rf"(?<![\w.-])(?P<card>[0-9](?:{sep}[0-9]){{12,18}})(?![\w-]|\.[0-9])",
            "phone": r"(?<![\w.-])(?P<phone>(?:\+1[ .-]?)?\([0-9]{3}\)[ .-]?[0-9]{3}[ .-][0-9]{4}|\+1[ .-]?[0-9]{3}[ .-][0-9]{3}[ .-][0-9]{4}|[0-9]{3}[.-][0-9]{3}[.-][0-9]{4})(?![\w-])",
            "ssn": r"(?<![\w.-])(?P<ssn>[0-9]{3}-[0-9]{2}-[0-9]{4})(?![\w-])",
        }
        self.find = re.compile("|".join(forms[k] for k in s.kinds)).search
        self.one = {k: re.compile(forms[k]).match for k in s.kinds}
        self.group = re.compile(r"[A-Za-z0-9]+").match
        self.maybe = re.compile(r"[0-9@]|(?i:token|secret|key|password)").search

    def permute(self, kind: str, values: list[int], sizes: list[int], valid: Callable[[list[int]], bool] = lambda _: True) -> list[int]:
        x, n = _radix(values, sizes)
        net = Feistel(self.s.key, f"{kind}:{','.join(map(str, sizes))}", n)
        while True:  # from valid to valid: the walk stays a bijection of the valid values
            x = net.apply(x)
            if valid(out := _digits(x, sizes)):
                return out

    def replace(self, kind: str, value: str) -> str | None:
        """The pseudonym, or None where the value is not a valid one."""
        if (kind, value) not in self.made:
            if len(self.made) > 100_000:
                self.made.clear()
            self.made[kind, value] = getattr(self, f"_{kind}")(value)
        return self.made[kind, value]

    def _card(self, v: str) -> str | None:
        d = _only(v)
        if luhn_digit(d[:-1]) != int(d[-1]) or len(set(d)) == 1:
            return None
        new = "".join(map(str, self.permute("card", [int(c) for c in d[:-1]], [10] * (len(d) - 1), lambda x: len(set(x)) > 1)))
        return _refill(v, new + str(luhn_digit(new)))

    def _phone(self, v: str) -> str | None:
        """Ten digits without an area or exchange of zeros, not all the same."""
        ok = lambda x: any(x[:3]) and any(x[3:6]) and len(set(x)) > 1
        d = [int(c) for c in _only(v)[-10:]]
        if not ok(d):
            return None
        return _refill(v, _only(v)[:-10] + "".join(map(str, self.permute("phone", d, [10] * 10, ok))))

    def _ssn(self, v: str) -> str | None:
        ok = lambda x: x[0] not in (0, 666) and x[0] < 900 and x[1] > 0 and x[2] > 0
        x = [int(p) for p in v.split("-")]
        if not ok(x):
            return None
        return "{:03d}-{:02d}-{:04d}".format(*self.permute("ssn", x, [1000, 100, 10000], ok))

    def _ip(self, v: str) -> str | None:
        parts = v.split(".")
        if any(int(p) > 255 or (len(p) > 1 and p[0] == "0") for p in parts):
            return None
        low = [{1: 0, 2: 10, 3: 100}[len(p)] for p in parts]
        size = [{1: 10, 2: 90, 3: 156}[len(p)] for p in parts]
        new = self.permute("ip", [int(p) - a for p, a in zip(parts, low, strict=True)], size)
        return ".".join(str(x + a) for x, a in zip(new, low, strict=True))

    def _date(self, v: str) -> str | None:
        """Dates from 1900 to 2099; day first where a day leads, unless only
        month first is a date."""
        import datetime as dt

        sep = next(c for c in v if not c.isdigit())
        p = v.split(sep)
        orders = [(0, 1, 2)] if len(p[0]) == 4 else [(2, 1, 0), (2, 0, 1)]
        for o in orders:
            try:
                day = dt.date(*(int(p[i]) for i in o))
            except ValueError:
                continue
            if not 1900 <= day.year <= 2099:
                return None
            first, last = dt.date(1900, 1, 1).toordinal(), dt.date(2099, 12, 31).toordinal()
            wide = [len(x) for x in p]

            def shape(d, o=o, wide=wide) -> list[str]:
                out = ["", "", ""]
                for i, x in zip(o, (d.year, d.month, d.day), strict=True):
                    out[i] = f"{x:0{wide[i]}d}"
                return out

            unpadded = [i for i in range(3) if wide[i] == 1]
            fits = lambda x: all(len(t) == w for t, w in zip(shape(dt.date.fromordinal(first + x[0])), wide, strict=True))
            new = self.permute(f"date{o}{unpadded}", [day.toordinal() - first], [last - first + 1], fits)
            return sep.join(shape(dt.date.fromordinal(first + new[0])))
        return None

    def _iban(self, v: str) -> str | None:
        flat = v.replace(" ", "")
        number = lambda t: int("".join(str(int(c, 36)) for c in t))
        if number(flat[4:] + flat[:4]) % 97 != 1:
            return None
        body = flat[4:]
        new = iter(self.permute("iban" + flat[:2], [int(c, 36) if c.isdigit() else ord(c) - 65 for c in body], [10 if c.isdigit() else 26 for c in body]))
        body = "".join(str(next(new)) if c.isdigit() else chr(65 + next(new)) for c in body)
        fresh = iter(flat[:2] + f"{98 - number(body + flat[:2] + '00') % 97:02d}" + body)
        return "".join(c if c == " " else next(fresh) for c in v)

    def _email(self, v: str) -> str | None:
        return self._letters("email", v, "abcdefghijklmnopqrstuvwxyz")

    def _secret(self, v: str) -> str | None:
        hexed = "0123456789abcdef"
        new = self.permute("secret", [hexed.index(c) for c in v.lower()], [16] * len(v))
        out = "".join(hexed[x] for x in new)
        return out.upper() if v.upper() == v and v.lower() != v else out

    def _letters(self, kind: str, v: str, letters: str) -> str:
        at = [i for i, c in enumerate(v) if c.isalnum()]
        if not at:
            return v
        sizes = [10 if v[i].isdigit() else 26 for i in at]
        new = self.permute(kind, [int(v[i]) if v[i].isdigit() else letters.index(v[i].lower()) for i in at], sizes)
        out = list(v)
        for i, x in zip(at, new, strict=True):
            out[i] = str(x) if v[i].isdigit() else (letters[x].upper() if v[i].isupper() else letters[x])
        return "".join(out)

    def text(self, text: str) -> tuple[str, list[str]]:
        """The text with its valid values replaced, and their kinds in order."""
        if not self.maybe(text):
            return text, []
        out, kinds, at, m = [], [], 0, self.find(text)
        while m:
            got = self._valid(text, m)
            if got:
                kind, start, end, new = got
                out += [text[at:start], new]
                at = end
                kinds.append(kind)
            else:  # what follows the first group may be a value of its own
                first = self.group(text, m.start(m.lastgroup))
                end = first.end() if first else m.end(m.lastgroup)
            m = self.find(text, end)
        return "".join([*out, text[at:]]), kinds

    def _valid(self, text: str, m) -> tuple[str, int, int, str] | None:
        """(kind, start, end, pseudonym) of the first valid reading of a match:
        its own kind whole, then up to an earlier group, then other kinds."""
        own = m.lastgroup
        for kind in (own, *(k for k in self.s.kinds if k != own)):
            found = m if kind == own else self.one[kind](text, m.start())
            if not found:
                continue
            value, start = found[kind], found.start(kind)
            for size in self._sizes(kind, value):
                new = self.replace(kind, value[:size])
                if new is not None:
                    return kind, start, start + size, new
        return None

    def _sizes(self, kind: str, value: str) -> list[int]:
        """Lengths to try: the whole, and where neighbouring groups may have
        been taken in, what ends with an earlier group and is long enough."""
        least = {"card": 13, "iban": 12}.get(kind)
        sizes = [len(value)]
        if least:
            sizes += [i for i in range(len(value) - 1, 0, -1) if value[i] in " -" and sum(c.isalnum() for c in value[:i]) >= least]
        return sizes


def pseudonymise(docs: DataFrame, text_col: str = "text", s: Settings | None = None, report: bool = True) -> DataFrame:
    """All columns of ``docs`` with the text replaced, plus n_replaced int and
    kinds array<string>; a column of ``docs`` of those names gives way. Without
    ``report`` those two are left out and every column of ``docs`` stays.

    One row per row; a null text stays null, an empty one empty, repeated rows
    are replaced alike and an empty table stays empty. Texts are read whole;
    their lengths do not change. Digits are those of ASCII. Numbers that fail
    their validation stay as they are.
    """
    s = s or Settings()
    extra = ("n_replaced", "kinds") if report else ()
    base = docs.drop(*extra)
    schema = [f"`{f.name}` {f.dataType.simpleString()}" for f in base.schema.fields] + (["n_replaced int", "kinds array<string>"] if report else [])
    names = base.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make = Pseudonymiser(s)
        for b in blocks(batches, text_col):
            done = [make.text(t) if t is not None else (None, []) for t in b.column(text_col).to_pylist()]
            cols = [pa.array([t for t, _ in done], pa.string()) if n == text_col else b.column(n) for n in names]
            told = [pa.array([len(k) for _, k in done], pa.int32()), pa.array([k for _, k in done], pa.list_(pa.string()))] if report else []
            yield pa.RecordBatch.from_arrays([*cols, *told], [*names, *extra])

    return base.mapInArrow(run, ", ".join(schema))
