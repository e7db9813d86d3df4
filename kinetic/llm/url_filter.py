"""URL filters by a bit-parallel wildcard automaton.

Every glob rule (``*`` any run of characters, ``?`` one character) is packed
into multiword Shift-And masks; all rules then advance together, one character
of each URL at a time, for a whole batch of URLs.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Symbols: any character that no rule has, the border between host and path, and the end; the rules' own characters follow.
OTHER, BORDER, END, OWN = 0, 1, 2, 3
#: Characters of the URLs that advance together, about, with what pads them.
CELLS = 2_000_000
#: Fewer URLs than this are taken one by one.
FEW = 8
ONE = np.uint64(1)


@dataclass(frozen=True)
class Rule:
    """verdict for URLs whose host fits ``host`` (or a subdomain) and whose path fits ``path``; both are globs."""

    host: str
    path: str
    verdict: str

    @property
    def name(self) -> str:
        return self.host + self.path


class ShiftAnd:
    """All rules in one automaton over host + BORDER + path.

    A rule occupies one bit per symbol and one accepting bit. ``step`` masks
    hold the symbols that advance a bit, ``stay`` those that keep it: a ``*``
    keeps its bit on every symbol of the same field.
    """

    def __init__(self, rules: list[Rule]):
        own = sorted({"."} | {c for r in rules for c in r.host + r.path})
        symbol = {c: OWN + i for i, c in enumerate(own)}
        self.chars, self.dot = np.array([ord(c) for c in own], np.uint32), symbol["."]
        symbols_ = OWN + len(own)
        anything = [s for s in range(symbols_) if s not in (BORDER, END)]
        places: list[tuple[set[int] | None, bool, bool]] = []  # symbols, star before it, in the host
        self.first, self.last = [], []
        for r in rules:
            self.first.append(len(places))
            star = True  # a dot precedes the canonical host, so that a suffix glob meets the host and its subdomains
            for host, part in ((True, "." + r.host), (False, r.path)):
                for c in part:
                    if c == "*":
                        star = True
                        continue
                    places.append((None if c == "?" else {symbol[c]}, star, host))
                    star = False
                if host:
                    places.append(({BORDER}, star, True))
                    star = False
            self.last.append(len(places))
            places.append((set(), True, False))  # accepting: whatever follows in the path
        self.words = max(1, -(-len(places) // 64))
        self.step = np.zeros((symbols_, self.words), np.uint64)
        self.stay = np.zeros((symbols_, self.words), np.uint64)
        self.start = np.zeros(self.words, np.uint64)
        for i in self.first:
            self.start[i // 64] |= ONE << np.uint64(i % 64)
        for i, (symbols, star, host) in enumerate(places):
            bit = ONE << np.uint64(i % 64)
            for s in anything if symbols is None else symbols:
                self.step[s, i // 64] |= bit
            if star:
                for s in anything + ([] if host else [BORDER]):
                    self.stay[s, i // 64] |= bit
        for i in self.last:  # accepted paths stay so to the end and beyond it
            self.stay[END, i // 64] |= ONE << np.uint64(i % 64)

    def encoded(self, host: str, path: str) -> np.ndarray:
        """Symbols of a URL: a dot, the host, the border, the path; one for each character."""
        code = np.frombuffer((host + path).encode("utf-32-le", "surrogatepass"), "<u4")
        at = np.minimum(np.searchsorted(self.chars, code), len(self.chars) - 1)
        symbols = np.where(self.chars[at] == code, at + OWN, OTHER)
        return np.concatenate([[self.dot], symbols[: len(host)], [BORDER], symbols[len(host) :]]).astype(np.int16)

    def run(self, urls: list[tuple[str, str]]) -> np.ndarray:
        """Boolean matrix of (host, path) x rules. URLs of like length advance together, CELLS characters at a time."""
        fits = np.zeros((len(urls), len(self.last)), bool)
        lengths = np.array([len(h) + len(p) + 2 for h, p in urls], np.int64)
        order = np.argsort(-lengths, kind="stable")
        start = 0
        while start < len(order):
            part = order[start : start + max(1, CELLS // int(lengths[order[start]]))]
            symbols = [self.encoded(*urls[u]) for u in part]
            fits[part] = self._advance(symbols) if len(part) >= FEW else np.array([self._alone(s) for s in symbols])
            start += len(part)
        return fits

    def _alone(self, url: np.ndarray) -> list[bool]:
        """The same for one URL, with its state as one long integer."""
        step, stay = ([int.from_bytes(row.astype("<u8").tobytes(), "little") for row in table] for table in (self.step, self.stay))
        state = int.from_bytes(self.start.astype("<u8").tobytes(), "little")
        for c in url.tolist():
            state = (state & step[c]) << 1 | state & stay[c]
        return [bool(state >> i & 1) for i in self.last]

    def _advance(self, urls: list[np.ndarray]) -> np.ndarray:
        """For URLs from the longest to the shortest. Bit i of a state: everything before place i has been met."""
        n = len(urls)
        lengths = np.fromiter(map(len, urls), np.int64, n)
        state = np.tile(self.start, (n, 1))
        flat = np.full((n, int(lengths[0])), END, np.int16)
        for row, u in enumerate(urls):
            flat[row, : len(u)] = u
        live = np.searchsorted(-lengths, -np.arange(flat.shape[1]), side="left")
        for at in range(flat.shape[1]):
            m = live[at]
            c, d = flat[:m, at], state[:m]
            hit = d & self.step[c]
            moved = hit << ONE
            moved[:, 1:] |= hit[:, :-1] >> np.uint64(63)
            state[:m] = moved | (d & self.stay[c])
        fits = np.zeros((n, len(self.last)), bool)
        for k, i in enumerate(self.last):
            fits[:, k] = (state[:, i // 64] >> np.uint64(i % 64)) & ONE == ONE
        return fits


def host_of(url: Column) -> Column:
    """Between the first ``://`` and ``/``, ``?``, ``#`` or the end, A-Z in lower case; empty if there is no ``://``."""
    rest = _rest(url)
    return F.translate(F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def path_of(url: Column) -> Column:
    """From the end of the host up to ``?``, ``#`` or the end."""
    return F.regexp_extract(_rest(url), r"(?s)^[^/?#]*([^?#]*)", 1)


def _rest(url: Column) -> Column:
    url = F.coalesce(url, F.lit(""))
    at = F.instr(url, "://")
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))


def judge_urls(df: DataFrame, rules: list[Rule], url_col: str = "url", keep: list[str] | None = None, default: str = "allow") -> DataFrame:
    """+host, path, rule (name of the longest fitting rule, else null), verdict, for every row.

    Of fitting rules the one with the longest name wins; equal lengths: block
    before allow, then the earlier rule. Null, empty and malformed URLs have an
    empty host and path, fit no rule and get ``default``. Repeated rows stay.
    ``keep`` names the input columns to return (all but clashing ones if None).
    """
    made = ["host", "path", "rule", "verdict"]
    keep = [c for c in df.columns if c not in made] if keep is None else keep
    ranked = sorted(rules, key=lambda r: (-len(r.name), r.verdict != "block"))
    parts = df.select(*[F.col(f"`{c}`") for c in keep], host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"))
    fields = [f for f in parts.schema.fields]

    def judged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = ShiftAnd(ranked)
        names = np.array([*(r.name for r in ranked), None], object)
        says = np.array([*(r.verdict for r in ranked), default], object)
        for b in batches:
            if not b.num_rows:
                continue
            hosts, paths = (b.column(n).to_pylist() for n in ("host", "path"))
            fits = machine.run(list(zip(hosts, paths, strict=True)))
            won = np.where(fits.any(1), fits.argmax(1), len(ranked)) if ranked else np.zeros(b.num_rows, np.int64)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(names[won].tolist(), pa.string()), pa.array(says[won].tolist(), pa.string())], names=[*b.schema.names, "rule", "verdict"])

    from pyspark.sql.types import StringType, StructField, StructType

    schema = StructType([*fields, StructField("rule", StringType()), StructField("verdict", StringType())])
    return parts.mapInArrow(judged, schema)
