"""URL filter: all wildcard rules of a list run at once as one multiword Shift-And automaton."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

U64 = np.uint64
START, SPLIT, PAD = 0xFE, 0xFF, 0xFD  # bytes that UTF-8 never has: start of host, host/path border, end of url
HOST_ANY = "*"


@dataclass(frozen=True)
class Rule:
    """A host (with all its subdomains) and a path prefix; `*` in the host stands for any run of host characters and
    `*` in the path for any run of path characters. The rule with the most characters wins, then the earlier one."""

    verdict: str
    host: str
    path: str = "/"

    @property
    def name(self) -> str:
        return self.host + self.path


class ShiftAnd:
    """Patterns packed side by side into 64-bit words.

    Bit i of a row's state says that pattern position i is the last one matched. Each byte moves all patterns of all
    rows at once: shift (with carry between words), keep the bits whose position accepts the byte, and add the
    self-loops of wildcards. Positions with an optional repeat ("any run of") let the state pass over them.
    """

    def __init__(self, rules: list[Rule]):
        self.rules = list(rules)
        cells: list[tuple[str, int]] = []  # (kind, byte): kind 'b' a byte, 'h' host run, 'p' path run
        self.first, self.last = [], []
        for r in self.rules:
            self.first.append(len(cells))
            # the host is a whole host or follows a dot: START, then optionally any run that ends with a dot
            cells.append(("b", START))
            cells.append(("d", 0))
            cells += [("h", 0) if c == ord("*") else ("b", c) for c in r.host.encode()]
            cells.append(("b", SPLIT))
            cells += [("p", 0) if c == ord("*") else ("b", c) for c in r.path.encode()]
            self.last.append(len(cells) - 1)
        self.bits = len(cells)
        self.words = max(1, -(-self.bits // 64))
        bit = lambda i: (i // 64, U64(1) << U64(i % 64))
        self.accept = np.zeros((256, self.words), U64)
        self.loop = np.zeros((256, self.words), U64)
        self.skip = np.zeros(self.words, U64)  # positions that may match nothing
        self.begin = np.zeros(self.words, U64)
        host = [c for c in range(256) if c not in (START, SPLIT, PAD)]
        for i, (kind, byte) in enumerate(cells):
            w, m = bit(i)
            if kind == "b":
                self.accept[byte, w] |= m
            else:
                for c in host:
                    self.loop[c, w] |= m
                    self.accept[c, w] |= m
                self.skip[w] |= m
        self.dotted = np.zeros(self.words, U64)  # the optional subdomain run, left only after a dot
        for i, (kind, _) in enumerate(cells):
            if kind == "d":
                w, m = bit(i)
                self.dotted[w] |= m
        for f in self.first:
            w, m = bit(f)
            self.begin[w] |= m
        self.final = [bit(i) for i in self.last]

    def _up(self, d: np.ndarray) -> np.ndarray:
        out = d << U64(1)
        if self.words > 1:
            out[:, 1:] |= d[:, :-1] >> U64(63)
        return out

    def match(self, texts: list[bytes]) -> np.ndarray:
        """Boolean matrix texts x rules: which patterns' last position was ever reached."""
        n = len(texts)
        hit = np.zeros((n, self.words), U64)
        if not n or not self.rules:
            return np.zeros((n, len(self.rules)), bool)
        order = np.argsort([-len(t) for t in texts], kind="stable")
        lengths = np.array([len(texts[i]) for i in order])
        flat = np.frombuffer(b"".join(texts[i] for i in order), np.uint8)
        at = np.concatenate([[0], np.cumsum(lengths)[:-1]])
        state = np.zeros((n, self.words), U64)
        live = n
        previous = np.zeros(n, np.uint8)
        for step in range(int(lengths[0])):
            while lengths[live - 1] <= step:
                live -= 1
            byte = flat[at[:live] + step]
            d = state[:live]
            # a subdomain run hands on only after a dot
            ready = np.where((previous[:live] == 0x2E)[:, None], d, d & ~self.dotted)
            moved = self._up(ready)
            if step == 0:
                moved |= self.begin
            through = self._up(moved & self.skip)
            while (through & ~moved).any():
                moved |= through
                through = self._up(moved & self.skip)
            d = (moved & self.accept[byte]) | (d & self.loop[byte])
            state[:live] = d
            hit[:live] |= d
            previous[:live] = byte
        out = np.zeros((n, len(self.rules)), bool)
        for k, (w, m) in enumerate(self.final):
            out[order, k] = (hit[:, w] & m) != 0
        return out

    def judge(self, texts: list[bytes]) -> np.ndarray:
        """Index of the winning rule of each text, -1 for none."""
        won = np.full(len(texts), -1)
        matched = self.match(texts)
        for k in sorted(range(len(self.rules)), key=lambda k: (len(self.rules[k].name), -k)):
            won[matched[:, k]] = k
        return won


def canonical(df: DataFrame, url: str = "url") -> DataFrame:
    """Adds host (A-Z lower-cased) and path by built-in functions; null or no `://`: both empty."""
    rest = F.expr(f"CASE WHEN {url} IS NOT NULL AND locate('://', {url}) > 0 THEN substring({url}, locate('://', {url}) + 3) ELSE '' END")
    host = F.regexp_extract("_rest", "^([^/?#]*)", 1)
    lower = F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    path = F.regexp_extract("_rest", "^[^/?#]*([^?#]*)", 1)
    return df.withColumn("_rest", rest).withColumn("host", lower).withColumn("path", path).drop("_rest")


def filter_urls(pages: DataFrame, rules: list[Rule], default: str = "allow") -> DataFrame:
    """page_id, host, path, rule, verdict of every page's url, in one narrow pass.

    No rule fits: rule is null and the verdict is `default`. Empty tables give no rows; repeated rows stay; other
    columns, whatever their names, are not carried.
    """
    machine = ShiftAnd(rules)
    names, verdicts = [r.name for r in machine.rules], [r.verdict for r in machine.rules]
    schema = pa.schema([("page_id", pa.int64()), ("host", pa.string()), ("path", pa.string()), ("rule", pa.string()), ("verdict", pa.string())])

    def run(batches):
        for batch in batches:
            for i in range(0, batch.num_rows, 4096):
                ids, hosts, paths = (c.slice(i, 4096) for c in batch.columns)
                texts = [bytes([START]) + h.encode() + bytes([SPLIT]) + p.encode() for h, p in zip(hosts.to_pylist(), paths.to_pylist())]
                won = machine.judge(texts)
                rule = pa.array([names[k] if k >= 0 else None for k in won], pa.string())
                verdict = pa.array([verdicts[k] if k >= 0 else default for k in won], pa.string())
                yield pa.RecordBatch.from_arrays([ids, hosts.cast(pa.string()), paths.cast(pa.string()), rule, verdict], schema=schema)

    plain = canonical(pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"))).select("page_id", "host", "path")
    return plain.mapInArrow(run, "page_id long, host string, path string, rule string, verdict string")


# fixed values: the rules of the pages query
PAGE_RULES = [
    Rule("allow", "org", "/"),
    Rule("block", "example.org", "/es/"),
    Rule("block", "example.org", "/en/1"),
    Rule("allow", "com", "/fr/"),
    Rule("block", "com", "/de/"),
]
