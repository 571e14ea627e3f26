"""URL filters by a bit-parallel wildcard automaton.

All glob rules are packed end to end into machine words (Shift-And). Each rule has a start bit and one bit for each
literal or `?`; `*` after a bit lets that bit hold itself. One step per byte of the canonical URL moves every rule at
once: shift with a carry from word to word, mask by the byte, keep the held bits. Whole columns of URLs move together.

Canonical URL: "." + host + NUL + path + NUL + rest, so a host glob such as `*.org` is closed by the first NUL.
The rules of the list are judged first, the longest fitting one wins; where none fits, the method's own globs block.

Cases: null url or one without "://": host, path and rest are empty; further columns are ignored; an empty table gives
no rows; URLs of any length are read whole.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from slowlens.llm.common import table

NUL = "\x00"
#: (verdict, host, path prefix)
RULES = [("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/")]
#: What blocks a URL that no rule fits, as globs over the canonical URL.
OWN_GLOBS = [f".ads.*{NUL}*", f".tracker.*{NUL}*", f"*{NUL}*/login*{NUL}*", f"*{NUL}*.exe{NUL}*", f"*{NUL}*.zip{NUL}*"]
CELLS = 4_000_000


class WildcardAutomaton:
    def __init__(self, globs: list[str]):
        bits: list[tuple[bytes | None, int]] = []  # the byte a bit waits for (b"" a start, None any); its number
        held, self.finals, starts = [], [], []
        for glob in globs:
            at = len(bits)
            bits.append((b"", at))
            starts.append(at)
            for ch in glob.encode():
                if ch == ord("*"):
                    held.append(len(bits) - 1)
                else:
                    bits.append((None if ch == ord("?") else bytes([ch]), len(bits)))
            self.finals.append(len(bits) - 1)
        self.words = -(-len(bits) // 64)
        self.start, self.hold, self.by_byte = self._mask(starts), self._mask(held), np.zeros((256, self.words), np.uint64)
        for want, i in bits:
            for c in [] if want == b"" else range(256) if want is None else [want[0]]:
                self.by_byte[c, i // 64] |= np.uint64(1 << (i % 64))

    def _mask(self, places: list[int]) -> np.ndarray:
        out = np.zeros(self.words, np.uint64)
        for i in places:
            out[i // 64] |= np.uint64(1 << (i % 64))
        return out

    def match(self, urls: list[bytes]) -> np.ndarray:
        """A row per URL, a column per glob: whether it fits the whole URL."""
        out = np.zeros((len(urls), len(self.finals)), bool)
        order = sorted(range(len(urls)), key=lambda i: len(urls[i]))
        at = 0
        while at < len(order):
            n = 1
            while at + n < len(order) and (n + 1) * len(urls[order[at + n]]) <= CELLS and n < 8192:
                n += 1
            rows = order[at : at + n]
            out[rows] = self._run([urls[i] for i in rows])
            at += n
        return out

    def _run(self, urls: list[bytes]) -> np.ndarray:
        lengths = np.array([len(u) for u in urls])
        width = int(lengths.max(initial=0))
        cells = np.frombuffer(b"".join(u.ljust(width, b"\x00") for u in urls), np.uint8).reshape(len(urls), width)
        state = np.tile(self.start, (len(urls), 1))
        one, top = np.uint64(1), np.uint64(63)
        for k in range(width):
            live = int(np.searchsorted(lengths, k, side="right"))  # lengths ascend: those before have ended
            now = state[live:]
            moved = now << one
            moved[:, 1:] |= now[:, :-1] >> top
            state[live:] = (moved & self.by_byte[cells[live:, k]]) | (now & self.hold)
        return np.stack([(state[:, f // 64] >> np.uint64(f % 64)) & one != 0 for f in self.finals], axis=1)


def host_and_path(url: Column) -> tuple[Column, Column, Column]:
    """Host (A-Z lower-cased), path, and what follows them."""
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    text = F.coalesce(url, F.lit(""))
    host = F.translate(F.regexp_extract(text, r"(?s)^.*?://([^/?#]*)", 1), upper, lower)
    return host, F.regexp_extract(text, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.regexp_extract(text, r"(?s)^.*?://[^?#]*(.*)$", 1)


def judge(pages: DataFrame, rules: list[tuple[str, str, str]] = RULES, globs: list[str] = OWN_GLOBS) -> DataFrame:
    """page_id, host, path, rule, verdict, glob (the first of the method's own globs that fits, or null)."""
    host, path, rest = host_and_path(F.col("url"))
    parts = pages.select("page_id", host.alias("host"), path.alias("path"), rest.alias("rest"))
    names = [h + p for _, h, p in rules]
    ranked = sorted(range(len(rules)), key=lambda i: -len(names[i]))
    packed = [f"*.{h}{NUL}{p}*" for _, h, p in rules] + globs

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        automaton = WildcardAutomaton(packed)
        for batch in batches:
            hosts, paths, rests = (batch.column(c).to_pylist() for c in ("host", "path", "rest"))
            clean = lambda s: s.replace(NUL, "�")
            fits = automaton.match([f".{clean(h)}{NUL}{clean(p)}{NUL}{clean(r)}".encode() for h, p, r in zip(hosts, paths, rests, strict=True)])
            rule, verdict, glob = [], [], []
            for row in fits:
                won = next((i for i in ranked if row[i]), None)
                own = next((g for g, hit in zip(globs, row[len(rules) :], strict=True) if hit), None)
                rule.append(None if won is None else names[won])
                glob.append(None if own is None else own.replace(NUL, "|"))
                verdict.append(rules[won][0] if won is not None else "block" if own is not None else "allow")
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("host"), batch.column("path"), pa.array(rule, pa.string()), pa.array(verdict, pa.string()), pa.array(glob, pa.string())], names=["page_id", "host", "path", "rule", "verdict", "glob"])

    return parts.mapInArrow(run, "page_id bigint, host string, path string, rule string, verdict string, glob string")


def op5_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "pages").select("page_id", "url"))


OP5_SQL = r"""
WITH u AS (
  SELECT page_id, translate(regexp_extract(coalesce(url, ''), '^.*?://([^/?#]*)', 1, 's'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    regexp_extract(coalesce(url, ''), '^.*?://[^/?#]*([^?#]*)', 1, 's') AS path
  FROM pages
), r(verdict, host, path) AS (VALUES ('allow', 'org', '/'), ('block', 'example.org', '/es/'), ('block', 'example.org', '/en/1'), ('allow', 'com', '/fr/'), ('block', 'com', '/de/')),
w AS (
  SELECT u.page_id, arg_max(r.host || r.path, length(r.host || r.path)) AS rule, arg_max(r.verdict, length(r.host || r.path)) AS verdict
  FROM u JOIN r ON ends_with('.' || u.host, '.' || r.host) AND starts_with(u.path, r.path) GROUP BY u.page_id
), g AS (
  SELECT page_id, CASE WHEN '.' || host LIKE '.ads.%' THEN '.ads.*|*' WHEN '.' || host LIKE '.tracker.%' THEN '.tracker.*|*'
    WHEN path LIKE '%/login%' THEN '*|*/login*|*' WHEN path LIKE '%.exe' THEN '*|*.exe|*' WHEN path LIKE '%.zip' THEN '*|*.zip|*' END AS glob FROM u
)
SELECT u.page_id, u.host, u.path, w.rule, coalesce(w.verdict, CASE WHEN g.glob IS NOT NULL THEN 'block' ELSE 'allow' END) AS verdict, g.glob
FROM u LEFT JOIN w USING (page_id) JOIN g USING (page_id)
"""
