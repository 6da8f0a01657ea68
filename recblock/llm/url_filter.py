"""URL filters by a bit-parallel wildcard automaton.

A rule is a glob over a canonical url: a dot, the host in lower case, a separator that no
text holds, the path. All globs share one row of 64-bit words, a bit for each literal and one
for each glob's start; reading a byte shifts the row by one, keeps the bits that the byte
allows and those that stand under a star. The urls of a batch are simulated side by side, so
a step is a few array operations for all of them and all rules.

A null url, or one without ``://``, has an empty host and path; it fits no rule with a host.
An empty table gives no rows; repeated rows are judged each for itself; of equally long rules
that fit, the first in the list wins."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from recblock.llm import textkernel as K

SEPARATOR = b"\xff"
#: The rules (action, host and path).
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))
#: The filter's own globs over hosts, where no rule fits.
BLOCKED_HOSTS = ("*casino*", "*cheap-pills*", "*free-bets*", "*ads-track*")
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def rule_glob(rule: str) -> bytes:
    """The host and its subdomains, then paths that start with the rule's."""
    host, _, path = rule.partition("/")
    return b"*." + host.encode() + SEPARATOR + b"/" + path.encode() + b"*"


def host_glob(glob: str) -> bytes:
    return b"." + glob.encode() + SEPARATOR + b"*" if not glob.startswith("*") else glob.encode() + SEPARATOR + b"*"


class Automaton:
    """Shift-And masks of globs in which ``*`` stands for any bytes, over whole texts."""

    def __init__(self, globs: list[bytes]):
        allowed: list[set[int]] = []
        loop, start, accept = [], [], []
        for glob in globs:
            parts = glob.split(b"*")
            start.append(len(allowed))
            allowed.append(set())
            loop.append(parts[0] == b"" and len(parts) > 1)
            for k, part in enumerate(parts):
                for c in part:
                    allowed.append({c})
                    loop.append(False)
                if k < len(parts) - 1:
                    loop[-1] = True
            accept.append(len(allowed) - 1)
        self.words = (len(allowed) + 63) // 64
        bits = lambda which: self._pack([bool(x) for x in which])
        self.moves = np.stack([bits(c in a for a in allowed) for c in range(256)])
        self.loop = bits(loop)
        self.start = bits(i in set(start) for i in range(len(allowed)))
        self.accept = accept

    def _pack(self, flags: list[bool]) -> np.ndarray:
        out = np.zeros(self.words, np.uint64)
        for i, f in enumerate(flags):
            if f:
                out[i // 64] |= np.uint64(1 << (i % 64))
        return out

    def fits(self, data: np.ndarray, offs: np.ndarray) -> np.ndarray:
        """bool (texts, globs)."""
        lengths = np.diff(offs)
        order = np.argsort(-lengths, kind="stable")
        state = np.tile(self.start, (len(order), 1))
        begin, sorted_lengths = offs[:-1][order], lengths[order]
        live = len(order)
        for k in range(int(lengths.max(initial=0))):
            live = int(np.searchsorted(-sorted_lengths[:live], -k, "left"))  # texts that have a byte k
            now = state[:live]
            moved = now << np.uint64(1)
            moved[:, 1:] |= now[:, :-1] >> np.uint64(63)
            state[:live] = (moved & self.moves[data[begin[:live] + k]]) | (now & self.loop)
        out = np.zeros((len(order), len(self.accept)), bool)
        for g, bit in enumerate(self.accept):
            out[order, g] = (state[:, bit // 64] >> np.uint64(bit % 64)) & np.uint64(1) > 0
        return out


def host_and_path(url: Column) -> tuple[Column, Column]:
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substr(url, at + 3)).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    return F.translate(F.regexp_extract(rest, r"^[^/?#]*", 0), UPPER, LOWER), F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)


def judge_urls(pages: DataFrame, rules: tuple = RULES, blocked: tuple = BLOCKED_HOSTS) -> DataFrame:
    """``pages(page_id, url)`` to page_id, host, path, rule and verdict."""
    host, path = host_and_path(F.col("url").cast("string"))
    named = pages.select("page_id", host.alias("host"), path.alias("path"))
    page_type = named.schema["page_id"].dataType.simpleString()
    texts = [r for _, r in rules]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = Automaton([rule_glob(r) for r in texts] + [host_glob(b) for b in blocked])
        weight = np.array([len(t) for t in texts] or [0])
        for batch in batches:
            hosts, paths = (c.to_pylist() for c in batch.columns[1:3])
            canonical = pa.array([b"." + h.encode() + SEPARATOR + p.encode() for h, p in zip(hosts, paths, strict=True)], pa.binary())
            rule, verdict = [], []
            for _, _, data, offs in K.chunks(canonical):
                hit = machine.fits(data, offs)
                own = np.where(hit[:, : len(texts)], weight[: len(texts)], -1)
                best = own.argmax(1) if len(texts) else np.zeros(len(hit), int)
                fit = hit[:, : len(texts)].any(1)
                other = hit[:, len(texts) :].any(1)
                rule += [texts[b] if f else None for b, f in zip(best, fit, strict=True)]
                verdict += [rules[b][0] if f else "block" if o else "allow" for b, f, o in zip(best, fit, other, strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(rule, pa.string()), pa.array(verdict, pa.string())], ["page_id", "host", "path", "rule", "verdict"])

    return named.mapInArrow(run, f"page_id {page_type}, host string, path string, rule string, verdict string")


def op2_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_urls(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url"))


OP2_SQL = r"""
WITH r AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
h AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
             regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM r),
m AS (SELECT *, CASE WHEN ends_with('.' || host, '.example.net') AND starts_with(path, '/en/') THEN 'example.net/en/'
                     WHEN ends_with('.' || host, '.example.com') AND starts_with(path, '/de/') THEN 'example.com/de/'
                     WHEN ends_with('.' || host, '.org') AND starts_with(path, '/fr/') THEN 'org/fr/'
                     WHEN ends_with('.' || host, '.net') AND starts_with(path, '/') THEN 'net/' END AS rule FROM h)
SELECT page_id, host, path, rule,
       CASE WHEN rule IN ('net/', 'example.com/de/') THEN 'block' WHEN rule IS NOT NULL THEN 'allow'
            WHEN host LIKE '%casino%' OR host LIKE '%cheap-pills%' OR host LIKE '%free-bets%' OR host LIKE '%ads-track%' THEN 'block' ELSE 'allow' END AS verdict
FROM m
"""
