"""URL filter: a sort-merge range join of page keys with nested rule intervals.

A host is turned round label by label (``blog.example.org`` → ``org.example.blog.``), so a
rule for a host and all its subdomains is the interval of keys that start with the rule's
key, and intervals of different rules nest or are disjoint. Pages sorted by key are swept
once: a stack holds the rule hosts whose interval is open; on each of them a sorted list of
path prefixes, linked to the next shorter prefix, gives the longest path that fits.

Rules of up to ``local_rules`` (counted first) are swept within each map task, without any
shuffle. Beyond that the keys are dealt by range, and each rule goes to every range that its
interval meets: ranges are cut by (key, tie), so one very common host spreads too.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cotengine.llm.blocks import rows, schema_of

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_OUT = "page_id long, host string, path string, rule string, verdict string"
#: Keys sampled to place range boundaries: it affects balance only, never results.
BOUNDARY_SAMPLE = 20_000


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host and path of a url; both empty where it is null or has no ``://``."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")
    host = F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), _UPPER, _LOWER)
    return F.coalesce(host, F.lit("")), F.coalesce(F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def reversed_host(host: Column) -> Column:
    """Canonical key of a host: its labels from the last to the first, each closed by a dot."""
    return F.when(host == "", "").otherwise(F.concat(F.array_join(F.reverse(F.split(host, r"\.")), "."), F.lit(".")))


def _key(host: str) -> str:
    return "".join(label + "." for label in reversed(host.split("."))) if host else ""


class RuleSweep:
    """Rules as sorted intervals; ``sweep`` walks page keys in ascending order once."""

    def __init__(self, rules: list[tuple[str, str, str]]):
        by_host: dict[str, dict[str, tuple[str, str]]] = {}
        for host, path, verdict in rules:
            held = by_host.setdefault(_key(host), {})
            # One rule twice: blocking wins, whatever the order of the rows.
            if path not in held or verdict == "block":
                held[path] = (host + path, verdict)
        self.nodes = []
        for key in sorted(by_host):
            paths = sorted(by_host[key])
            up = [next((j for j in range(i - 1, -1, -1) if p.startswith(paths[j])), -1) for i, p in enumerate(paths)]
            self.nodes.append((key, paths, up, [by_host[key][p] for p in paths]))

    @staticmethod
    def _fit(node, path: str):
        _, paths, up, named = node
        i = bisect_right(paths, path) - 1
        while i >= 0 and not path.startswith(paths[i]):
            i = up[i]
        return named[i] if i >= 0 else None

    def sweep(self, pages: list[tuple[str, str]], default: str) -> list[tuple[str | None, str]]:
        """(key, path) in ascending order of key → (rule, verdict) of each."""
        out, stack, at = [], [], 0
        for key, path in pages:
            while at < len(self.nodes) and self.nodes[at][0] <= key:
                while stack and not self.nodes[at][0].startswith(stack[-1][0]):
                    stack.pop()
                stack.append(self.nodes[at])
                at += 1
            while stack and not key.startswith(stack[-1][0]):
                stack.pop()
            best = None
            for node in stack:
                fit = self._fit(node, path)
                if fit and (best is None or len(fit[0]) >= len(best[0])):
                    best = fit
            out.append(best or (None, default))
        return out


def _swept(table: pa.Table | pa.RecordBatch, sweep: RuleSweep, default: str, schema: pa.Schema) -> pa.RecordBatch:
    keys, paths = table.column("key").to_pylist(), table.column("path").to_pylist()
    order = sorted(range(len(keys)), key=keys.__getitem__)
    found = sweep.sweep([(keys[i], paths[i]) for i in order], default)
    rule, verdict = [None] * len(keys), [default] * len(keys)
    for i, (r, v) in zip(order, found):
        rule[i], verdict[i] = r, v
    return rows(schema, table.column("page_id").cast(pa.int64()), table.column("host"), table.column("path"), rule, verdict)


def filter_urls(pages: DataFrame, rules: DataFrame, *, page_id: str = "page_id", url: str = "url", default: str = "allow", local_rules: int = 100_000, ranges: int | None = None) -> DataFrame:
    """pages × rules (host, path, verdict) → page_id, host, path, rule, verdict of every page.

    A rule fits its host and all subdomains if the page's path starts with the rule's path.
    The longest rule string wins; of equal lengths the one with the longer host. Null or
    unparsable urls have empty host and path and get ``default``, as pages that no rule fits.
    Rules with a null host or path are left out. Repeated pages each keep their row; an empty
    page table gives an empty result; other columns of ``pages`` are ignored.
    """
    host, path = host_and_path(F.col(url))
    keyed = pages.select(F.col(page_id).cast("long").alias("page_id"), host.alias("host"), path.alias("path")).withColumn("key", reversed_host(F.col("host")))
    wanted = rules.select("host", "path", "verdict").where("host IS NOT NULL AND path IS NOT NULL AND verdict IS NOT NULL")
    schema = schema_of(_OUT)
    first = wanted.limit(local_rules + 1).collect()
    if len(first) <= local_rules:
        sweep = RuleSweep([tuple(r) for r in first])

        def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                yield _swept(batch, sweep, default, schema)

        return keyed.mapInArrow(local, _OUT)
    return _by_range(keyed, wanted, default, ranges)


def _by_range(keyed: DataFrame, rules: DataFrame, default: str, ranges: int | None) -> DataFrame:
    spark = keyed.sparkSession
    n = ranges or max(2, int(spark.conf.get("spark.sql.shuffle.partitions")))
    tied = keyed.withColumn("tie", F.abs(F.xxhash64("page_id", "path")) % 1_000_003)
    sample = sorted((r.key, r.tie) for r in tied.select("key", "tie").orderBy(F.xxhash64("page_id", "path", "key")).limit(BOUNDARY_SAMPLE).collect())
    cuts = sorted({sample[len(sample) * i // n] for i in range(1, n)} if sample else set())
    schema = schema_of(_OUT)
    to = "part int, page_id long, host string, path string, key string, is_rule boolean, verdict string"
    part = schema_of(to)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys, ties = b.column("key").to_pylist(), b.column("tie").to_pylist()
            k = len(keys)
            yield rows(part, [bisect_right(cuts, x) for x in zip(keys, ties)], b.column("page_id"), b.column("host"), b.column("path"), b.column("key"), [False] * k, [None] * k)

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[tuple] = []
            for host, path, verdict in zip(b.column("host").to_pylist(), b.column("path").to_pylist(), b.column("verdict").to_pylist()):
                key = _key(host)
                low, high = bisect_right(cuts, (key, -1)), bisect_right(cuts, (key + "\U0010ffff", -1)) if key else len(cuts)
                out += [(p, None, host, path, key, True, verdict) for p in range(low, high + 1)]
            yield rows(part, *(zip(*out) if out else [[]] * 7))

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # Within a partition the rules of a range come first (sorted so), then its pages in batches.
        own: dict[int, list] = {}
        made: dict[int, RuleSweep] = {}
        for b in batches:
            for p, host, path, verdict in zip(*(b.filter(b.column("is_rule")).column(c).to_pylist() for c in ("part", "host", "path", "verdict"))):
                own.setdefault(p, []).append((host, path, verdict))
            left = b.filter(pa.compute.invert(b.column("is_rule")))
            for p in pa.compute.unique(left.column("part")).to_pylist():
                if p not in made:
                    made = {p: RuleSweep(own.pop(p, []))}
                yield _swept(left.filter(pa.compute.equal(left.column("part"), p)), made[p], default, schema)

    both = tied.mapInArrow(deal, to).union(rules.mapInArrow(spread, to))
    return both.repartition(n, "part").sortWithinPartitions("part", F.col("is_rule").desc()).mapInArrow(merge, _OUT)
