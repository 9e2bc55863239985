"""Secret scan with corpus-wide ownership frequency.

One pass over whole texts finds candidates: assigned values, access keys, long hex runs, and further formats of
credentials (``MORE``, the last of them any opaque string of mixed letters and digits with high entropy). Values are hashed;
an aggregate counts for each hash the distinct repositories and owners that hold it. A value that more than
MAX_OWNERS owners hold is a widely copied example; a value that looks live and stays with few owners is
a credential. Base spans always stay; a further span is added only if its value is such a credential.

The text never leaves the pass. Counting first reduces to distinct (hash, repository, owner). Hashes held by more than
1/HEAVY of all candidates, HEAVY at most, are joined by broadcast, the others by hash, so no value gathers
its documents in one task.

Defined cases: null text is empty; spans are in code points of the text as it is; repeated rows are judged alike and
each returned; null repositories or owners are one more repository or owner; no rows, no result; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize

# Fixed patterns of the base kinds, and how long their value must be.
ASSIGN = re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.IGNORECASE | re.ASCII)
ACCESS, HEX = re.compile(r"AKIA[A-Z0-9]+"), re.compile(r"[0-9a-f]{24,}")
HINTS = ("password", "passwd", "secret", "token", "api")
# Further kinds in order of precedence: name, hint, pattern.
MORE = [
    ("private_key", "-----BEGIN", re.compile(r"-----BEGIN [A-Z ]*PRIVATE KEY-----[A-Za-z0-9+/=\s]+-----END [A-Z ]*PRIVATE KEY-----")),
    ("jwt", "eyJ", re.compile(r"eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]+")),
    ("forge_token", "_", re.compile(r"(?<![A-Za-z0-9])(?:gh[pousr]_[A-Za-z0-9]{30,}|glpat-[A-Za-z0-9_-]{20,})")),
    ("maps_key", "AIza", re.compile(r"AIza[0-9A-Za-z_-]{30,}")),
    ("chat_token", "xox", re.compile(r"xox[abprs]-[0-9A-Za-z-]{10,}")),
    ("opaque", "", re.compile(r"[A-Za-z0-9+/_-]{20,}={0,2}")),
]
KINDS = ["assign", "access", "hex", *[k for k, _, _ in MORE]]
ENTROPY, MAX_OWNERS, HEAVY = 3.0, 2, 1000
EXAMPLES = re.compile(r"example|sample|dummy|changeme|your[-_]?|test|xxxx|1234567", re.IGNORECASE)
CANDIDATE = pa.struct([("kind", pa.int32()), ("start", pa.int32()), ("end", pa.int32()), ("hash", pa.int64()), ("live", pa.bool_())])


def entropy(s: str) -> float:
    n = len(s)
    return -sum(c / n * math.log2(c / n) for c in Counter(s).values()) if n else 0.0


def looks_live(value: str) -> bool:
    """High entropy, letters or digits mixed, and none of the marks of examples."""
    return entropy(value) >= ENTROPY and any(c.isdigit() for c in value) and not EXAMPLES.search(value)


def base_spans(text: str) -> list[tuple[int, int, int, str]]:
    """(start, kind, end, value), by start and then kind."""
    low, found = text.lower(), []
    if any(h in low for h in HINTS):
        found += [(m.start(), 0, m.end(), m[2]) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end(), m[0]) for m in ACCESS.finditer(text) if len(m[0]) >= 20]
    found += [(m.start(), 2, m.end(), m[0]) for m in HEX.finditer(text)]
    return sorted(found)


def more_spans(text: str, base: list) -> list[tuple[int, int, int, str]]:
    """Further live-looking candidates that touch no base span and no span of a kind before theirs."""
    taken, found = [(a, b) for a, _, b, _ in base], []
    for k, (_, hint, pattern) in enumerate(MORE, 3):
        if hint and hint not in text:
            continue
        mine = []
        for m in pattern.finditer(text):
            a, b = m.span()
            if looks_live(m[0]) and any(c.isalpha() for c in m[0]) and not any(a < y and x < b for x, y in taken):
                mine.append((a, k, b, m[0]))
        taken += [(a, b) for a, _, b, _ in mine]
        found += mine
    return found


def joined(spans: list) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in sorted(spans))


def find(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """-> row__ (a number of the row), ``id_col``, repository, owner, counts, base digest, base spans and candidates."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts, digests, bases, all_candidates = ([], [], []), [], [], []
            for t in batch.column("t__"):
                text = t.as_py() or ""
                base = base_spans(text)
                for k in range(3):
                    counts[k].append(sum(x[1] == k for x in base))
                line = joined([x[:3] for x in base])
                digests.append(hashlib.sha256(line.encode()).hexdigest())
                bases.append(line)
                h = lambda v: xxhash.xxh64_intdigest(v.encode(), 0) - (1 << 63)
                all_candidates.append(
                    [{"kind": k, "start": a, "end": b, "hash": h(v), "live": looks_live(v)} for a, k, b, v in base + more_spans(text, base)]
                )
            yield pa.RecordBatch.from_arrays(
                [*[batch.column(c) for c in (id_col, "repo__", "owner__")], *[pa.array(c, pa.int64()) for c in counts], pa.array(digests), pa.array(bases), pa.array(all_candidates, pa.list_(CANDIDATE))],
                names=[id_col, "repo__", "owner__", "n_assign", "n_access", "n_hex", "base_sha256", "base", "candidates"],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    schema = f"`{id_col}` {kind}, repo__ string, owner__ string, n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, base string, candidates array<struct<kind:int,start:int,end:int,hash:bigint,live:boolean>>"
    return docs.mapInArrow(run, schema).withColumn("row__", F.monotonically_increasing_id())


def ownership(candidates: DataFrame) -> DataFrame:
    """``hash``, ``repo__``, ``owner__`` -> ``hash``, ``n_rows``, ``n_repos``, ``n_owners``."""
    pairs = candidates.groupBy("hash", "owner__", "repo__").agg(F.count("*").alias("n"))
    owners = pairs.groupBy("hash", "owner__").agg(F.sum("n").alias("n"), F.count("*").alias("repos"))
    return owners.groupBy("hash").agg(F.sum("n").alias("n_rows"), F.sum("repos").alias("n_repos"), F.count("*").alias("n_owners"))


def scan(docs: DataFrame, repo, owner, id_col: str = "doc_id", text_col: str = "text", max_owners: int = MAX_OWNERS) -> DataFrame:
    """-> a row for each document: counts, ``base_sha256``, ``spans``, and how many of its values are ``n_live`` or ``n_copied``.

    ``repo`` and ``owner`` are columns or expressions of ``docs``.
    """
    given = docs.select(F.col(id_col), repo.cast("string").alias("repo__"), owner.cast("string").alias("owner__"), F.col(text_col).alias("t__"))
    found = materialize(find(given, id_col, "t__"), "secrets")
    each = found.where(F.size("candidates") > 0).select("row__", "repo__", "owner__", F.explode("candidates").alias("c")).select("row__", "repo__", "owner__", "c.*")
    counts = materialize(ownership(each), "ownership")
    total = counts.agg(F.coalesce(F.sum("n_rows"), F.lit(0))).first()[0]
    heavy = F.col("n_rows") > max(1, total // HEAVY)
    verdict = counts.withColumn("copied", F.col("n_owners") > max_owners).select("hash", "copied", heavy.alias("heavy"))
    often = F.broadcast(verdict.where("heavy").select("hash", F.col("copied").alias("heavy_copied")))  # at most HEAVY rows
    judged = each.join(often, "hash", "left")
    rest = judged.where("heavy_copied is null").join(verdict.where("not heavy").select("hash", "copied"), "hash")
    judged = judged.where("heavy_copied is not null").withColumn("copied", F.col("heavy_copied")).unionByName(rest)
    added = F.when((F.col("kind") > 2) & ~F.col("copied") & F.col("live"), F.struct("start", "kind", "end"))
    rows = judged.groupBy("row__").agg(
        F.collect_list(added).alias("added"),
        F.count_if(~F.col("copied") & F.col("live")).alias("n_live"),
        F.count_if(F.col("copied")).alias("n_copied"),
    )
    out = found.join(rows, "row__", "left")
    own = F.transform(F.filter("candidates", lambda c: c["kind"] < 3), lambda c: F.struct(c["start"].alias("start"), c["kind"].alias("kind"), c["end"].alias("end")))
    every = F.array_sort(F.concat(own, F.coalesce("added", F.array().cast("array<struct<start:int,kind:int,end:int>>"))))
    names = F.array(*[F.lit(k) for k in KINDS])
    spans = F.array_join(F.transform(every, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ",")
    zero = F.lit(0).cast("long")
    return out.select(id_col, "n_assign", "n_access", "n_hex", "base_sha256", spans.alias("spans"), F.coalesce("n_live", zero).alias("n_live"), F.coalesce("n_copied", zero).alias("n_copied"))
