"""Secret scans with an incremental blob ledger.

Every version of a text is named by the SHA-256 of its content. A ledger holds, for each (blob, rule version), that
it was scanned and what was found. A run scans only pairs that the ledger lacks, one copy of each blob, adds them
to the ledger, and joins the findings back to every row (path) with that content. The rule version is a digest
of the rules, so a changed rule scans again and an unchanged one never does.

Defined results: a null text is empty; equal contents have equal findings whatever their path; repeated rows come
back as often as they occur; offsets are code points, ends exclusive; columns ``blob`` and ``findings`` of the input
are replaced, all others stay; an empty table gives no rows. Every rule reads a text in linear time.
"""

from __future__ import annotations

import hashlib
import re
from functools import partial

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from bspframe.llm import text as K
from bspframe.session import materialise, ship, table_path

#: (kind, pattern or patterns of both ends, group that must be long enough, least length, plain strings one of which must occur or None)
BASE_RULES = (
    ("assign", r"""(?ai)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6, ("passw", "secret", "token", "api")),
    ("access", r"AKIA[A-Z0-9]+", 0, 20, ("AKIA",)),
    ("hex", r"[0-9a-f]{24,}", 0, 24, None),
)
#: Public formats of further credentials.
MORE_RULES = (
    ("pem", (r"-----BEGIN [A-Z ]*PRIVATE KEY-----", r"-----END [A-Z ]*PRIVATE KEY-----"), 0, 1, ("PRIVATE KEY-----",)),
    ("forge", r"\bgh[pousr]_[A-Za-z0-9]{36,}", 0, 40, ("gh",)),
    ("chat", r"\bxox[abprs]-[A-Za-z0-9-]{10,}", 0, 15, ("xox",)),
    ("web", r"(?<![A-Za-z0-9_-])eyJ[A-Za-z0-9_-]{8,}+\.eyJ[A-Za-z0-9_-]{8,}+\.[A-Za-z0-9_-]{8,}", 0, 1, ("eyJ",)),
    ("maps", r"\bAIza[A-Za-z0-9_-]{35}", 0, 39, ("AIza",)),
    ("pay", r"\b[sr]k_live_[A-Za-z0-9]{16,}", 0, 24, ("k_live_",)),
)
RULES = BASE_RULES + MORE_RULES
#: Blobs that a task remembers to have scanned.
SEEN = 100_000
BASE = tuple(r[0] for r in BASE_RULES)


def rule_version(rules=RULES) -> str:
    return hashlib.sha256(repr(rules).encode()).hexdigest()[:16]


def _between(text: str, begin: re.Pattern, end: re.Pattern):
    """Spans from a begin mark to the first end mark behind it; each mark is looked for once."""
    ends = [m.span() for m in end.finditer(text)]
    at = k = 0
    for m in begin.finditer(text):
        if m.start() < at:
            continue
        while k < len(ends) and ends[k][0] < m.end():
            k += 1
        if k == len(ends):
            return
        at = ends[k][1]
        yield m.start(), at


def find(text: str, rules=RULES, compiled: dict | None = None) -> list[tuple[str, int, int]]:
    """(kind, start, end) of every match of every rule: leftmost, not overlapping within a kind."""
    out = []
    low = None
    for kind, pattern, group, least, hints in rules:
        if hints is not None:
            if kind == "assign":
                low = text.lower() if low is None else low
                if not any(h in low for h in hints):
                    continue
            elif not any(h in text for h in hints):
                continue
        if isinstance(pattern, tuple):
            out += [(kind, *span) for span in _between(text, *map(re.compile, pattern))]
            continue
        search = re.compile(pattern) if compiled is None else compiled.setdefault(kind, re.compile(pattern))
        out += [(kind, *m.span()) for m in search.finditer(text) if m.end(group) - m.start(group) >= least]
    order = {r[0]: i for i, r in enumerate(rules)}
    return sorted(out, key=lambda f: (f[1], order[f[0]]))


def _scan(batches, rules):
    kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))
    compiled: dict = {}
    seen: dict = {}  # repeated rows of one path and content meet in one task
    for batch in batches:
        for part in K.slices(batch, "text"):
            if len(seen) > SEEN:
                seen.clear()
            part = part.filter(pa.array([seen.setdefault(b, n) == n for n, b in enumerate(part.column(0).to_pylist(), len(seen) << 32)], pa.bool_()))
            found = [[dict(zip(("kind", "start", "end"), f)) for f in find(t or "", rules, compiled)] for t in part.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(found, kind)], ["blob", "findings"])


def scan(versions: DataFrame, ledger: str | None = None, rules=RULES) -> DataFrame:
    """``versions(doc_id, text, ...)`` → the same rows with blob and findings array<struct<kind,start,end>>.

    ``ledger`` is a folder of earlier runs (created when missing); without one the run has a ledger of its own.
    """
    spark = versions.sparkSession
    ship(spark)
    version = rule_version(rules)
    path = ledger or table_path(spark, "ledger")
    base = versions.select(F.col("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    named = base.withColumn("blob", F.sha2("text", 256)).withColumn("at", F.xxhash64(F.col("doc_id")))
    # one row stands for each blob; a task's copies are folded before the shuffle
    chosen = named.groupBy("blob").agg(F.min("at").alias("at"))
    old = _ledger(spark, path)
    if old is not None:
        chosen = chosen.join(old.where(F.col("rule_version") == version).select("blob"), "blob", "left_anti")
    texts = named.select("at", "blob", "text").join(chosen, ["at", "blob"], "left_semi").select("blob", "text")
    fresh = texts.mapInArrow(partial(_scan, rules=rules), "blob string, findings array<struct<kind:string,start:int,end:int>>").withColumn("rule_version", F.lit(version))
    fresh.write.mode("append").partitionBy("rule_version").parquet(path)
    known = _ledger(spark, path).where(F.col("rule_version") == version).dropDuplicates(["blob"]).select("blob", "findings")
    known = materialise(known, "findings")  # apart from the join, so that a blob with very many paths can be split there
    return versions.drop("findings").withColumn("blob", F.sha2(F.coalesce(F.col("text").cast("string"), F.lit("")), 256)).join(known, "blob")


def _ledger(spark, path: str) -> DataFrame | None:
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    p = jvm.org.apache.hadoop.fs.Path(path)
    if not p.getFileSystem(conf).exists(p):
        return None
    return spark.read.schema("blob string, findings array<struct<kind:string,start:int,end:int>>, rule_version string").parquet(path)


def digests(scanned: DataFrame) -> DataFrame:
    """doc_id, counts and digest of the base kinds, and all spans as text."""
    line = lambda a: F.array_join(F.transform(a, lambda f: F.concat_ws(":", f["kind"], f["start"].cast("string"), f["end"].cast("string"))), ",")
    count = lambda k: F.size(F.filter("findings", lambda f: f["kind"] == k)).cast("long").alias(f"n_{k}")
    base = F.filter("findings", lambda f: f["kind"].isin(*BASE))
    return scanned.select("doc_id", *[count(k) for k in BASE], F.sha2(line(base), 256).alias("base_sha256"), line("findings").alias("spans"))


def redact(scanned: DataFrame, mark: str = "[secret]") -> DataFrame:
    """``scanned`` with every span of ``text`` (spans that overlap count as one) replaced by ``mark``."""
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("parts"))

    def step(acc, f):
        cut = F.greatest(f["start"] - acc["at"], F.lit(0))
        kept = F.substring(F.col("text"), acc["at"] + 1, cut)
        fresh = f["start"] >= acc["at"]
        return F.struct(F.greatest(acc["at"], f["end"]).alias("at"), F.when(fresh, F.concat(acc["parts"], F.array(kept, F.lit(mark)))).otherwise(acc["parts"]).alias("parts"))

    body = F.aggregate("findings", start, step, lambda acc: F.concat(F.array_join(acc["parts"], ""), F.substring(F.col("text"), acc["at"] + 1, F.char_length("text"))))
    return scanned.withColumn("text", F.when(F.size("findings") == 0, F.col("text")).otherwise(body))
