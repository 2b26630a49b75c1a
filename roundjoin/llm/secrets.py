"""Secret scans by an incremental blob ledger: every text version is addressed by its content, only pairs of blob and rule version that the
ledger lacks are scanned, and findings are joined back to all paths (documents) that hold the blob. DataFrame functions only.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import DOC_COLUMNS, cut, pick, spread_join


@dataclass(frozen=True)
class Rule:
    """A secret is a match of pattern (leftmost, not overlapping) whose group has at least least characters. probe: a cheap necessary pattern."""

    kind: str
    version: int
    pattern: str
    group: int
    least: int
    probe: str
    base: bool


_KEYWORD = r"(?i:(password|passwd|secret|token|api_?key))"
#: The base kinds in their order, then the kinds that the method adds. A run of hex digits is matched only where it is long enough,
#: which finds the same spans, as do access keys.
RULES = (
    Rule("assign", 1, _KEYWORD + r"[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", 2, 6, _KEYWORD + r"[\"']?\x20*[:=]", True),
    Rule("access", 1, r"AKIA[A-Z0-9]{16,}", 0, 20, r"AKIA", True),
    Rule("hex", 1, r"[0-9a-f]{24,}", 0, 24, r"[0-9a-f]{24}", True),
    Rule("pem", 2, r"-----BEGIN [A-Z ]*PRIVATE KEY-----(?:[A-Za-z0-9+/=:,\s-]*?-----END [A-Z ]*PRIVATE KEY-----)?", 0, 1, r"-----BEGIN ", False),
    Rule("jwt", 1, r"eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", 0, 1, r"eyJ", False),
    Rule("forge", 1, r"gh[pousr]_[A-Za-z0-9]{36,}", 0, 1, r"gh[pousr]_", False),
)
_SPANS = "array<struct<start:int,kind_no:int,kind:string,stop:int>>"
#: Spans that one step handles at a time. What a text costs grows with its spans times this, not with their square.
_BLOCK = 128


def _quoted(pattern: str) -> Column:
    return F.lit(pattern)


def _let(value: Column, use: Callable[[Column], Column]) -> Column:
    """use(value), with the value computed once."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _blocks(x: Column) -> Column:
    """An array cut into arrays of _BLOCK elements."""
    starts = F.when(F.size(x) > 0, F.sequence(F.lit(0), F.floor((F.size(x) - 1) / _BLOCK).cast("int"))).otherwise(F.array().cast("array<int>"))
    return F.transform(starts, lambda k: F.slice(x, k * _BLOCK + 1, F.lit(_BLOCK)))


def _before(values: Column, start: Column, combine: Callable[[Column, Column], Column]) -> Column:
    """For each value the combination of start and all values before it; short arrays only."""
    first = F.struct(start.alias("now"), F.array().cast("array<int>").alias("out"))
    return F.aggregate(values, first, lambda a, v: F.struct(combine(a["now"], v).alias("now"), F.concat(a["out"], F.array(a["now"])).alias("out")), lambda a: a["out"])


def running(values: Column, combine: Callable[[Column, Column], Column]) -> Column:
    """For each int of an array the combination of 0 and all before it, by two levels: within blocks, and over the blocks' totals."""

    def by_blocks(parts: Column) -> Column:
        starts = _before(F.transform(parts, lambda x: F.aggregate(x, F.lit(0), combine)), F.lit(0), combine)
        return F.flatten(F.transform(F.arrays_zip(parts.alias("part"), starts.alias("start")), lambda z: _before(z["part"], z["start"], combine)))

    return _let(_blocks(values), by_blocks)


def _sum(a: Column, b: Column) -> Column:
    return a + b


def _larger(a: Column, b: Column) -> Column:
    return F.greatest(a, b)


def rule_spans(text: Column, number: int, rule: Rule) -> Column:
    """Spans of one rule in code points: the matches, and the stretches between them, whose lengths give the offsets."""
    matches = F.regexp_extract_all(text, _quoted(rule.pattern), F.lit(0))
    values = F.regexp_extract_all(text, _quoted(rule.pattern), F.lit(rule.group)) if rule.group else matches
    gaps = F.split(text, rule.pattern, -1)
    steps = F.transform(
        F.arrays_zip(F.slice(gaps, F.lit(1), F.size(matches)).alias("gap"), matches.alias("hit"), values.alias("value")),
        lambda x: F.struct(F.length(x["gap"]).alias("gap"), F.length(x["hit"]).alias("hit"), F.length(x["value"]).alias("value")),
    )

    def spans(x: Column) -> Column:
        begins = running(F.transform(x, lambda y: y["gap"] + y["hit"]), _sum)

        def span(y: Column, begin: Column) -> Column:
            return F.struct((begin + y["gap"]).alias("start"), F.lit(number).alias("kind_no"), F.lit(rule.kind).alias("kind"), (begin + y["gap"] + y["hit"]).alias("stop"), y["value"].alias("value"))

        kept = F.filter(F.zip_with(x, begins, span), lambda z: z["value"] >= rule.least)
        return F.transform(kept, lambda z: F.struct(z["start"].alias("start"), z["kind_no"].alias("kind_no"), z["kind"].alias("kind"), z["stop"].alias("stop")))

    return F.when(text.rlike(rule.probe), _let(steps, spans)).otherwise(F.array().cast(_SPANS))


def scan(blobs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """blob, text, todo (array of kind:version) -> blob, kind, version, spans; a row for each pair asked for, also without findings."""
    per_rule = F.array(*[F.struct(F.lit(r.kind).alias("kind"), F.lit(r.version).alias("version"), rule_spans(F.col("text"), i, r).alias("spans"), F.array_contains("todo", f"{r.kind}:{r.version}").alias("asked")) for i, r in enumerate(rules)])
    return blobs.select("blob", F.explode(F.filter(per_rule, lambda x: x["asked"])).alias("f")).select("blob", "f.kind", "f.version", "f.spans")


def _versions(docs: DataFrame) -> DataFrame:
    rows = pick(docs, "doc_id", "text").select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return rows.withColumn("blob", F.sha2("text", 256))


def update_ledger(docs: DataFrame, ledger: DataFrame | None = None, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """New ledger rows (blob, kind, version, spans) for the pairs of blob and rule version that the ledger lacks. Append them to the stored ledger.

    ledger: blob, kind, version at least. Null texts count as the empty blob; equal texts are scanned once; an empty table gives no rows."""
    rows = _versions(docs)
    wanted = [f"{r.kind}:{r.version}" for r in rules]
    if ledger is None:
        blobs = rows.groupBy("blob").agg(F.first("text").alias("text")).withColumn("todo", F.array(*map(F.lit, wanted)))
    else:
        known = pick(ledger, "blob", "kind", "version").groupBy("blob").agg(F.collect_set(F.concat_ws(":", "kind", "version")).alias("known"))
        todo = F.array_except(F.array(*map(F.lit, wanted)), F.coalesce(F.col("known"), F.array().cast("array<string>")))
        due = rows.select("blob").distinct().join(known, "blob", "left").select("blob", todo.alias("todo")).where(F.size("todo") > 0)
        blobs = rows.groupBy("blob").agg(F.first("text").alias("text")).join(due, "blob")
    return scan(blobs, rules)


def _joined(spans: Column) -> Column:
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["stop"])))


def blob_findings(new: DataFrame) -> DataFrame:
    """blob, spans (sorted by start, then kind) of the blobs with findings. The group of a blob has one row per rule."""
    some = new.where(F.size("spans") > 0)
    return some.groupBy("blob").agg(F.array_sort(F.flatten(F.collect_list("spans"))).alias("found"))


def _to_paths(rows: DataFrame, new: DataFrame) -> DataFrame:
    """rows (doc_id and blob at least) with found, the spans of their blob, or null. A blob that many rows hold is split."""
    findings = blob_findings(new)
    groups = cut(rows.groupBy("blob").agg(F.count("*").alias("n")).join(findings, "blob"))
    return spread_join(rows, groups, "blob", "doc_id", "left")


def find_secrets(docs: DataFrame, ledger: DataFrame | None = None, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Per row of docs: doc_id, n_assign, n_access, n_hex, base_sha256, spans.

    ledger: findings of earlier runs with their spans; what it holds isn't scanned again. Null and empty texts have no findings; repeated rows have
    one row each; a null doc_id stays; an empty table gives no rows; other columns are ignored."""
    rows = _versions(docs).select("doc_id", "blob")
    new = update_ledger(docs, ledger, rules)
    if ledger is not None:
        new = new.unionByName(pick(ledger, "blob", "kind", "version", "spans").where(F.concat_ws(":", "kind", "version").isin([f"{r.kind}:{r.version}" for r in rules])))
    all_rows = _to_paths(rows, new).withColumn("found", F.coalesce("found", F.array().cast(_SPANS)))
    base = F.filter("found", lambda s: s["kind"].isin([r.kind for r in rules if r.base]))
    count = lambda kind: F.size(F.filter("found", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return all_rows.select("doc_id", count("assign"), count("access"), count("hex"), F.sha2(_joined(base), 256).alias("base_sha256"), _joined(F.col("found")).alias("spans"))


def redacted(text: Column, found: Column, mark: str = "[SECRET]") -> Column:
    """text with each stretch that spans (in order) cover replaced by mark; overlapping spans make one stretch.

    The text is cut into one piece for each block of spans first, so that finding a place in it doesn't begin at its start each time."""

    def whole(reach: Column) -> Column:
        spans = F.zip_with(found, reach, lambda x, at: F.struct(x["start"].alias("start"), x["stop"].alias("stop"), at.alias("at")))
        end = F.element_at(F.transform(F.slice(spans, -1, 1), lambda z: F.greatest(z["at"], z["stop"])), 1)

        def piece(block: Column) -> Column:
            low, high = block[0]["at"], F.element_at(block, -1)["start"]
            part = F.substring(text, low + 1, F.greatest(high - low, F.lit(0)))
            shown = lambda p: F.array_join(F.transform(block, lambda z: F.when(z["start"] >= z["at"], F.concat(F.substring(p, z["at"] - low + 1, z["start"] - z["at"]), F.lit(mark))).otherwise("")), "")
            return _let(part, shown)

        return F.concat(F.array_join(F.transform(_blocks(spans), piece), ""), F.substring(text, end + 1, F.length(text)))

    return F.when(F.size(found) > 0, _let(running(F.transform(found, lambda x: x["stop"]), _larger), whole)).otherwise(text)


def redact_secrets(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """All rows of docs with the columns of documents; secrets in their texts are replaced by a mark, and n_chars follows where text changed.

    Rows without findings (null texts too) stay as they are. Only rows that a rule's probe fits are addressed by content, scanned and joined."""
    body = pick(docs, *DOC_COLUMNS)
    probe = F.coalesce(F.lit(False), F.lit(False))
    for r in rules:
        probe = probe | F.coalesce(F.col("text").rlike(r.probe), F.lit(False))
    # written, so that the probes read each text twice only
    suspects = cut(body.where(probe).withColumn("__blob", F.sha2("text", 256)))
    new = update_ledger(suspects.select("doc_id", "text"), None, rules)
    joined = _to_paths(suspects.withColumnRenamed("__blob", "blob"), new).withColumnRenamed("found", "__found")
    text = F.when(F.col("__found").isNotNull(), redacted(F.col("text"), F.col("__found"))).otherwise(F.col("text"))
    changed = joined.withColumn("__text", text).select("doc_id", F.col("__text").alias("text"), "lang", "source", F.when(F.col("__found").isNotNull(), F.length("__text").cast("long")).otherwise(F.col("n_chars")).alias("n_chars"))
    return body.where(~probe).unionByName(changed)
