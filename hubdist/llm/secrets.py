"""Secret scans over an incremental ledger of blobs, in DataFrame functions only.

Every version of every path is a blob, named by the digest of its text. The
ledger is a table of (blob, rules, found): which blob was scanned under which
versions of which rules, and what was found. A run scans only the pairs the ledger
lacks, appends them, and joins the findings back to all paths that hold the blob.
Copies are scanned once. A text in which no pattern occurs at all is told apart
where it is read, so that only digests and texts with a match travel.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from operator import or_

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.scratch import cut, exists, new_path
from .columns import own_names


@dataclass(frozen=True)
class Rule:
    """A kind of secret: matches of ``pattern`` whose ``group`` has ``least`` characters or more; every match holds one of the letters or words in ``holds``, which are sought first."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 1
    version: int = 1
    holds: tuple[str, ...] = ()

    @property
    def key(self) -> str:
        return f"{self.kind}@{self.version}"


#: Patterns of the base kinds, then of common key formats.
BASE = (
    Rule("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6, holds=("=", ":")),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 20, holds=("AKIA",)),
    Rule("hex", r"[0-9a-f]{24,}", 0, 24),
)
MORE = (
    Rule("pem", r"-----BEGIN [A-Z ]*PRIVATE KEY-----", 0, 1, holds=("-----BEGIN ",)),
    Rule("forge", r"gh[pousr]_[A-Za-z0-9]{36,}", 0, 40, holds=("gh",)),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", 0, 1, holds=("eyJ",)),
)
RULES = BASE + MORE
FOUND = "array<struct<rule:string,start:bigint,end:bigint>>"
LEDGER = f"blob binary, rules array<string>, found {FOUND}"


def blob_id(text: Column) -> Column:
    return F.unhex(F.sha2(F.coalesce(text, F.lit("")).cast("binary"), 256))


def occurs(text: Column, rules: tuple[Rule, ...]) -> Column:
    """Whether any pattern matches somewhere; null text: no."""
    return F.coalesce(reduce(or_, [one(text, r) for r in rules]), F.lit(False))


def one(text: Column, rule: Rule) -> Column:
    found = text.rlike(rule.pattern)
    return reduce(or_, [text.contains(w) for w in rule.holds]) & found if rule.holds else found


def scan(blobs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Findings (blob, rule, start, end) of ``blobs`` (blob, text, todo), one row each; todo: the rules to scan for.

    Starts and ends are code points, ends exclusive; matches of a kind are leftmost
    and do not overlap. The text between matches and the matches themselves give
    the places by running sums.
    """
    kinds = []
    for r in rules:
        p = F.lit(r.pattern)
        parts = F.arrays_zip(
            F.transform(F.split("text", r.pattern, -1), lambda x: F.length(x)).alias("gap"),
            F.transform(F.regexp_extract_all("text", p, F.lit(0)), lambda x: F.length(x)).alias("len"),
            F.transform(F.regexp_extract_all("text", p, F.lit(r.group)), lambda x: F.length(x)).alias("own"),
        )
        kinds.append(F.when(F.array_contains("todo", r.key) & one(F.col("text"), r), F.struct(F.lit(r.key).alias("rule"), F.lit(r.least).alias("least"), parts.alias("parts"))))
    hit = blobs.select("blob", F.explode(F.filter(F.array(*kinds), lambda x: x.isNotNull())).alias("k"))
    at = hit.select("blob", "k.rule", "k.least", F.posexplode("k.parts").alias("i", "p"))
    w = Window.partitionBy("blob", "rule").orderBy("i")
    end = F.sum(F.col("p.gap").cast("long") + F.coalesce(F.col("p.len"), F.lit(0))).over(w.rowsBetween(Window.unboundedPreceding, 0))
    at = at.withColumn("end", end).where("p.len is not null and p.own >= least")
    return at.select("blob", "rule", (F.col("end") - F.col("p.len")).alias("start"), "end")


def open_ledger(spark: SparkSession, path: str) -> DataFrame:
    """The ledger at ``path``; none there yet: an empty one."""
    return spark.read.schema(LEDGER).parquet(path) if exists(spark, path) else spark.createDataFrame([], LEDGER)


def update_ledger(versions: DataFrame, path: str, rules: tuple[Rule, ...] = RULES, text_col: str = "text") -> DataFrame:
    """Scan the (blob, rule version) pairs of ``versions`` that the ledger at ``path`` lacks, append them, and return the ledger.

    Null text is the empty blob. Nothing new: nothing is written.
    """
    spark = versions.sparkSession
    ledger = open_ledger(spark, path)
    rows = versions.select(blob_id(F.col(text_col)).alias("blob"), F.col(text_col).alias("text"))
    keys = F.array(*[F.lit(r.key) for r in rules])
    blobs = rows.select("blob").distinct()
    if exists(spark, path):
        seen = ledger.groupBy("blob").agg(F.array_distinct(F.flatten(F.collect_list("rules"))).alias("seen"))
        blobs = blobs.join(seen, "blob", "left").select("blob", F.array_except(keys, F.coalesce("seen", F.array().cast("array<string>"))).alias("todo")).where(F.size("todo") > 0)
    else:
        blobs = blobs.withColumn("todo", keys)
    texts = rows.where(occurs(F.col("text"), rules)).groupBy("blob").agg(F.first("text").alias("text"))
    found = scan(texts.join(blobs, "blob"), rules).groupBy("blob").agg(F.collect_list(F.struct("rule", "start", "end")).alias("found"))
    new = blobs.join(found, "blob", "left").select("blob", F.col("todo").alias("rules"), F.coalesce("found", F.array().cast(FOUND)).alias("found"))
    new.write.mode("append").parquet(path)
    return open_ledger(spark, path)


def findings(ledger: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(blob, spans) of blobs with findings under these rules; spans by start, then by kind as listed."""
    named = F.create_map(*[x for no, r in enumerate(rules) for x in (F.lit(r.key), F.struct(F.lit(no).alias("no"), F.lit(r.kind).alias("kind")))])
    one = ledger.where(F.size("found") > 0).select("blob", F.explode("found").alias("f")).withColumn("r", named[F.col("f.rule")]).where("r is not null")
    return one.groupBy("blob").agg(F.sort_array(F.collect_set(F.struct("f.start", "r.no", "r.kind", "f.end"))).alias("spans"))


def secrets(docs: DataFrame, rules: tuple[Rule, ...] = RULES, ledger: str | None = None) -> DataFrame:
    """(doc_id, blob, spans) of every row; no finding: an empty list. Null text is empty; null ids and repeated rows stay as they are.

    ``ledger``: the folder of a ledger kept between runs; none: one is begun for this run.
    """
    found = cut(findings(update_ledger(docs, ledger or new_path(docs.sparkSession, "ledger"), rules), rules), "findings")
    at = docs.select(F.col("doc_id").cast("long").alias("doc_id"), blob_id(F.col("text")).alias("blob"))
    none = F.array().cast("array<struct<start:bigint,no:int,kind:string,end:bigint>>")
    return at.join(found, "blob", "left").select("doc_id", F.lower(F.hex("blob")).alias("blob"), F.coalesce("spans", none).alias("spans"))


def redact(docs: DataFrame, mark: str = "[secret]", rules: tuple[Rule, ...] = RULES, ledger: str | None = None) -> DataFrame:
    """Documents with each run of overlapping findings replaced by ``mark``; texts without findings stay, and so do all columns. Only rows in which a pattern occurs meet the findings."""
    blob, spans = own_names(docs, 2)
    found = cut(findings(update_ledger(docs, ledger or new_path(docs.sparkSession, "ledger"), rules), rules), "findings")
    found = found.select(F.col("blob").alias(blob), F.col("spans").alias(spans))
    some = occurs(F.col("text"), rules)
    out = docs.where(some).join(found, blob_id(F.col("text")) == F.col(blob), "left")
    start = F.struct(F.lit(0).cast("long").alias("pos"), F.lit("").alias("out"))

    def step(acc: Column, s: Column) -> Column:
        return F.when(s.end <= acc.pos, acc).otherwise(
            F.struct(
                s.end.alias("pos"),
                F.when(s.start < acc.pos, acc.out).otherwise(F.concat(acc.out, F.expr("text").substr(acc.pos.cast("int") + 1, (s.start - acc.pos).cast("int")), F.lit(mark))).alias("out"),
            )
        )

    clean = F.aggregate(spans, start, step, lambda acc: F.concat(acc.out, F.expr("text").substr(acc.pos.cast("int") + 1, F.lit(2**31 - 1))))
    changed = {"text": F.when(F.col(spans).isNull(), F.col("text")).otherwise(clean)}
    if "n_chars" in docs.columns:
        changed["n_chars"] = F.when(F.col(spans).isNull(), F.col("n_chars")).otherwise(F.length(changed["text"]).cast(docs.schema["n_chars"].dataType))
    return docs.where(~some).unionByName(out.withColumns(changed).select(*docs.columns))


def digest(found: DataFrame) -> DataFrame:
    """The contract's columns from ``secrets``."""
    base = F.filter("spans", lambda s: s.no < len(BASE))
    joined = lambda a: F.array_join(F.transform(a, lambda s: F.concat_ws(":", s.kind, s.start.cast("string"), s.end.cast("string"))), ",")
    of = lambda k: F.size(F.filter("spans", lambda s: s.no == k)).cast("long")
    counts = [of(k).alias(f"n_{r.kind}") for k, r in enumerate(BASE)]
    return found.select("doc_id", *counts, F.sha2(joined(base).cast("binary"), 256).alias("base_sha256"), joined(F.col("spans")).alias("spans"))


def digest_sql(rules: tuple[Rule, ...] = RULES) -> str:
    """The same result for DuckDB, from the texts alone."""
    quoted = lambda p: "'" + p.replace("'", "''") + "'"
    either = lambda w: "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in w)
    arms = []
    for no, r in enumerate(rules):
        p = r.pattern.replace("(?i:password|passwd|secret|token|api_?key)", "|".join(map(either, ("password", "passwd", "secret", "token", "api_?key"))))
        arms.append(
            f"select id, {no} no, '{r.kind}' kind, {r.least} least, unnest(generate_series(1, len(m))) i, m, g, s from (select id, "
            f"list_transform(regexp_extract_all(text, {quoted(p)}), lambda x: length(x)) m, list_transform(regexp_extract_all(text, {quoted(p)}, {r.group}), lambda x: length(x)) g, "
            f"list_transform(string_split_regex(text, {quoted(p)}), lambda x: length(x)) s from t)"
        )
    return (
        "with t as (select row_number() over () id, doc_id, coalesce(text, '') as text from documents), a as (" + " union all ".join(arms) + "), "
        "f as (select id, no, kind, (list_sum(s[1:i]) + coalesce(list_sum(m[1:i-1]), 0))::bigint b, m[i]::bigint n from a where g[i] >= least), "
        "h as (select id, count(*) filter (no = 0) n_assign, count(*) filter (no = 1) n_access, count(*) filter (no = 2) n_hex, "
        f"string_agg(kind || ':' || b || ':' || (b + n), ',' order by b, no) filter (no < {len(BASE)}) base, string_agg(kind || ':' || b || ':' || (b + n), ',' order by b, no) spans from f group by id) "
        "select doc_id::bigint doc_id, coalesce(n_assign, 0)::bigint n_assign, coalesce(n_access, 0)::bigint n_access, coalesce(n_hex, 0)::bigint n_hex, sha256(coalesce(base, '')) base_sha256, coalesce(spans, '') spans from t left join h using (id)"
    )
