"""Incremental secret scanning over a ledger of content-addressed blobs.

Every version of every path is reduced to the SHA-256 of its text. A ledger holds the pairs of blob and
rule version that were scanned before; only unseen pairs are scanned, each once, and what was found is
joined back to every path that holds the blob. All of it is SQL expressions.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from approxboot.llm.common import table, written


def _either_case(word: str) -> str:
    return "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in word)


@dataclass(frozen=True)
class Rule:
    """kind, version, pattern; the group that must have min_length characters; base rules count for base_sha256."""

    kind: str
    version: int
    pattern: str
    group: int = 0
    min_length: int = 1
    base: bool = False


# Patterns of the secrets to be found, in the order in which kinds are listed.
KEYWORDS = ["password", "passwd", "secret", "token"]
RULES = [
    Rule("assign", 1, "(" + "|".join([*map(_either_case, KEYWORDS), _either_case("api") + "_?" + _either_case("key")]) + r""")["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6, True),
    Rule("access", 1, "AKIA[A-Z0-9]+", 0, 20, True),
    Rule("hex", 1, "[0-9a-f]+", 0, 24, True),
    Rule("pem", 1, "-----BEGIN [A-Z ]*PRIVATE KEY-----"),
    Rule("forge", 1, "gh[opsur]_[A-Za-z0-9]+", 0, 40),
]

SPAN = "struct<start:int,rank:int,kind:string,end:int>"


def _screen(rule: Rule) -> str:
    """A pattern that is found wherever the rule has a match that is long enough; cheaper than all matches."""
    if rule.kind == "hex":
        return f"[0-9a-f]{{{rule.min_length}}}"
    return rule.pattern


def rule_spans(text: Column, rule: Rule, rank: int) -> Column:
    """Spans of a rule's leftmost non-overlapping matches in text: matches alternate with what split() leaves between."""
    whole = F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(0))
    group = F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(rule.group)) if rule.group else whole
    gaps = F.split(text, rule.pattern, -1)
    steps = F.arrays_zip(whole.alias("w"), group.alias("g"), F.slice(gaps, 1, F.size(whole)).alias("s"))
    walk = F.aggregate(
        steps,
        F.struct(F.lit(0).alias("at"), F.lit(None).cast(f"array<{SPAN}>").alias("out")),
        lambda acc, x: F.struct(
            (acc["at"] + F.length(x["s"]) + F.length(x["w"])).alias("at"),
            F.when(
                F.length(x["g"]) >= rule.min_length,
                F.concat(
                    F.coalesce(acc["out"], F.array().cast(f"array<{SPAN}>")),
                    F.array(F.struct((acc["at"] + F.length(x["s"])).alias("start"), F.lit(rank).alias("rank"), F.lit(rule.kind).alias("kind"), (acc["at"] + F.length(x["s"]) + F.length(x["w"])).alias("end"))),
                ),
            ).otherwise(acc["out"]).alias("out"),
        ),
        lambda acc: acc["out"],
    )
    return F.when(text.rlike(_screen(rule)), walk)


def blob_id(text: Column) -> Column:
    return F.unhex(F.sha2(F.coalesce(text, F.lit("")), 256))


def unseen(blobs: DataFrame, rules: list[Rule], ledger: DataFrame | None) -> DataFrame:
    """Blobs with the array todo of ranks of those rules that the ledger (blob, kind, version) lacks for them."""
    every = F.array(*[F.lit(i) for i in range(len(rules))])
    if ledger is None:
        return blobs.withColumn("todo", every)
    spark = blobs.sparkSession
    named = spark.createDataFrame([(r.kind, r.version, i) for i, r in enumerate(rules)], "kind string, version int, rank int")
    done = ledger.join(F.broadcast(named), ["kind", "version"]).groupBy("blob").agg(F.collect_set("rank").alias("done"))
    left = blobs.join(done, "blob", "left")
    return left.withColumn("todo", F.array_except(every, F.coalesce("done", F.array().cast("array<int>")))).drop("done").where(F.size("todo") > 0)


def scan(versions: DataFrame, rules: list[Rule] | None = None, ledger: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Scan the distinct texts of versions (column text) under rules, less what ledger has.

    Returns findings (blob, spans) of blobs that have any, and the pairs (blob, kind, version) to add to
    the ledger. A null text is the empty text; equal texts are scanned once, however many rows hold them.
    """
    rules = RULES if rules is None else rules
    blobs = versions.select(blob_id(F.col("text")).alias("blob"), F.coalesce("text", F.lit("")).alias("text"))
    blobs = blobs.groupBy("blob").agg(F.first("text").alias("text"))
    todo = unseen(blobs, rules, ledger)
    found = [F.when(F.array_contains("todo", i), rule_spans(F.col("text"), r, i)) for i, r in enumerate(rules)]
    none = F.array().cast(f"array<{SPAN}>")
    scanned = todo.select("blob", F.array_sort(F.concat(*[F.coalesce(x, none) for x in found])).alias("spans"))
    pairs = todo.select("blob", F.explode("todo").alias("rank"))
    names = F.array(*[F.struct(F.lit(r.kind).alias("kind"), F.lit(r.version).alias("version")) for r in rules])
    pairs = pairs.select("blob", names[F.col("rank")].alias("r")).select("blob", "r.kind", "r.version")
    # few blobs have findings: written, they meet all paths in a join whose large keys Spark can split
    return written(scanned.where(F.size("spans") > 0), "secret-findings"), pairs


def merge_findings(old: DataFrame | None, new: DataFrame) -> DataFrame:
    """Findings of blobs from earlier runs and this one, one row for each blob."""
    if old is None:
        return new
    return old.unionByName(new).groupBy("blob").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("spans")))).alias("spans"))


def span_text(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def _is(kind: str):
    return lambda s: s["kind"] == kind


def findings_by_path(versions: DataFrame, findings: DataFrame, keep: list[str], rules: list[Rule] | None = None) -> DataFrame:
    """One row for each row of versions, with the columns keep, counts by base kind, base_sha256 and spans.

    Rows without a finding get zero counts and an empty list. Rows of one blob may be a large part of all
    rows: the join is a plain equi-join whose large keys Spark splits.
    """
    rules = RULES if rules is None else rules
    base = [r.kind for r in rules if r.base]
    only = F.filter("spans", lambda s: s["kind"].isin(base))
    facts = findings.select("blob", *[F.size(F.filter("spans", _is(k))).cast("long").alias(f"n_{k}") for k in base], F.sha2(span_text(only), 256).alias("base_sha256"), span_text(F.col("spans")).alias("spans"))
    paths = versions.select(*keep, blob_id(F.col("text")).alias("blob"))
    out = paths.join(facts, "blob", "left")
    zero = F.sha2(F.lit(""), 256)
    return out.select(*keep, *[F.coalesce(f"n_{k}", F.lit(0).cast("long")).alias(f"n_{k}") for k in base], F.coalesce("base_sha256", zero).alias("base_sha256"), F.coalesce("spans", F.lit("")).alias("spans"))


def masked(docs: DataFrame, findings: DataFrame, mark: str = "[secret]") -> DataFrame:
    """docs with mark in place of every span found in text; spans that overlap are masked as one."""

    def step(acc, s):
        piece = F.concat(acc["out"], F.substring(F.col("text"), acc["at"] + 1, s["start"] - acc["at"]), F.lit(mark))
        after = F.struct(s["end"].alias("at"), piece.alias("out"))
        inside = F.struct(F.greatest(acc["at"], s["end"]).alias("at"), acc["out"].alias("out"))
        return F.when(s["start"] >= acc["at"], after).otherwise(inside)

    begin = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))
    text = F.aggregate("__masked_spans", begin, step, lambda acc: F.concat(acc["out"], F.substring(F.col("text"), acc["at"] + 1, F.length("text"))))
    found = findings.select(F.col("blob").alias("__masked_blob"), F.col("spans").alias("__masked_spans"))
    keyed = docs.withColumn("__blob_of_text", blob_id(F.col("text")))
    joined = keyed.join(found, F.col("__blob_of_text") == F.col("__masked_blob"), "left")
    return joined.withColumn("text", F.when(F.col("__masked_spans").isNull(), F.col("text")).otherwise(text)).select(docs.columns)


def op1_secret_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Secrets of all documents. A null text is empty and has none; repeated rows and equal texts each get the findings of their blob."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    findings, _ = scan(docs)
    return findings_by_path(docs, findings, ["doc_id"])


def _oracle() -> str:
    parts = []
    for rank, r in enumerate(RULES):
        pattern = r.pattern.replace("'", "''")
        parts.append(
            f"select doc_id, {rank} as rank, '{r.kind}' as kind, {str(r.base).lower()} as base, {r.min_length} as least, "
            f"regexp_extract_all(t, '{pattern}') as w, regexp_extract_all(t, '{pattern}', {r.group}) as g, regexp_split_to_array(t, '{pattern}') as s from d"
        )
    return f"""
with d as (select doc_id, coalesce(text, '') as t from documents),
m as ({" union all ".join(parts)}),
x as (select doc_id, rank, kind, base, least, g, w, s, unnest(range(1, len(w) + 1)) as i from m where len(w) > 0),
p as (select doc_id, rank, kind, base, least, length(g[i]) as n,
             list_sum(list_transform(s[1:i], lambda y: length(y)))::bigint + coalesce(list_sum(list_transform(w[1:i-1], lambda y: length(y))), 0)::bigint as start, length(w[i]) as size from x),
f as (select *, kind || ':' || start || ':' || (start + size) as span from p where n >= least),
a as (select doc_id, count(*) filter (kind = 'assign') as n_assign, count(*) filter (kind = 'access') as n_access, count(*) filter (kind = 'hex') as n_hex,
             string_agg(span, ',' order by start, rank) filter (base) as b, string_agg(span, ',' order by start, rank) as spans from f group by doc_id)
select d.doc_id, coalesce(n_assign, 0)::bigint as n_assign, coalesce(n_access, 0)::bigint as n_access, coalesce(n_hex, 0)::bigint as n_hex,
       sha256(coalesce(b, '')) as base_sha256, coalesce(spans, '') as spans
from d left join a on d.doc_id is not distinct from a.doc_id"""


QUERIES = {"op1_secret_ledger": op1_secret_ledger}
ORACLES = {"op1_secret_ledger": _oracle()}
