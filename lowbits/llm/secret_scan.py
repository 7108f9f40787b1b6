"""Secret scans with corpus-wide ownership frequency (operator 10), DataFrame functions only.

Candidates are assignments to credential names, access-key ids and long hexadecimal runs.  Each distinct
candidate value is hashed and counted over the corpus by distinct repositories and owners: values that many
owners share are widely copied examples, values of one owner look live.  Here a document's owner is its
``source`` and its repository is (source, lang).

Edge cases: null or empty text has no candidates and keeps its row; null owner or repository counts as one
owner named by null; repeated rows count once per owner; spans are code points, end exclusive, ordered by
start and then kind.  Rows are told apart by id and text hash: a null doc_id keeps its figures, two texts under one id have
figures of their own.  An empty table gives an empty table.  Only needed columns are read, so extra ones can't clash.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .engine import same_row, stored

#: Kinds in order, their pattern, the group that is the value, its least length.
ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{14,}"
HEX = r"[0-9a-f]{16,}+"
ASSIGN_LEAST = 12
KINDS = ("assign", "access", "hex")
EXAMPLE_OWNERS, EXAMPLE_REPOSITORIES = 3, 5


def _spans(kind: int) -> F.Column:
    """array<struct<start, kind, end, value>> of all matches: the pieces between matches give the starts."""
    return F.expr(
        f"""aggregate(
            transform(m{kind}, (x, i) -> named_struct('m', x, 'v', v{kind}[i], 'gap', g{kind}[i])),
            cast(named_struct('at', 0, 'out', array()) as struct<at:int, out:array<struct<start:int,kind:int,end:int,value:string>>>),
            (s, x) -> named_struct('at', s.at + length(x.gap) + length(x.m),
                'out', concat(s.out, array(named_struct('start', s.at + length(x.gap), 'kind', {kind}, 'end', s.at + length(x.gap) + length(x.m), 'value', x.v)))),
            s -> s.out)"""
    )


def candidates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", owner_col: str = "source", repository_cols: tuple[str, ...] = ("source", "lang")) -> DataFrame:
    """doc_id, th (hash of the text), owner, repository, spans (struct start, kind, end, value), one row per row of docs."""
    none = F.expr("cast(array() as array<struct<start:int,kind:int,end:int,value:string>>)")
    d = docs.select(
        docs[id_col].cast("long").alias("doc_id"),
        docs[owner_col].cast("string").alias("owner"),
        F.concat_ws("/", *(F.coalesce(docs[c].cast("string"), F.lit("")) for c in repository_cols)).alias("repository"),
        F.coalesce(docs[text_col], F.lit("")).alias("text"),
        F.xxhash64(docs[text_col]).alias("th"),
    )
    kinds = list(enumerate(((ASSIGN, 2), (ACCESS, 0), (HEX, 0))))
    keys = ["doc_id", "th", "owner", "repository"]
    d = d.select(*keys, "text", *(F.col("text").rlike(p).alias(f"has{k}") for k, (p, _) in kinds))  # most texts hold no match of a kind
    parts = []
    for k, (p, group) in kinds:
        has, text, pattern = F.col(f"has{k}"), F.col("text"), F.lit(p)
        parts += [F.when(has, F.regexp_extract_all(text, pattern, F.lit(0))).alias(f"m{k}"), F.when(has, F.regexp_extract_all(text, pattern, F.lit(group))).alias(f"v{k}"), F.when(has, F.split(text, p, -1)).alias(f"g{k}")]
    d = d.select(*keys, *parts)
    d = d.select(*keys, *(F.coalesce(_spans(k), none).alias(f"f{k}") for k, _ in kinds))
    kept = F.filter("f0", lambda x: F.length(x["value"]) >= ASSIGN_LEAST)
    return d.select(*keys, F.array_sort(F.concat(kept, "f1", "f2")).alias("spans"))


def ownership(found: DataFrame, example_owners: int = EXAMPLE_OWNERS, example_repositories: int = EXAMPLE_REPOSITORIES) -> DataFrame:
    """value_hash, n_docs, n_owners, n_repositories, widely_copied: one row per distinct candidate value."""
    one = found.select("doc_id", "owner", "repository", F.explode(F.array_distinct(F.transform("spans", lambda x: F.sha2(x["value"], 256)))).alias("value_hash"))
    by_place = one.groupBy("value_hash", "owner", "repository").agg(F.count("*").alias("n_docs"))
    by_owner = by_place.groupBy("value_hash", "owner").agg(F.sum("n_docs").alias("n_docs"), F.count("*").alias("n_repositories"))
    out = by_owner.groupBy("value_hash").agg(F.sum("n_docs").alias("n_docs"), F.count("*").alias("n_owners"), F.sum("n_repositories").alias("n_repositories"))
    return out.withColumn("widely_copied", (F.col("n_owners") >= example_owners) | (F.col("n_repositories") >= example_repositories))


def scan(docs: DataFrame) -> DataFrame:
    """One row per document: counts and spans by kind, and how many of its distinct values look live or copied."""
    found = stored(candidates(docs), "candidates")  # read three times below; texts are scanned once
    some = found.where(F.size("spans") > 0)
    owned = stored(ownership(some), "owned")  # stored, so that Spark can split a value that a third of all rows hold
    values = some.select(F.col("doc_id").alias("d"), F.col("th").alias("t"), F.explode(F.array_distinct(F.transform("spans", lambda x: F.sha2(x["value"], 256)))).alias("value_hash")).distinct()
    verdict = values.join(owned, "value_hash").groupBy("d", "t").agg(F.count_if("widely_copied").alias("n_copied"), F.count_if(~F.col("widely_copied")).alias("n_live"), F.max("n_owners").alias("most_owners"))
    names = F.array(*(F.lit(k) for k in KINDS))
    text = F.array_join(F.transform("spans", lambda x: F.concat_ws(":", names[x["kind"]], x["start"].cast("string"), x["end"].cast("string"))), ",")
    count = lambda k: F.size(F.filter("spans", lambda x: x["kind"] == k)).cast("long")
    rows = found.select("doc_id", "th", *(count(k).alias(f"n_{n}") for k, n in enumerate(KINDS)), text.alias("listed"))
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    out = rows.join(verdict, same_row(), "left")
    return out.select("doc_id", "n_assign", "n_access", "n_hex", F.sha2("listed", 256).alias("base_sha256"), F.col("listed").alias("spans"), zero("n_live"), zero("n_copied"), zero("most_owners"))
