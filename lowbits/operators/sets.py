"""Set builders: every result is (set_id, elem), distinct."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import to_domain


def tokens(text: Column | str) -> Column:
    """Lower-cased runs of letters and digits."""
    return F.filter(F.split(F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", " "), " "), lambda x: x != "")


def shingle_array(toks: Column, w: int, sep: str = " ") -> Column:
    """All runs of w tokens, joined by sep, distinct; null where there are fewer.

    The tokens are bound to a lambda variable, so they are computed once, however the optimizer merges projections;
    runs come from w shifted copies zipped, as a slice per run would copy the array each time."""

    def runs(t: Column) -> Column:
        n = F.size(t) - w + 1
        shifted = F.arrays_zip(*(F.slice(t, i + 1, n) for i in range(w)))
        return F.when(n > 0, F.array_distinct(F.transform(shifted, lambda x: F.concat_ws(sep, *(x[str(i)] for i in range(w))))))

    return F.element_at(F.transform(F.array(toks), runs), 1)


def shingles(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", w: int = 5, unit: str = "word", bits: int = 31) -> DataFrame:
    """w-shingles of words or characters, hashed.  Distinct inside the row first, so little is left to shuffle."""
    if unit == "word":
        runs = shingle_array(tokens(text_col), w)
    elif unit == "char":
        runs = shingle_array(F.split(F.regexp_replace(F.lower(text_col), r"[^\p{L}\p{N}]+", " "), ""), w, "")
    else:
        raise ValueError(unit)
    base = docs.select(F.col(id_col).alias("set_id"), F.explode(runs).alias("s"))
    # dealt by set alone: what groups by set or by set and element afterwards needs no second shuffle
    return base.select("set_id", to_domain(F.col("s"), bits).alias("elem")).repartition("set_id").distinct()


def shingle_lists(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", w: int = 5, bits: int = 31) -> DataFrame:
    """(set_id, elems): as shingles of words, but each set is one array, where an element may be repeated.

    Rows are shuffled only if an id occurs in several of them; null ids, which pair with nothing, are left out."""
    named = docs.where(F.col(id_col).isNotNull())
    each = named.select(F.col(id_col).alias("set_id"), F.transform(shingle_array(tokens(text_col), w), lambda s: to_domain(s, bits)).alias("elems"))
    if named.groupBy(id_col).count().where("count > 1").isEmpty():
        return each
    return each.groupBy("set_id").agg(F.flatten(F.collect_list("elems")).alias("elems"))  # of one set


def postings(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_df: int = 1, top_n: int | None = None) -> DataFrame:
    """(set_id = word, elem = document): the documents each word occurs in."""
    rows = docs.select(F.col(id_col).alias("elem"), F.explode(F.array_distinct(tokens(text_col))).alias("set_id"))
    if min_df <= 1 and top_n is None:
        return rows.select("set_id", "elem")
    df = rows.groupBy("set_id").agg(F.count("*").alias("df")).where(F.col("df") >= min_df)
    if top_n is not None:
        df = df.orderBy(F.desc("df"), "set_id").limit(top_n)
    return rows.join(df.select("set_id"), "set_id", "left_semi").select("set_id", "elem")


def baskets(df: DataFrame, set_col: str, elem_col: str) -> DataFrame:
    """Sets out of any two columns: parts per supplier, users per day, and so on."""
    return df.select(F.col(set_col).alias("set_id"), F.col(elem_col).alias("elem")).where("set_id is not null and elem is not null").distinct()


def strip_tags(html: Column | str) -> Column:
    """Text of a page: scripts, styles and tags go."""
    no_code = F.regexp_replace(html, r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " ")
    return F.regexp_replace(no_code, r"<[^>]*>", " ")


def top_coordinates(df: DataFrame, id_col: str, vector_col: str, m: int) -> DataFrame:
    """The indices of a vector's m greatest coordinates, ties to the lower index."""
    pairs = F.transform(F.col(vector_col), lambda x, i: F.struct((-x.cast("double")).alias("x"), i.alias("i")))
    return df.select(F.col(id_col).alias("set_id"), F.explode(F.transform(F.slice(F.array_sort(pairs), 1, m), lambda p: p["i"].cast("long"))).alias("elem"))


def sizes(sets: DataFrame) -> DataFrame:
    return sets.groupBy("set_id").agg(F.count("*").alias("f"))
