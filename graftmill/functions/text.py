"""Text building blocks as column expressions."""

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Patterns of personal data, applied in this order; each match becomes <name>.
PATTERNS = {
    "mail": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+[.][A-Za-z]{2,}",
    "ip": r"[0-9]{1,3}(?:[.][0-9]{1,3}){3}",
    "card": r"[0-9]{16}",
    "phone": r"[+][0-9]{1,3}[ -][0-9]{2,4}[ -][0-9]{3,4}",
    "token": r"[A-Za-z0-9_-]{32,}",
}
ACCENTS = ("áàâäãåéèêëíìîïóòôöõúùûüñç", "aaaaaaeeeeiiiiooooouuuunc")


def clean_text(col: Column, *, lower: bool = False) -> Column:
    """White space collapsed and trimmed."""
    out = F.trim(F.regexp_replace(col, r"[ \t\r\n]+", " "))
    return F.lower(out) if lower else out


def deidentify(df: DataFrame, col: str, *, patterns: dict[str, str] = PATTERNS) -> DataFrame:
    """``masked`` text and one count for each pattern, in one projection chain."""
    cur = F.coalesce(F.col(col), F.lit(""))
    counts = []
    for name, pattern in patterns.items():
        counts.append(F.regexp_count(cur, F.lit(pattern)).cast("long").alias(f"n_{name}"))
        cur = F.regexp_replace(cur, pattern, f"<{name}>")
    return df.select("*", cur.alias("masked"), *counts)


def words(col: Column) -> Column:
    """Lower-cased white-space separated words."""
    return F.filter(F.split(F.lower(F.coalesce(col, F.lit(""))), r"[ \t\r\n]+"), lambda x: x != "")


def chars(col: Column) -> Column:
    return F.split(F.coalesce(col, F.lit("")), "")


def ngrams(items: Column, n: int, sep: str = " ") -> Column:
    """All runs of n items joined by sep; empty if there are fewer.

    The outer lambda binds the items, which would else be computed anew for every run.
    """

    def runs(w: Column) -> Column:
        last = F.size(w) - n + 1
        made = F.transform(F.sequence(F.lit(1), F.greatest(last, F.lit(1))), lambda i: F.array_join(F.slice(w, i, n), sep))
        return F.when(last < 1, F.array().cast("array<string>")).otherwise(made)

    return F.element_at(F.transform(F.array(items), runs), 1)


def normalize_entity(col: Column) -> Column:
    """Lower case, accents off, outer marks off, a plural s off words of four letters or more."""
    plain = F.translate(F.lower(F.trim(col)), *ACCENTS)
    return F.regexp_replace(F.regexp_replace(plain, r"^[^a-z0-9]+|[^a-z0-9]+$", ""), r"^(.{3,}[^s])s$", "$1")


def sentence_array(col: Column) -> Column:
    """Runs between . ! ? and line ends, trimmed, blanks dropped."""
    return F.filter(F.transform(F.split(F.coalesce(col, F.lit("")), r"[.!?\n]+"), lambda x: F.trim(x)), lambda x: x != "")


def sentences(docs: DataFrame, *, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, sent_no (from 0), sent, n_tok."""
    out = docs.select(key, F.posexplode(sentence_array(F.col(text))).alias("sent_no", "sent"))
    return out.withColumn("n_tok", F.size(F.filter(F.split("sent", " +"), lambda x: x != "")).cast("long"))
