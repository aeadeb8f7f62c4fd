"""Stage 1: documents to traced sentences, with built-in functions only."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from normgraph.functions.pin import pin

ABBREVIATIONS = ("e.g", "i.e", "etc", "Mr", "Mrs", "Dr", "No", "Art", "Sec", "St")
_MARK = "\x1e"


@dataclass(frozen=True)
class SplitRules:
    bullets: bool = True  # list items are sentences of their own
    semicolon: bool = True
    wrap: bool = True  # a newline before a lower-case letter is a blank
    abbreviations: tuple[str, ...] = ABBREVIATIONS


def html_text(html: Column) -> Column:
    """Readable text of a page: without scripts, styles, navigation, advertisements, footers and tags."""
    out = html
    for tag in ("script", "style", "nav", "footer", "head"):
        out = F.regexp_replace(out, f"(?is)<{tag}[ >].*?</{tag}>|<{tag}>.*?</{tag}>", " ")
    out = F.regexp_replace(out, '(?is)<div class="ad">.*?</div>', " ")
    out = F.regexp_replace(out, "(?s)<!--.*?-->", " ")
    out = F.regexp_replace(out, "(?i)</p>|<br ?/?>|</h[1-6]>|</li>", "\n")
    out = F.regexp_replace(out, "<[^>]*>", "")
    for entity, char in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&amp;", "&")):
        out = F.regexp_replace(out, entity, char)
    return F.trim(F.regexp_replace(F.regexp_replace(out, "[ \t]+", " "), " *\n[ \n]*", "\n"))


def repeated_lines(df: DataFrame, id_col: str, text_col: str, min_repeat: int) -> DataFrame:
    """Digest and count of lines that stand in at least ``min_repeat`` documents (headers, footers, boilerplate)."""
    lines = df.select(id_col, F.explode(F.split(text_col, "\n")).alias("line")).select(id_col, F.trim("line").alias("line")).where("line <> ''")
    return lines.groupBy(F.md5("line").alias("digest")).agg(F.count_distinct(id_col).alias("n_docs"), F.count(F.lit(1)).alias("n_lines"), F.min("line").alias("line")).where(F.col("n_docs") >= min_repeat)


def strip_boilerplate(df: DataFrame, min_repeat: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Documents without repeated lines and page numbers; the join back is on line digests."""
    lines = df.select(id_col, F.posexplode(F.split(text_col, "\n")).alias("pos", "line"))
    lines = lines.where(~F.regexp_like(F.trim("line"), F.lit(r"^(page )?[0-9]{1,4}( of [0-9]{1,4})?$")))
    repeated = repeated_lines(df, id_col, text_col, min_repeat).select("digest")
    left = lines.withColumn("digest", F.md5(F.trim("line"))).join(repeated, "digest", "left_anti")
    return left.groupBy(id_col).agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "line"))), lambda x: x["line"]), "\n").alias(text_col))


def mark_boundaries(text: Column, rules: SplitRules = SplitRules()) -> Column:
    """Text with a separator at each sentence boundary (look-around in one pass each)."""
    out = text
    if rules.wrap:
        out = F.regexp_replace(out, "\n(?=[a-z])", " ")
    if rules.bullets:
        out = F.regexp_replace(out, r"\n(?=[ \t]*([-*]|[0-9]+[.)]|\([a-z]\)) )", _MARK)
    if rules.semicolon:
        out = F.regexp_replace(out, r";(?= *(and |or )?[^;.]*\b(must|shall|may)\b)", f";{_MARK}")
    guard = "".join(f"(?<!\\b{a.replace('.', chr(92) + '.')})" for a in rules.abbreviations)
    out = F.regexp_replace(out, rf"{guard}([.!?])\s+(?=[A-Z])", f"$1{_MARK}")
    return F.regexp_replace(out, "\n", _MARK)


def sentences(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: SplitRules = SplitRules()) -> DataFrame:
    """``(id, seq, text)``: policy-aware sentences."""
    parts = F.filter(F.split(mark_boundaries(F.col(text_col), rules), _MARK), lambda s: F.trim(s) != "")
    return df.select(id_col, F.posexplode(parts).alias("seq", "raw")).select(id_col, "seq", simplify(F.col("raw")).alias("text"))


def pieces(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """``(id, keep.., seq, raw)``: plain pieces between runs of ``. ! ?`` and line ends, blank ones left out."""
    parts = F.filter(F.split(F.col(text_col), "[.!?\n]+"), lambda s: F.trim(s) != "")
    return df.select(id_col, *keep, F.posexplode(parts).alias("seq", "raw"))


def with_spans(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id, seq, start, length, raw)``: line pieces with the place in the source (1-based characters)."""
    parts = F.split(F.col(text_col), "\n")
    zero = F.struct(F.lit(1).alias("at"), F.array().cast("array<struct<start:int,raw:string>>").alias("out"))
    placed = F.aggregate(parts, zero, lambda a, p: F.struct((a["at"] + F.length(p) + 1).alias("at"), F.concat(a["out"], F.array(F.struct(a["at"].alias("start"), p.alias("raw")))).alias("out")))["out"]
    flat = df.select(id_col, F.posexplode(placed).alias("seq", "p"))
    return flat.select(id_col, "seq", F.col("p.start").alias("start"), F.length("p.raw").alias("length"), F.col("p.raw").alias("raw"))


def simplify(col: Column) -> Column:
    """Join broken lines and squeeze blanks; words and their order stay."""
    return F.trim(F.regexp_replace(F.regexp_replace(col, r"[\r\n]+", " "), "[ \t]+", " "))


def tokens_preserved(raw: Column, simple: Column) -> Column:
    """Whether both have the same sequence of tokens."""
    split = lambda c: F.filter(F.split(c, r"\s+"), lambda t: t != "")
    return split(raw) == split(simple)


def count_cosine(a: Column, b: Column) -> Column:
    """Cosine of two texts' token counts."""
    tokens = lambda c: F.filter(F.split(F.lower(c), "[^a-z0-9]+"), lambda t: t != "")
    ta, tb = tokens(a), tokens(b)
    words = F.array_distinct(F.concat(ta, tb))
    count = lambda arr, w: F.size(F.filter(arr, lambda t: t == w)).cast("double")
    dot = F.aggregate(words, F.lit(0.0), lambda s, w: s + count(ta, w) * count(tb, w))
    na = F.aggregate(words, F.lit(0.0), lambda s, w: s + count(ta, w) * count(ta, w))
    nb = F.aggregate(words, F.lit(0.0), lambda s, w: s + count(tb, w) * count(tb, w))
    return F.when((na == 0) | (nb == 0), F.lit(0.0)).otherwise(dot / F.sqrt(na * nb))


def similarity_gate(df: DataFrame, raw_col: str, simple_col: str, threshold: float = 0.85) -> DataFrame:
    # equal token sequences need no counting
    tokens = lambda c: F.filter(F.split(F.lower(F.col(c)), "[^a-z0-9]+"), lambda t: t != "")
    df = pin(df, _a=tokens(raw_col), _b=tokens(simple_col))
    score = F.when((F.col("_a") == F.col("_b")) & (F.size("_a") > 0), F.lit(1.0)).otherwise(count_cosine(F.col(raw_col), F.col(simple_col)))
    return pin(df, similarity=score).drop("_a", "_b").withColumn("accepted", F.col("similarity") >= threshold)


def dual_gate(df: DataFrame, self_check: str = "self_check", accepted: str = "accepted") -> DataFrame:
    """Both the similarity and the proposer's own check must accept."""
    return df.withColumn("preserved", F.col(self_check) & F.col(accepted))
