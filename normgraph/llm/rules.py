"""Line-first cleaning with DataFrame functions only.

Every line is judged on its own (navigation, boilerplate, punctuation); failing lines go; a document that
loses too much of its text is rejected.  Nothing is exploded: all counts are array functions on the row, so no
row is shuffled and one very long text costs only its own length.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from normgraph.llm.common import prune

#: Fixed values of the base counts.
WORD_GAP = r"[\x20\x09-\x0D]+"
GAP_CHARS = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
WINDOW = 8


@dataclass(frozen=True)
class LineRules:
    """Limits of the line rules; all documented parameters."""

    boilerplate: tuple[str, ...] = (
        "cookie policy", "cookies", "all rights reserved", "terms of use", "terms of service", "privacy policy",
        "javascript", "lorem ipsum", "click here", "sign up", "log in", "subscribe to", "share this", "read more",
    )
    short_words: int = 12  # boilerplate phrases count only in lines of at most so many words
    min_pipes: int = 3  # navigation: so many separators in a line ...
    pipe_words: float = 0.25  # ... and that share of separators among its words
    symbol_share: float = 0.20  # punctuation: symbols for each character
    max_lost: float = 0.5  # share of word characters a kept document may lose


def _drop(c: Column, chars: str) -> Column:
    return F.translate(c, chars, "")


def _words(c: Column) -> Column:
    return F.filter(F.split(c, WORD_GAP), lambda w: w != "")


def _has_phrase(text: Column, rules: LineRules) -> Column:
    found = F.lit(False)
    for p in rules.boilerplate:
        found = found | F.lower(text).contains(p)
    return found


def line_fails(line: Column, rules: LineRules) -> Column:
    """Whether a line breaks a rule; a line without words never does."""
    bare = _drop(line, GAP_CHARS)
    n_chars = F.length(bare)
    n_words = F.size(_words(line))
    pipes = F.length(line) - F.length(_drop(line, "|"))
    symbols = F.length(line) - F.length(_drop(line, SYMBOLS))
    phrases = _has_phrase(line, rules)
    navigation = (pipes >= rules.min_pipes) & (pipes >= rules.pipe_words * n_words)
    punctuation = symbols > rules.symbol_share * n_chars
    return (n_chars > 0) & (navigation | punctuation | (phrases & (n_words <= rules.short_words)))


def _let(value: Column, body) -> Column:
    """Bind an array to a lambda variable: Catalyst would inline it into lambdas and compute it for every element."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _word_counts(words: Column) -> Column:
    """Number of words, and of words in 8-word windows that stand twice or more, the first finding included."""
    n = F.size(words)
    hashes = _let(
        F.transform(words, lambda w: F.xxhash64(w)),
        lambda coded: F.when(n >= WINDOW, F.transform(F.sequence(F.lit(0), n - WINDOW), lambda i: F.xxhash64(*[F.get(coded, i + k) for k in range(WINDOW)]))).otherwise(F.array().cast("array<bigint>")),
    )
    return _let(hashes, lambda h: F.struct(n.cast("long").alias("n_words"), F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(_covered(h)).cast("long").alias("n_repeat_words")))


def _covered(hashes: Column) -> Column:
    """Words under the windows whose hash stands twice or more."""
    ordered = F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    again = lambda p: F.filter(
        p, lambda x, i: ((i > 0) & (F.get(p, i - 1)["h"] == x["h"])) | F.coalesce(F.get(p, i + 1)["h"] == x["h"], F.lit(False))
    )
    starts = F.sort_array(F.transform(_let(ordered, again), lambda x: x["i"]))
    gaps = lambda at: F.transform(at, lambda p, i: F.coalesce(F.least(F.lit(WINDOW), F.get(at, i + 1) - p), F.lit(WINDOW)))
    return F.aggregate(_let(starts, gaps), F.lit(0), lambda a, g: a + g)


def score_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: LineRules = LineRules(), with_text: bool = True) -> DataFrame:
    """Base counts, verdict and, with ``with_text``, the cleaned text of every whole document.

    One row for each input row, repeated rows included.  A null text has no words and fails the base rules,
    as an empty one does.  ``clean_text`` keeps the order and the breaks of the remaining lines.  Extra columns
    are dropped.
    """
    text = F.coalesce(F.col(f"`{text_col}`"), F.lit(""))
    df = prune(docs, id_col, text_col).select(F.col(f"`{id_col}`"), text.alias("t"))
    counted = _let(_words(F.col("t")), _word_counts)
    df = df.select(f"`{id_col}`", "t", counted.alias("c"))
    df = df.select(f"`{id_col}`", "t", F.col("c.n_words").alias("n_words"), F.col("c.n_repeat_words").alias("n_repeat_words"))
    df = df.withColumn("lines", F.split("t", "\n", -1))
    with_words = F.filter("lines", lambda x: _drop(x, GAP_CHARS) != "")
    df = df.select(f"`{id_col}`", "t", "n_words", "n_repeat_words", "lines", with_words.alias("full"))
    # a text without any symbol or phrase has no failing line; most texts end here
    suspect = (F.length("t") > F.length(_drop(F.col("t"), SYMBOLS))) | _has_phrase(F.col("t"), rules)
    df = df.withColumn("kept_lines", F.when(suspect, F.filter("lines", lambda x: ~line_fails(x, rules))).otherwise(F.col("lines")))
    df = df.select(
        f"`{id_col}`",
        "n_words",
        F.length(_drop(F.col("t"), GAP_CHARS)).cast("long").alias("word_chars"),
        (F.length("t") - F.length(_drop(F.col("t"), SYMBOLS))).cast("long").alias("n_symbols"),
        (F.size("full") - F.size(F.array_distinct("full"))).cast("long").alias("n_dup_lines"),
        "n_repeat_words",
        (F.size("lines") - F.size("kept_lines")).cast("long").alias("n_lines_removed"),
        F.array_join("kept_lines", "\n").alias("clean_text"),
    )
    df = df.withColumn("clean_chars", F.length(_drop(F.col("clean_text"), GAP_CHARS)).cast("long"))
    failed = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    df = df.withColumn("base_failed", failed)
    df = df.withColumn("kept", ~failed & (F.col("clean_chars") >= (1 - rules.max_lost) * F.col("word_chars")))
    cols = [f"`{id_col}`", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_lines_removed", "clean_chars"]
    return df.select(*cols, *(["clean_text"] if with_text else []))
