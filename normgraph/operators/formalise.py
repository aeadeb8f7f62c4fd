"""Stage 3: classified sentences to deontic formulas, with validation, one retry and a fallback taxonomy."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from normgraph.functions.pin import pin

CUE = "(must not|shall not|may not|shall be entitled to|is permitted to|is prohibited from|must|shall|may)"
PLACEHOLDERS = ("", "predicate", "action", "thing")
#: Fallback categories in the order of precedence of ours, with the printed counts.
FALLBACKS = (("bulleted", 10), ("multi_modal", 3), ("very_long", 14), ("multi_clause", 14), ("compound", 28), ("misc", 23))
SIGNATURES = ("predicate", "set", "function", "lambda", "closure", "meta")


def n_words(text: Column) -> Column:
    return F.size(F.filter(F.split(text, r"\s+"), lambda w: w != ""))


def categorise(text: Column) -> Column:
    """First structure that keeps a sentence from the plain pattern; null for none."""
    t = F.concat(F.lit(" "), F.regexp_replace(F.lower(text), "[^a-z]+", " "), F.lit(" "))
    modals = F.regexp_count(t, F.lit(" (must|shall|may)(?= )"))
    negations = F.regexp_count(t, F.lit(" (not|never)(?= )"))
    subordinators = F.regexp_count(t, F.lit(" (if|when|because|unless|although|while)(?= )"))
    return (
        F.when(F.regexp_like(text, F.lit("\n *[-*] ")), F.lit("bulleted"))
        .when((modals >= 2) | (negations >= 2), F.lit("multi_modal"))
        .when(n_words(text) >= 60, F.lit("very_long"))
        .when(subordinators >= 2, F.lit("multi_clause"))
        .when(F.regexp_like(t, F.lit(" (must|shall|may) .* (and|or) ")), F.lit("compound"))
    )


def verb_phrase(text: Column) -> Column:
    """Up to three words after the cue, cut at a preposition."""
    raw = F.regexp_extract(F.lower(text), CUE + " ([a-z]+( [a-z]+){0,2})", 2)
    return F.regexp_replace(raw, " (on|under|with|for|in|of|to|and|or|together|that|next)( .*)?$", "")


def camel(phrase: Column) -> Column:
    words = F.split(phrase, " ")
    return F.concat(F.get(words, F.lit(0)), F.array_join(F.transform(F.slice(words, 2, 8), lambda w: F.initcap(w)), ""))


def subject_class(text: Column) -> Column:
    """First known noun, as a class name; null without any."""
    return F.nullif(F.initcap(F.regexp_extract(F.lower(text), "(customer|order|supplier|controller|processor|subject)", 1)), F.lit(""))


def lift(df: DataFrame, attempt: int = 0) -> DataFrame:
    """``(sent_id, op, quant, var, cls, pred, exception_of, formula, diagnostics, ok, attempt)``.

    Attempt 0 takes the plain pattern only; attempt 1, made with the diagnostics of the first, also takes the first
    verb phrase of a compound sentence.
    """
    text = F.col("text")
    df = pin(df, category=categorise(text), _phrase=verb_phrase(text))
    category = F.col("category")
    pred = camel(F.col("_phrase"))
    quant = F.when(F.regexp_like(F.lower(text), F.lit("^(at least one|some) ")), F.lit("exists")).otherwise(F.lit("forall"))
    cls = subject_class(text)
    blocking = category.isNotNull() if attempt == 0 else category.isNotNull() & (category != "compound")
    out = pin(df, cls=cls, pred=pred).select(
        "sent_id", F.col("label").alias("op"), quant.alias("quant"), F.lit("x").alias("var"), "cls", "pred",
        F.when(F.regexp_like(F.lower(text), F.lit(" (waive|exempt|except|unless) ")), F.lit("base")).alias("exception_of"), "text", "category", blocking.alias("blocking"),
    )
    diagnostics = F.filter(
        F.array(
            F.when(~F.col("op").isin("O", "P", "F"), F.lit("no_op")),
            F.when(F.col("cls").isNull(), F.lit("empty_class")),
            F.when(F.col("pred").isin(*PLACEHOLDERS) | (F.length("pred") < 2), F.lit("placeholder")),
            F.when(F.col("blocking"), F.concat(F.lit("structure:"), F.col("category"))),
        ),
        lambda d: d.isNotNull(),
    )
    out = pin(out, diagnostics=diagnostics).withColumn("ok", F.size("diagnostics") == 0).withColumn("attempt", F.lit(attempt))
    return out.withColumn("formula", F.when(F.col("ok"), to_text(F.col("quant"), F.col("cls"), F.col("op"), F.col("pred")))).drop("blocking")


def retry(first: DataFrame) -> DataFrame:
    """Formulas after one bounded retry of those that failed; rows that passed are not touched.

    A failed row has all that the second attempt needs, so nothing is joined.
    """
    failed = first.where("not ok").select("sent_id", "text", F.col("op").alias("label"))
    return first.where("ok").unionByName(lift(failed, 1))


def to_text(quant: Column, cls: Column, op: Column, pred: Column) -> Column:
    return F.concat(quant, F.lit(" x. "), cls, F.lit("(x) -> "), op, F.lit("("), pred, F.lit("(x))"))


def normalise_op(op: Column, negated: Column) -> tuple[Column, Column]:
    """O of a negated body is F of the body, and the other way round; (operator, still negated)."""
    flipped = negated & op.isin("O", "F")
    return F.when(flipped, F.when(op == "O", F.lit("F")).otherwise(F.lit("O"))).otherwise(op), negated & ~flipped


def derive_permissions(formulas: DataFrame) -> DataFrame:
    """What is obligatory is permitted: one derived permission for each obligation's class and predicate."""
    return formulas.where("ok and op = 'O'").select("cls", "pred").distinct().withColumn("op", F.lit("P"))


def conflicts(formulas: DataFrame) -> DataFrame:
    """Classes and predicates both obligatory and forbidden; an aggregate, not a self-join."""
    g = formulas.where("ok and op in ('O', 'F')").groupBy("cls", "pred").agg(F.count_if(F.col("op") == "O").alias("n_obliged"), F.count_if(F.col("op") == "F").alias("n_forbidden"))
    return g.where("n_obliged > 0 and n_forbidden > 0")


def signatures(text: Column) -> dict[str, Column]:
    """One flag for each higher-order construct."""
    t = F.lower(text)
    like = lambda p: F.regexp_like(t, F.lit(p))
    return {
        "ho_predicate": like("every (property|predicate|relation) that|for all predicates"),
        "ho_set": like("any (set|collection|subset) of|\\{[a-z] ?\\|"),
        "ho_function": like("every function [a-z]|[^a-z][fgh]\\([a-z]\\)"),
        "ho_lambda": like("lambda|λ"),
        "ho_closure": like("transitively|recursively|directly or indirectly"),
        "ho_meta": like("any (policy|rule) that governs|rules governing rules|policies about policies"),
    }


def ho_audit(df: DataFrame) -> DataFrame:
    return df.withColumns(signatures(F.col("text")))


def review_queue(formulas: DataFrame) -> DataFrame:
    """Rows without a formula, with only their text to look at."""
    return formulas.where("not ok").select("sent_id", "text", F.coalesce("category", F.lit("misc")).alias("category"))


def nodes(formulas: DataFrame) -> DataFrame:
    """Formula trees as ``(sent_id, node, parent, ord, kind, name)`` rows."""
    node = lambda i, parent, ord_, kind, name: F.struct(F.lit(i).alias("node"), F.lit(parent).cast("int").alias("parent"), F.lit(ord_).alias("ord"), F.lit(kind).alias("kind"), name.alias("name"))
    tree = F.array(
        node(0, None, 0, "quant", F.col("quant")), node(1, 0, 0, "conn", F.lit("->")), node(2, 1, 0, "pred", F.col("cls")), node(3, 2, 0, "term", F.col("var")),
        node(4, 1, 1, "op", F.col("op")), node(5, 4, 0, "pred", F.col("pred")), node(6, 5, 0, "term", F.col("var")),
    )
    return formulas.where("ok").select("sent_id", F.explode(tree).alias("n")).select("sent_id", "n.*")


@dataclass(frozen=True)
class Parsed:
    """A formula read from text."""

    quant: str
    var: str
    cls: str
    op: str
    literals: tuple[tuple[str, tuple[str, ...], bool], ...]
    connective: str

    def normal(self) -> str:
        """Alpha-normal text: the variable is always ``x``."""
        arg = lambda a: "x" if a == self.var else a
        body = f" {self.connective} ".join(("!" if neg else "") + f"{p}({', '.join(map(arg, args))})" for p, args, neg in self.literals)
        return f"{self.quant} x. {self.cls}(x) -> {self.op}({body})"


def parse(text: str) -> tuple[Parsed | None, list[str]]:
    """Recursive-free reader of the canonical pattern with diagnostics: paren, no_op, multi_op, free_var, arity0, unknown_conn."""
    diagnostics = []
    if text.count("(") != text.count(")"):
        diagnostics.append("paren")
    ops = re.findall(r"(?<![A-Za-z])([OPF])\(", text)
    if not ops:
        diagnostics.append("no_op")
    if len(ops) > 1:
        diagnostics.append("multi_op")
    m = re.fullmatch(r"(forall|exists) (\w+)\. (\w+)\((\w+)\) -> ([OPF])\((.*)\)", text)
    if not m or diagnostics:
        return None, diagnostics or ["paren"]
    quant, var, cls, arg, op, body = m.groups()
    conns = set(re.findall(r"\) (\S+) !?\w+\(", body))
    if conns - {"&", "|"} or len(conns) > 1:
        diagnostics.append("unknown_conn")
    literals = []
    for neg, pred, args in re.findall(r"(!?)(\w+)\(([^()]*)\)", body):
        names = tuple(a.strip() for a in args.split(",") if a.strip())
        if not names:
            diagnostics.append("arity0")
        literals.append((pred, names, bool(neg)))
    free = {a for _, names, _ in literals for a in names if a != var and len(a) == 1} | ({arg} - {var})
    if free:
        diagnostics.append("free_var")
    if not literals:
        diagnostics.append("arity0")
    return (None if diagnostics else Parsed(quant, var, cls, op, tuple(literals), next(iter(conns), "&"))), diagnostics
