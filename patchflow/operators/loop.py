"""Closed loop over a caption recipe: score, diagnose, propose one edit, verify, accept, freeze, apply.

A recipe is a set of rewriting rules and one switch that adds the frame clock to a text.  All
candidates of a round are scored in one job over the same small batches; the driver sees only a
row per candidate and dimension.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .curate import words

DIMENSIONS = ("brevity", "coherence", "novelty", "timing")


@dataclass(frozen=True)
class Recipe:
    """Rules by name, applied in the order of ``RULES``; ``clock`` is the input transform."""

    rules: tuple[str, ...] = ()
    clock: bool = False

    def label(self) -> str:
        return "+".join([*sorted(self.rules), *(["clock"] if self.clock else [])]) or "none"


def _sentences(text: Column) -> Column:
    return F.filter(F.transform(F.split(text, r"[.!?]+\s*|\n", -1), lambda s: F.trim(s)), lambda s: s != "")


#: rule -> rewriting of a text; each names the dimension it is meant to lift
RULES: dict[str, tuple[str, Callable[[Column], Column]]] = {
    "one_space": ("brevity", lambda t: F.trim(F.regexp_replace(t, r"[ \t]+", " "))),
    "no_markup": ("coherence", lambda t: F.regexp_replace(t, r"[*#%$&|]{2,}", "")),
    "no_restated": ("novelty", lambda t: F.array_join(F.array_distinct(_sentences(t)), ". ")),
    "no_fragments": ("coherence", lambda t: F.array_join(F.filter(_sentences(t), lambda s: F.size(F.split(s, " ")) >= 4), ". ")),
    "no_stutter": ("brevity", lambda t: F.regexp_replace(t, r"\b(\w+)(?: \1\b)+", "$1")),
}


def rewrite(text: Column, recipe: Recipe) -> Column:
    """A null text stays null; the rules see whole texts."""
    for name, (_, rule) in RULES.items():
        if name in recipe.rules:
            text = rule(text)
    if recipe.clock:
        text = F.concat(F.lit("[00:00] "), text)
    return text


def score(texts: DataFrame) -> DataFrame:
    """Adds the four dimensions (0 to 1) of ``text``; an empty or null text scores 0 in each."""
    w = words(F.col("text"))
    n = F.size("_w")
    s = _sentences(F.col("text"))
    d = {
        "brevity": F.least(F.lit(1.0), 200.0 / n),
        "coherence": F.size(F.filter("_s", lambda x: (F.size(F.split(x, " ")) >= 4) & ~x.rlike(r"[*#%$&|]{2,}"))) / F.size("_s"),
        "novelty": F.size(F.array_distinct("_s")) / F.size("_s"),
        "timing": F.when(F.col("text").rlike(r"\[\d\d:\d\d\]"), 1.0).otherwise(0.5),
    }
    known = (n > 0) & (F.size("_s") > 0)
    return texts.withColumns({"_w": w, "_s": s}).withColumns({k: F.when(known, F.round(v, 6)).otherwise(0.0) for k, v in d.items()}).drop("_w", "_s")


def evaluate(batch: DataFrame, recipes: list[Recipe]) -> dict[str, dict[str, float]]:
    """Mean of each dimension by recipe, in one job: each row is rewritten by every candidate."""
    variants = F.array(*[F.struct(F.lit(r.label()).alias("recipe"), rewrite(F.col("text"), r).alias("text")) for r in recipes])
    each = batch.select(F.explode(variants).alias("v")).select("v.recipe", "v.text")
    rows = score(each).groupBy("recipe").agg(*[F.round(F.avg(k), 6).alias(k) for k in DIMENSIONS]).collect()  # a row per candidate
    return {r["recipe"]: {k: r[k] for k in DIMENSIONS} for r in rows}


def propose(recipe: Recipe, weakest: str) -> list[Recipe]:
    """Every recipe one edit away that is meant for the dimension."""
    if weakest == "timing":
        return [] if recipe.clock else [replace(recipe, clock=True)]
    return [replace(recipe, rules=tuple(sorted((*recipe.rules, n)))) for n, (k, _) in RULES.items() if k == weakest and n not in recipe.rules]


def total(scores: dict[str, float]) -> float:
    return round(sum(scores[k] for k in DIMENSIONS) / len(DIMENSIONS), 6)


def optimize(rollout: DataFrame, validation: DataFrame, rounds: int = 10, reviewer: Callable[[Recipe, Recipe], bool] | None = None, start: Recipe = Recipe()) -> tuple[Recipe, list[tuple]]:
    """The frozen recipe and the log (round, dimension, before, candidate, score before, score after, verdict).

    The rollout batch finds the weak dimension and the best edit for it; the validation batch, disjoint
    from it, decides.  A rejected edit is archived in the log and not proposed again.
    """
    rollout, validation = rollout.select("text").cache(), validation.select("text").cache()  # about 1,200 rows
    recipe, log, rejected = start, [], set()
    try:
        for i in range(1, rounds + 1):
            options = {k: [c for c in propose(recipe, k) if c.label() not in rejected] for k in DIMENSIONS}
            seen = evaluate(rollout, [recipe, *(c for v in options.values() for c in v)])
            own = seen[recipe.label()]
            open_dims = [k for _, k in sorted((own[k], k) for k in DIMENSIONS) if options[k]]
            if not open_dims:
                break
            weak = open_dims[0]
            best = max(options[weak], key=lambda c: (total(seen[c.label()]), c.label()))
            held = evaluate(validation, [recipe, best])
            before, after = total(held[recipe.label()]), total(held[best.label()])
            verdict = "rejected" if after <= before else "accepted" if reviewer is None or reviewer(recipe, best) else "vetoed"
            log.append((i, weak, recipe.label(), best.label(), before, after, verdict))
            if verdict == "accepted":
                recipe, rejected = best, set()
            else:
                rejected.add(best.label())
    finally:
        rollout.unpersist()
        validation.unpersist()
    return recipe, log


def apply(corpus: DataFrame, recipe: Recipe) -> DataFrame:
    """The frozen recipe over the whole corpus: one narrow pass."""
    return corpus.withColumn("text", rewrite(F.col("text"), recipe))
