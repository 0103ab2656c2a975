"""Quality classifier: a sparse ensemble of rules over text statistics.

Shallow boosted trees are grown on a bounded sample of labelled documents; every path from a
root is a conjunctive rule. A logistic model with a lasso penalty weighs the rules and drops
most. What is left is compiled into one Spark column expression over the statistics.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecquant.llm.textstats import CLASSES, text_statistics

Condition = tuple[str, bool, float]  # a statistic, whether it is to be above, the bound


def _share(part: Column, whole: Column) -> Column:
    return F.coalesce(part / F.nullif(whole, F.lit(0)), F.lit(0.0))


def features() -> dict[str, Column]:
    """Statistics that rules may use, over the columns of text_statistics; 0 where undefined."""
    count = {c: F.col("class_counts")[i] for i, c in enumerate(CLASSES)}
    words, chars = F.col("n_words"), F.col("n_chars")
    common = F.aggregate("common_counts", F.lit(0), lambda a, x: a + x)
    found = {f"{c}_share": _share(count[c], chars) for c in CLASSES}
    found |= {
        "log_words": F.log1p(words),
        "word_length": _share(F.col("word_chars"), words),
        "words_per_line": _share(words, F.col("n_lines")),
        "repeat_share": _share(F.col("n_repeat_words"), words),
        "repeat_line_share": _share(F.col("n_dup_lines"), F.col("n_lines")),
        "symbols_per_word": _share(F.col("n_symbols"), words),
        "marks_per_word": _share(count["mark"], words),
        "stops_per_word": _share(count["stop"], words),
        "common_share": _share(common, words),
        "upper_of_letters": _share(count["upper"], count["upper"] + count["lower"] + count["wide"]),
    }
    return found


@dataclass
class RuleModel:
    """Weighted rules; score() is their logistic sum as a column over the feature columns."""

    bias: float
    rules: list[tuple[list[Condition], float]] = field(default_factory=list)

    def score(self) -> Column:
        total = F.lit(self.bias)
        for conditions, weight in self.rules:
            holds = F.lit(True)
            for name, above, bound in conditions:
                holds = holds & ((F.col(name) > bound) if above else (F.col(name) <= bound))
            total = total + F.when(holds, F.lit(weight)).otherwise(F.lit(0.0))
        return 1 / (1 + F.exp(-total))


def _grow(x: np.ndarray, bounds: list[np.ndarray], slope: np.ndarray, depth: int, least: int) -> list[list[tuple[int, bool, float]]]:
    """Paths of one regression tree on the residuals, best split by squared gain."""
    paths: list[list[tuple[int, bool, float]]] = []

    def split(rows: np.ndarray, path: list[tuple[int, bool, float]]) -> None:
        if len(path) == depth or len(rows) < 2 * least:
            return
        total, n, best = slope[rows].sum(), len(rows), (1e-9, -1, 0.0)
        for f, cuts in enumerate(bounds):
            if not len(cuts):
                continue
            slot = np.searchsorted(cuts, x[rows, f], side="left")
            counts = np.cumsum(np.bincount(slot, minlength=len(cuts) + 1))[:-1]
            sums = np.cumsum(np.bincount(slot, weights=slope[rows], minlength=len(cuts) + 1))[:-1]
            good = (counts >= least) & (n - counts >= least)
            if not good.any():
                continue
            gain = np.where(good, sums**2 / np.maximum(counts, 1) + (total - sums) ** 2 / np.maximum(n - counts, 1), 0) - total**2 / n
            k = int(gain.argmax())
            if gain[k] > best[0]:
                best = (gain[k], f, float(cuts[k]))
        if best[1] < 0:
            return
        above = x[rows, best[1]] > best[2]
        for side in (False, True):
            longer = [*path, (best[1], side, best[2])]
            paths.append(longer)
            split(rows[above == side], longer)

    split(np.arange(len(x)), [])
    return paths


def _holds(x: np.ndarray, path: list[tuple[int, bool, float]]) -> np.ndarray:
    out = np.ones(len(x), dtype=bool)
    for f, above, bound in path:
        out &= (x[:, f] > bound) == above
    return out


def fit_rules(
    x: np.ndarray, y: np.ndarray, names: list[str], trees: int = 16, depth: int = 3, penalty: float = 1e-3, steps: int = 400
) -> RuleModel:
    """Grow trees by boosting, then weigh their paths by logistic regression with a lasso penalty."""
    if not len(y):
        return RuleModel(0.0)
    share = min(max(y.mean(), 1e-3), 1 - 1e-3)
    bias = float(np.log(share / (1 - share)))
    if y.min() == y.max():
        return RuleModel(bias)
    bounds = [np.unique(np.quantile(x[:, f], np.linspace(0.02, 0.98, 33))) for f in range(x.shape[1])]
    least = max(5, len(y) // 200)
    margin = np.full(len(y), bias)
    paths: dict[tuple, list] = {}
    for _ in range(trees):
        p = 1 / (1 + np.exp(-margin))
        grown = _grow(x, bounds, y - p, depth, least)
        leaves = [q for q in grown if not any(len(o) > len(q) and o[: len(q)] == q for o in grown)]
        for q in leaves:
            rows = _holds(x, q)
            margin[rows] += 0.3 * (y - p)[rows].sum() / ((p * (1 - p))[rows].sum() + 1)
        paths |= {tuple(q): q for q in grown}
    table, kept, seen = [], [], set()
    for q in paths.values():
        column = _holds(x, q)
        if (mark := column.tobytes()) not in seen:
            seen.add(mark)
            table.append(column)
            kept.append(q)
    if not table:
        return RuleModel(bias)
    z = np.column_stack(table).astype(float)
    center = z.mean(axis=0)
    spread = np.maximum(z.std(axis=0), 0.05)
    z = (z - center) / spread
    weights, start, momentum, level = np.zeros(z.shape[1]), np.zeros(z.shape[1]), 1.0, bias
    rate = 4 / max(np.linalg.eigvalsh(z.T @ z / len(z)).max(), 1e-9)
    for _ in range(steps):
        error = 1 / (1 + np.exp(-(z @ start + level))) - y
        step = start - rate * (z.T @ error) / len(y)
        new = np.sign(step) * np.maximum(np.abs(step) - rate * penalty, 0)
        level -= 2 * error.mean()
        faster = (1 + np.sqrt(1 + 4 * momentum**2)) / 2
        start = new + (momentum - 1) / faster * (new - weights)
        weights, momentum = new, faster
    weights = weights / spread
    used = np.flatnonzero(weights)
    rules = [([(names[f], above, bound) for f, above, bound in kept[k]], float(weights[k])) for k in used]
    return RuleModel(float(level - (weights * center).sum()), rules)


def held_out(doc_id: Column, parts: int = 5) -> Column:
    """Whether the id is kept from learning: crc32 of its text leaves remainder 0."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % parts == 0, F.lit(False))


def fit_on_documents(
    docs: DataFrame,
    labels: DataFrame,
    id_column: str = "doc_id",
    text_column: str = "text",
    label_column: str = "quality",
    sample_rows: int = 8_000,
) -> RuleModel:
    """Learn from labelled documents outside the held-out part.

    sample_rows bounds the labelled rows that are learned from: those whose id hashes lowest.
    Rows with a null id or label teach nothing; of repeated labels the higher counts, of the rows
    of a repeated id one (the text that hashes lowest). So at most sample_rows rows of statistics
    reach the driver. Ties between hashes go to the smaller id. With no usable rows, every score
    is 0.5.
    """
    usable = labels.where(F.col(label_column).isNotNull() & F.col(id_column).isNotNull() & ~held_out(F.col(id_column)))
    known = usable.groupBy(F.col(id_column).alias("id")).agg(F.max(label_column).alias("label"))
    sample = known.orderBy(F.xxhash64("id"), "id").limit(sample_rows)
    texts = docs.select(F.col(id_column).alias("id"), F.col(text_column).alias("text"))
    # A sampled id may stand on any number of rows; the text that hashes lowest is learned from.
    own = texts.join(F.broadcast(sample), "id").groupBy("id", "label").agg(F.min_by("text", F.xxhash64("text")).alias("text"))
    columns = features()
    rows = text_statistics(own, "text", ("id", "label")).select("id", "label", *[c.alias(n) for n, c in columns.items()])
    found = rows.toPandas().sort_values(["id", *columns], kind="stable")
    return fit_rules(found[list(columns)].to_numpy(dtype=float), found["label"].to_numpy(dtype=float), list(columns))


def score_documents(docs: DataFrame, model: RuleModel, keep: tuple[str, ...], text_column: str = "text") -> DataFrame:
    """The columns to keep, and score: the probability of label 1 by the rules.

    A null text counts as empty and has a score too. Every row stays, repeated ones too, and equal
    texts have equal scores; an empty table gives no rows. Texts are counted whole; working memory
    is a few times that of the longest text.
    """
    stats = text_statistics(docs, text_column, keep)
    # Arrays are summed once per row, not once per rule.
    values = stats.select(*keep, *[c.alias(f"stat_{n}") for n, c in features().items()])
    renamed = RuleModel(model.bias, [([(f"stat_{n}", a, b) for n, a, b in rule], w) for rule, w in model.rules])
    return values.select(*keep, renamed.score().alias("score"))
