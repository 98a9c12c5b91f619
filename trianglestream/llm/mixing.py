"""Mixing sources to target weights by iterative proportional fitting, in DataFrame operations only.

Documents fall in cells (source, language, topic) with a token total each; only
cells are fitted. A sweep scales the cells to the source, the language and the
topic marginal in turn. Targets are shares by value; where none are given, the
present shares to the power ``temper``, scaled to one, are used. The fitted share
over the present one is a cell's ratio; probabilities are min(1, scale * ratio),
the scale such that the expected tokens meet the budget. A document is drawn if a
hash of seed and identifier lies below its cell's probability.

The topic is a rule over the text: the first marker it holds, else by its length.
Nulls are a value of their own (``?``), null texts have no tokens but count as a
cell with the least weight of one token, repeated rows share their draw, an empty
table gives no rows. Marginals of an empty cell set cannot be met and stay short;
``residuals`` reports how far each axis is from its target after the sweeps. Columns
of the input that bear the names added here keep their values; the added ones then get
leading underscores.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from .common import documents, materialize, release, unit_hash, working_name

AXES = ["source", "lang", "topic"]
#: Topic rules in order: name, texts of which one must occur.
TOPICS = [("legal", ["License", "license", "Copyright"]), ("web", ["http", "www."]), ("contact", ["@"]), ("code", ["{", "def ", "();"])]
SWEEPS, SCALE_STEPS, SHORT_TEXT = 10, 8, 1000


def topic_of(text: Column) -> Column:
    rule = None
    for name, marks in TOPICS:
        test = None
        for m in marks:
            test = text.contains(m) if test is None else test | text.contains(m)
        rule = F.when(test, name) if rule is None else rule.when(test, name)
    return rule.when(F.length(text) < SHORT_TEXT, "short").otherwise("long")


def token_count(text: Column) -> Column:
    """Spaces and line ends plus one: a cheap token measure, at least one."""
    return (F.length(text) - F.length(F.replace(F.replace(text, F.lit(" "), F.lit("")), F.lit("\n"), F.lit(""))) + 1).cast("bigint")


def described(docs: DataFrame, text_col: str = "text") -> tuple[DataFrame, dict[str, str]]:
    """``docs`` with source, lang, topic and tokens of the mix, and the names of these columns."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    have = {c.lower() for c in docs.columns}
    name = {a: working_name(docs, f"mix_{a}") for a in (*AXES, "tokens", "ratio", "probability", "kept")}
    axis = {a: F.coalesce(F.col(a).cast("string"), F.lit("?")) if a in have else F.lit("?") for a in ("source", "lang")}
    return docs.withColumns({name["source"]: axis["source"], name["lang"]: axis["lang"], name["topic"]: topic_of(text), name["tokens"]: token_count(text)}), name


def targets_of(cells: DataFrame, axis: str, given: dict[str, float] | None, temper: float) -> DataFrame:
    """(axis, target): shares that add up to one over the values present."""
    present = cells.groupBy(axis).agg(F.sum("tokens").alias("t"))
    if given is not None:
        pairs = F.create_map(*[x for k, v in given.items() for x in (F.lit(k), F.lit(float(v)))])
        present = present.select(axis, F.coalesce(F.element_at(pairs, F.col(axis)), F.lit(0.0)).alias("power"))
    else:
        present = present.select(axis, F.pow(F.col("t").cast("double"), F.lit(temper)).alias("power"))
    whole = present.agg(F.sum("power")).first()[0] or 1.0
    return present.select(axis, (F.col("power") / F.lit(whole)).alias("target"))


def fit_cells(cells: DataFrame, given: dict[str, dict[str, float]], temper: float, sweeps: int, budget: float) -> DataFrame:
    """Cells (axes, tokens) with ratio and probability. Only totals and the scale, single numbers, reach the driver."""
    targets = {a: materialize(targets_of(cells, a, given.get(a), temper), "targets") for a in AXES}
    total = float(cells.agg(F.sum("tokens")).first()[0] or 1)
    # A cell's fit is its present share times one factor for each axis. Only factors change, each in a plan
    # of its own over the cells, so plans stay small however many sweeps there are.
    share = cells.withColumn("share", F.col("tokens") / F.lit(total))
    factors = {a: targets[a].select(a, F.lit(1.0).alias(f"{a}_factor")) for a in AXES}
    spent = []
    for _ in range(sweeps):
        for axis in AXES:
            rows, weight = share, F.col("share")
            for other in AXES:
                if other != axis:
                    rows, weight = rows.join(factors[other], other), weight * F.col(f"{other}_factor")
            have = rows.groupBy(axis).agg(F.sum(weight).alias("have")).join(targets[axis], axis)
            new = have.select(axis, F.when(F.col("have") > 0, F.col("target") / F.col("have")).otherwise(0.0).alias(f"{axis}_factor"))
            spent.append(factors[axis])
            factors[axis] = materialize(new, "factors")
    now = share
    for axis in AXES:
        now = now.join(factors[axis], axis)
    fit = materialize(now.select(*AXES, "tokens", (F.col("share") * F.col("source_factor") * F.col("lang_factor") * F.col("topic_factor")).alias("fit")), "fit")
    release(*spent[len(AXES) :], *targets.values())  # the first factors are ones and no tables
    now = fit.withColumn("ratio", F.col("fit") * F.lit(total) / F.col("tokens"))
    scale = float(budget)
    for _ in range(SCALE_STEPS):
        certain = F.col("ratio") * F.lit(scale) >= 1
        sums = now.agg(F.sum(F.when(certain, F.col("tokens")).otherwise(0)).alias("full"), F.sum(F.when(certain, 0.0).otherwise(F.col("fit"))).alias("open")).first()
        if not sums["open"]:
            break
        scale = max(scale, (budget - sums["full"] / total) / sums["open"])
    return now.withColumn("probability", F.least(F.lit(1.0), F.col("ratio") * F.lit(scale))).select(*AXES, "tokens", "fit", "ratio", "probability")


def residuals(fitted: DataFrame, given: dict[str, dict[str, float]] | None = None, temper: float = 0.7) -> DataFrame:
    """(axis, value, target, share, residual) of fitted cells: what the sweeps left between the shares and their targets."""
    rows = None
    for axis in AXES:
        have = fitted.groupBy(axis).agg(F.sum("fit").alias("share")).join(targets_of(fitted, axis, (given or {}).get(axis), temper), axis)
        part = have.select(F.lit(axis).alias("axis"), F.col(axis).alias("value"), "target", "share", F.abs(F.col("share") - F.col("target")).alias("residual"))
        rows = part if rows is None else rows.unionByName(part)
    return rows


def cells_of(rows: DataFrame, name: dict[str, str]) -> DataFrame:
    return rows.groupBy(*[F.col(name[a]).alias(a) for a in AXES]).agg(F.sum(name["tokens"]).alias("tokens"))


def calibrated(docs: DataFrame, targets: dict[str, dict[str, float]] | None = None, temper: float = 0.7, budget: float = 0.8, sweeps: int = SWEEPS, seed: int = 13, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, dict[str, str]]:
    """``docs`` with columns mix_source, mix_lang, mix_topic, mix_tokens, mix_ratio, mix_probability and mix_kept, and
    their names by the part after ``mix_``, which differ where ``docs`` has such columns."""
    rows, name = described(docs, text_col)
    cells = materialize(cells_of(rows, name), "cells")
    fitted = fit_cells(cells, targets or {}, temper, sweeps, budget)
    fitted = materialize(fitted.select(*[F.col(a).alias(name[a]) for a in AXES], F.col("ratio").alias(name["ratio"]), F.col("probability").alias(name["probability"])), "fitted")
    release(cells)
    joined = rows.join(fitted, [name[a] for a in AXES], "left")
    return joined.withColumn(name["kept"], F.coalesce(unit_hash(id_col, seed=seed) < F.col(name["probability"]), F.lit(False))), name


def mix(docs: DataFrame, **options) -> DataFrame:
    """The drawn rows of ``docs`` with their own columns."""
    drawn, name = calibrated(docs, **options)
    return drawn.where(F.col(name["kept"])).select(*[f"`{c}`" for c in docs.columns])


def op1_mixing(spark, sf_dir: str) -> DataFrame:
    """Whole ``documents``: doc_id, cell, tokens, ratio, probability and whether the row is drawn, one row for each."""
    drawn, _ = calibrated(documents(spark, sf_dir).select("doc_id", "text", "source", "lang"))
    return drawn.select(
        "doc_id", F.col("mix_source").alias("source"), F.col("mix_lang").alias("lang"), F.col("mix_topic").alias("topic"), F.col("mix_tokens").alias("tokens"),
        F.round("mix_ratio", 6).alias("ratio"), F.round("mix_probability", 6).alias("probability"), F.col("mix_kept").alias("kept"),
    )


def mixing_sql(temper: float = 0.7, budget: float = 0.8, sweeps: int = SWEEPS, seed: int = 13) -> str:
    """The same in DuckDB, sweeps unrolled."""
    rules = " ".join(f"WHEN {' OR '.join(f'''contains(body, '{m}')''' for m in marks)} THEN '{name}'" for name, marks in TOPICS)
    steps = [
        "base AS (SELECT doc_id, coalesce(text, '') AS body, coalesce(source, '?') AS source, coalesce(lang, '?') AS lang FROM documents)",
        f"rows AS (SELECT doc_id, source, lang, CASE {rules} WHEN length(body) < {SHORT_TEXT} THEN 'short' ELSE 'long' END AS topic, CAST(length(body) - length(replace(replace(body, ' ', ''), chr(10), '')) + 1 AS BIGINT) AS tokens FROM base)",
        "cells AS MATERIALIZED (SELECT source, lang, topic, CAST(sum(tokens) AS BIGINT) AS tokens FROM rows GROUP BY ALL)",
    ]
    for a in AXES:
        steps.append(f"target_{a} AS MATERIALIZED (SELECT {a}, p / sum(p) OVER () AS target FROM (SELECT {a}, pow(CAST(sum(tokens) AS DOUBLE), {temper}) AS p FROM cells GROUP BY {a}))")
    steps.append("fit0 AS MATERIALIZED (SELECT *, CAST(sum(tokens) OVER () AS DOUBLE) AS total, tokens / CAST(sum(tokens) OVER () AS DOUBLE) AS fit FROM cells)")
    n = 0
    for _ in range(sweeps):
        for a in AXES:
            steps.append(f"fit{n + 1} AS MATERIALIZED (SELECT f.source, f.lang, f.topic, tokens, total, fit * target / sum(fit) OVER (PARTITION BY f.{a}) AS fit FROM fit{n} f JOIN target_{a} t ON f.{a} = t.{a})")
            n += 1
    steps.append(f"ratios AS MATERIALIZED (SELECT *, fit * total / tokens AS ratio FROM fit{n})")
    steps.append(f"scale0 AS (SELECT CAST({budget} AS DOUBLE) AS scale)")
    for i in range(SCALE_STEPS):
        steps.append(
            f"scale{i + 1} AS MATERIALIZED (SELECT CASE WHEN open > 0 THEN greatest(scale, ({budget} - full_ / total) / open) ELSE scale END AS scale FROM (SELECT max(scale) AS scale, max(total) AS total, "
            f"sum(CASE WHEN ratio * scale >= 1 THEN tokens ELSE 0 END) AS full_, sum(CASE WHEN ratio * scale >= 1 THEN 0.0 ELSE fit END) AS open FROM ratios, scale{i}))"
        )
    draw = f"CAST('0x' || substr(md5('{seed}:' || coalesce(CAST(doc_id AS VARCHAR), 'null')), 1, 13) AS BIGINT) / 4503599627370496.0"
    return (
        "WITH " + ",\n".join(steps) + f"\nSELECT doc_id, r.source, r.lang, r.topic, r.tokens, round(ratio, 6) AS ratio, round(least(1.0, ratio * scale), 6) AS probability, "
        f"{draw} < least(1.0, ratio * scale) AS kept FROM rows r JOIN ratios c ON r.source = c.source AND r.lang = c.lang AND r.topic = c.topic, scale{SCALE_STEPS}"
    )


OP1_SQL = mixing_sql()
