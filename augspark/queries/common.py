"""Tables, request fixtures and SQL fragments that several queries share."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from augspark.cluster import table
from augspark.ring import gram

#: Added before rounding, so that decimals that end in a 5 round alike whatever the order of summation.
TIE = 1.3e-9
LINE = ["l_quantity", "l_discount", "l_tax"]
FOLD_SQL = "((l_orderkey + 3 * l_linenumber) % 10)"
Y_SQL = "(10 * (p_retailprice - 950) + 0.1::DOUBLE * s_acctbal + 0.002::DOUBLE * o_totalprice)"
REQ_SQL = f"""req AS (
  SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_discount, l_tax, {FOLD_SQL}::INTEGER AS fold, {Y_SQL} AS y
  FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey
)"""


def fold_column():
    return ((F.col("l_orderkey") + 3 * F.col("l_linenumber")) % 10).cast("int").alias("fold")


def lines(spark: SparkSession, d: str) -> DataFrame:
    """Lineitem's small features, keys and folds."""
    return table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", *LINE, "l_extendedprice", fold_column())


def planted(spark: SparkSession, d: str) -> DataFrame:
    """Lineitem with a target planted in part, supplier and orders, whose columns are then dropped."""
    base = table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", *LINE, fold_column())
    part = table(spark, d, "part").select(F.col("p_partkey").alias("l_partkey"), "p_retailprice")
    supplier = table(spark, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_acctbal")
    orders = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_totalprice")
    joined = base.join(part, "l_partkey").join(supplier, "l_suppkey").join(orders, "l_orderkey")
    y = 10 * (F.col("p_retailprice") - 950) + F.lit(0.1) * F.col("s_acctbal") + F.lit(0.002) * F.col("o_totalprice")
    return joined.withColumn("y", y).drop("p_retailprice", "s_acctbal", "o_totalprice")


def exact(x: str) -> str:
    return f"CAST({x} AS DECIMAL(18,2))"


def sql_gram(features: list[str], digits: int = 4, cast=exact, prefix: str = "") -> str:
    """The select list c, s_<f>, q_<f>_<f> over rows."""
    out = ["count(*)::DOUBLE AS c"]
    out += [f"round(sum({cast(prefix + f)})::DOUBLE, {digits}) AS s_{f}" for f in features]
    out += [f"round(sum({cast(prefix + features[i])} * {cast(prefix + features[j])})::DOUBLE, {digits}) AS q_{features[i]}_{features[j]}" for i, j in gram.pairs(len(features))]
    return ", ".join(out)


def means(features: list[str], digits: int = 6, g=None) -> list:
    """c, and sums and pair sums divided by c: comparable however rows were added up."""
    g = F.col("g") if g is None else g
    m = len(features)
    out = [F.round(g["c"], 3).alias("c")]
    out += [F.round(g["s"][i] / g["c"] + TIE, digits).alias(f"s_{f}") for i, f in enumerate(features)]
    return out + [F.round(g["q"][gram.at(i, j, m)] / g["c"] + TIE, digits).alias(f"q_{features[i]}_{features[j]}") for i, j in gram.pairs(m)]


def sql_means(features: list[str], weight: str = "1", digits: int = 6, terms: dict | None = None) -> str:
    """The same over rows with weights; terms replaces the expression of a pair."""
    terms = terms or {}
    out = [f"round(sum({weight})::DOUBLE, 3) AS c"]
    out += [f"round(sum({weight} * {f})::DOUBLE / sum({weight}) + {TIE}::DOUBLE, {digits}) AS s_{f}" for f in features]
    out += [f"round(sum({weight} * {terms.get((features[i], features[j]), features[i] + ' * ' + features[j])})::DOUBLE / sum({weight}) + {TIE}::DOUBLE, {digits}) AS q_{features[i]}_{features[j]}" for i, j in gram.pairs(len(features))]
    return ", ".join(out)


def cv_sql(base: str, sets: dict[str, list[str]], y: str = "y", name: str = "r") -> str:
    """CTEs that end in ``name`` (dataset, cv_r2): mean fold R² of ordinary least squares on each list of columns.

    base is a query with fold and the columns. Covariances of the training side of a fold are swept column by column, which
    leaves the parameters in the target's column; they are then measured on the fold's own sums, unless its target is constant.
    """
    every = sorted({x for xs in sets.values() for x in xs}) + [y]
    cells = [(a, b) for i, a in enumerate(every) for b in every[i:]]
    sums = ", ".join([f"sum({v})::DOUBLE AS s_{v}" for v in every] + [f"sum({a} * {b})::DOUBLE AS q_{a}_{b}" for a, b in cells])
    whole = ", ".join([f"sum(s_{v}) AS s_{v}" for v in every] + [f"sum(q_{a}_{b}) AS q_{a}_{b}" for a, b in cells])
    rest = ", ".join([f"tot.s_{v} - f.s_{v} AS s_{v}" for v in every] + [f"tot.q_{a}_{b} - f.q_{a}_{b} AS q_{a}_{b}" for a, b in cells])
    out = [
        f"{name}_b AS ({base})",
        f"{name}_f AS (SELECT fold, count(*)::DOUBLE AS n, {sums} FROM {name}_b GROUP BY fold)",
        f"{name}_t AS (SELECT f.fold, tot.n - f.n AS n, {rest} FROM {name}_f f, (SELECT sum(n) AS n, {whole} FROM {name}_f) tot)",
    ]
    parts = []
    for i, (label, xs) in enumerate(sets.items()):
        vs = [v for v in every if v in xs] + [y]
        k = len(vs) - 1
        cov = ", ".join(f"q_{vs[a]}_{vs[b]} - s_{vs[a]} * s_{vs[b]} / n AS c{a}_{b}" for a in range(k + 1) for b in range(a, k + 1))
        out.append(f"{name}_{i}_0 AS (SELECT fold, {cov} FROM {name}_t)")
        out += [f"{name}_{i}_{step + 1} AS (SELECT fold, {_swept(step, k + 1)} FROM {name}_{i}_{step})" for step in range(k)]
        out.append(f"{name}_{i}_v AS (SELECT fold, n, {cov}, {', '.join(f's_{v} / n AS m{a}' for a, v in enumerate(vs))} FROM {name}_f)")
        out.append(f"{name}_{i}_m AS (SELECT fold, {', '.join(f's_{v} / n AS m{a}' for a, v in enumerate(vs))} FROM {name}_t)")
        w = [f"w.c{a}_{k}" for a in range(k)]
        bias = f"(v.m{k} - m.m{k})" + "".join(f" - {w[a]} * (v.m{a} - m.m{a})" for a in range(k))
        quad = f"v.c{k}_{k}" + "".join(f" - 2 * {w[a]} * v.c{a}_{k}" for a in range(k)) + "".join(f" + {w[a]} * {w[b]} * v.c{min(a, b)}_{max(a, b)}" for a in range(k) for b in range(k))
        parts.append(f"SELECT '{label}' AS dataset, avg(CASE WHEN v.c{k}_{k} > 1e-9 THEN 1 - (({quad}) + v.n * pow({bias}, 2)) / v.c{k}_{k} END) AS cv_r2 FROM {name}_{i}_{k} w JOIN {name}_{i}_v v USING (fold) JOIN {name}_{i}_m m USING (fold)")
    return ",\n".join([*out, f"{name} AS ({' UNION ALL '.join(parts)})"])


def _swept(k: int, n: int) -> str:
    """The select list of a symmetric matrix after a sweep on its k-th row."""
    c = lambda i, j: f"c{min(i, j)}_{max(i, j)}"
    cell = lambda i, j: f"-1 / {c(k, k)}" if i == j == k else f"{c(i, j)} / {c(k, k)}" if k in (i, j) else f"{c(i, j)} - {c(i, k)} * {c(k, j)} / {c(k, k)}"
    return ", ".join(f"{cell(i, j)} AS {c(i, j)}" for i in range(n) for j in range(i, n))


def greedy_sql(base: str, own: list[str], joins: dict[str, list[str]], steps: int = 3, delta: float = 0.02, extra: str = "") -> str:
    """Rows (step, dataset, cv_r2) of a greedy choice among joins, each with its columns; ``own`` columns are always in.

    Step 0 is the model without joins. A step is taken while it gains delta.
    """
    import itertools

    names = sorted(joins)
    sets = {"-": own} if own else {}
    for n in range(1, min(steps, len(names)) + 1):
        for chosen in itertools.combinations(names, n):
            sets["+".join(chosen)] = [*own, *(x for c in chosen for x in joins[c])]
    first = "b0 AS (SELECT '-' AS plan, '-' AS dataset, " + ("(SELECT cv_r2 FROM r WHERE dataset = '-')" if own else "0.0::DOUBLE") + " AS cv_r2)"
    out, taken = [cv_sql(base, sets), "plans AS (SELECT list_sort(string_split(dataset, '+')) AS members, cv_r2 FROM r WHERE dataset <> '-')", first], []
    for n in range(1, min(steps, len(names)) + 1):
        had = "CASE WHEN b.plan = '-' THEN []::VARCHAR[] ELSE string_split(b.plan, '+') END"
        out.append(
            f"b{n} AS (SELECT array_to_string(p.members, '+') AS plan, list_filter(p.members, lambda x: NOT list_contains({had}, x))[1] AS dataset, p.cv_r2 FROM plans p, b{n - 1} b "
            f"WHERE len(p.members) = {n} AND list_has_all(p.members, {had}) AND p.cv_r2 - b.cv_r2 >= {delta} ORDER BY p.cv_r2 DESC LIMIT 1)"
        )
        taken.append(f"SELECT {n}, dataset, round(cv_r2, 4) FROM b{n}")
    return f"WITH {extra}{', ' if extra else ''}" + ",\n".join(out) + " SELECT 0 AS step, '-' AS dataset, round(cv_r2, 4) AS cv_r2 FROM b0 UNION ALL " + " UNION ALL ".join(taken)
