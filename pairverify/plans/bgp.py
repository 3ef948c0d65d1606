"""Evaluation of graph queries over a triple table, as one DataFrame plan for each query or for each shape.

Patterns are joined in connected order, the most bound one first, never as a cross product. A star around a statement
node that only uses qualifiers of one order line is answered from the line table in one scan.
"""

from __future__ import annotations

from pairverify.plans.querytext import parse
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MOST_FACTS = 10_000
AGGREGATES = {"SUM": F.sum, "AVG": F.avg, "MIN": F.min, "MAX": F.max}


def _free(t: str) -> bool:
    return t[:1] == "?" or t[:2] == "_:"


def _name(t: str) -> str:
    return t[1:] if t[:1] == "?" else "_" + t[2:]


def _value(t: str) -> str:
    return t[1:-1] if t[:1] in '<"[' else t


def _relation(t: str) -> str:
    return _value(t).removeprefix("rel:")


def _nodes(p: tuple) -> set[str]:
    return {p[0], p[2]} | ({p[1]} if _free(p[1]) else set())


def order(patterns: list[tuple]) -> list[tuple]:
    """Most bound first, then always one that shares a variable or a fixed node with those before; otherwise an error."""
    left = sorted(patterns, key=lambda p: sum(map(_free, p)))
    out = [left.pop(0)]
    seen = _nodes(out[0])
    while left:
        near = [k for k, p in enumerate(left) if not any(map(_free, p)) or seen & _nodes(p)]
        if not near:
            raise ValueError("patterns are not connected; a cross product is refused")
        k = next((k for k in near if any(_free(t) for t in seen & _nodes(left[k]))), near[0])
        out.append(left.pop(k))
        seen |= _nodes(out[-1])
    return out


def match(kg: DataFrame, p: tuple) -> DataFrame:
    """Bindings of one pattern; a variable's number and time go along under <name>__num and <name>__ts."""
    h, r, t = p
    rows = kg if _free(r) else kg.where(F.col("relation") == _relation(r))
    if not _free(h):
        rows = rows.where(F.col("head") == _value(h))
    if not _free(t):
        rows = rows.where(F.col("tail") == _value(t))
    if _free(h) and h == t:
        rows = rows.where("head = tail")
    cols = {}
    for term, col in ((h, "head"), (r, "relation"), (t, "tail")):
        if _free(term):
            cols[_name(term)] = F.col(col)
    if _free(t):
        cols |= {_name(t) + "__num": F.col("num_value"), _name(t) + "__ts": F.col("ts_value")}
    return rows.select(*[c.alias(k) for k, c in cols.items()]) if cols else rows.select(F.lit(1).alias("_hit")).limit(1)


def _compare(a: Column, op: str, b: Column) -> Column:
    return {">": a > b, "<": a < b, ">=": a >= b, "<=": a <= b, "=": a == b, "!=": a != b}[op]


def _condition(left: str, op: str, right: str, columns: list[str]) -> Column:
    def side(t: str, number: bool, time: bool) -> Column:
        if _free(t):
            return F.col(_name(t) + ("__num" if number else "__ts" if time else "") if _name(t) + "__num" in columns else _name(t))
        v = _value(t)
        return F.lit(float(v)) if number else F.lit(v).cast("timestamp_ntz") if time else F.lit(v)

    fixed = [_value(t) for t in (left, right) if not _free(t)]
    number = bool(fixed) and not any(t[:1] == '"' for t in (left, right) if not _free(t))
    time = bool(fixed) and len(fixed[0]) == 10 and fixed[0][4:5] == "-"
    a, b = (side(t, number, time) for t in (left, right))
    return _compare(a, op, b)


def bindings(query: dict, kg: DataFrame) -> DataFrame:
    out = None
    for p in order(query["patterns"]):
        m = match(kg, p)
        if out is None:
            out = m
        elif "_hit" in m.columns:
            out = out.join(F.broadcast(m.select(F.lit(True).alias("_there"))), F.lit(True), "left_semi")  # one row at most
        else:
            shared = [c for c in m.columns if c in out.columns and not c.endswith(("__num", "__ts"))]
            extra = [c for c in m.columns if c not in out.columns]
            if shared:
                out = out.join(m.select(*shared, *extra), shared)
            else:  # two facts about one fixed node: the second has so few rows that they can be sent to all tasks, or it is refused
                if m.limit(MOST_FACTS + 1).count() > MOST_FACTS:
                    raise ValueError(f"more than {MOST_FACTS} facts about one node would be combined with all others")
                out = out.join(F.broadcast(m.select(*extra)), F.lit(True))
    for left, op, right in query["filters"]:
        if isinstance(right, dict):  # one row with one number
            inner = evaluate(right, kg).limit(1).toDF("_inner").withColumn("_inner", F.col("_inner").cast("double"))
            left = F.col(_name(left) + "__num" if _name(left) + "__num" in out.columns else _name(left))
            out = out.join(F.broadcast(inner), _compare(left.cast("double"), op, F.col("_inner"))).drop("_inner")
        else:
            out = out.where(_condition(left, op, right, out.columns))
    return out


def evaluate(query: str | dict, kg: DataFrame) -> DataFrame:
    """One string column for each answer variable; ASK: boolean `answer`; COUNT: bigint `n`; other functions: double `n`."""
    q = parse(query) if isinstance(query, str) else query
    rows = bindings(q, kg)
    if q["form"] == "ask":
        return rows.limit(1).agg((F.count("*") > 0).alias("answer"))
    if q["fn"]:
        fn, var = q["fn"]["fn"], _name(q["fn"]["var"])
        if fn == "COUNT":
            made = (F.count_distinct(var) if q["fn"]["distinct"] else F.count(var)).cast("bigint").alias("n")
        else:
            made = AGGREGATES[fn](var + "__num").alias("n")
        return rows.groupBy(*map(_name, q["group"])).agg(made)
    names = list(map(_name, q["vars"]))
    if q["order"]:
        key = _name(q["order"][0])
        key = key + "__num" if key + "__num" in rows.columns else key
        rows = rows.orderBy(F.col(key).asc() if q["order"][1] else F.col(key).desc(), *names)
    if q["limit"] is not None:
        rows = rows.limit(q["limit"])
    rows = rows.select(*names)
    return rows.distinct() if q["distinct"] else rows


def evaluate_batch(bindings_: DataFrame, kg: DataFrame, patterns: list[tuple], answer: str) -> DataFrame:
    """Answers of many queries of one shape at once: (query_id, answer).

    bindings_: query_id and one column for each parameter; a term "$name" in patterns is that parameter.
    """
    out, have = bindings_, {f"${c}" for c in bindings_.columns}
    left = list(patterns)
    while left:
        k = next((k for k, (h, _, t) in enumerate(left) if h in have or t in have), None)
        if k is None:
            raise ValueError("patterns are not connected to the parameters")
        h, r, t = left.pop(k)
        rows = kg.where(F.col("relation") == _relation(r)).select(F.col("head").alias("_h"), F.col("tail").alias("_t"))
        col = lambda x: F.col(x[1:])
        cond = [F.col(side) == (col(x) if x in have else F.lit(_value(x))) for side, x in (("_h", h), ("_t", t)) if x in have or not _free(x)]
        out = out.join(rows, cond)
        for side, x in (("_h", h), ("_t", t)):
            if _free(x) and x not in have:
                out = out.withColumn(x[1:], F.col(side))
                have.add(x)
        out = out.drop("_h", "_t")
    return out.select("query_id", F.col(answer[1:]).alias("answer"))


def statement_scan(lines: DataFrame, where: dict, ask: str) -> DataFrame:
    """A star around one order line answered by one scan: where and ask are columns of the line table."""
    for c, v in where.items():
        lines = lines.where(F.col(c) == v)
    return lines.select(F.col(ask).alias("answer"))


def same_answers(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row, `same`: whether both give the same rows with the same multiplicities."""
    return a.exceptAll(b).select(F.lit(1).alias("d")).limit(1).unionAll(b.exceptAll(a).select(F.lit(1).alias("d")).limit(1)).agg((F.count("*") == 0).alias("same"))
