"""Mixing sources to target weights by iterative proportional fitting, in DataFrame operations only.

Token weights are gathered per cell (one value of every dimension), a table whose size is bounded by the
product of the dimensions' domains and not by the rows. Sweeps multiply each cell's factor so that the
marginal of one dimension after the other meets its target, until every marginal is within ``residual`` of
it or nothing improves any more (targets that no factors can meet). Up to ``NARROW`` cells are one row of
arrays and a whole series of sweeps is one expression on it; more cells are swept as a table, a written
table a sweep. A water level then scales the factors to expected copies, such that the documents kept at least
once are expected to hold ``keep_share`` of the tokens. A cell above one keeps all its documents and repeats
them: whole copies, and one more by chance for the rest. Copies are what meets the targets: kept documents
without their repeats can't give a small group more than it has. The draw is a hash of the id, uniform in
[0, 1): reproducible, and free of any order.

Targets default to observed shares raised to ``temper`` and normalised, which lifts small sources, languages
and topics and lowers large ones.

Defined results: null in a dimension is a value of its own; a null or empty text has no tokens and follows
its cell; repeated ids get one draw; an empty table gives an empty result; columns of docs that are called
like the operator's own (the dimensions, mix_p, mix_w, mix_kept, mix_copies) are replaced by ``mix`` and left
as they are by ``keep_mixed``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from .common import cut, discard

NONE = "(none)"
NARROW = 20_000  # cells that one row may hold
SERIES = 16  # sweeps of one expression
RESIDUAL = 1e-9
MOST = 64  # series, or sweeps of a wide table, after which the rest is only told


def token_weight(text) -> F.Column:
    """Words as blanks + 1; no tokens where there is no text."""
    text = F.coalesce(text, F.lit(""))
    return F.when(text == "", F.lit(0)).otherwise(F.length(text) - F.length(F.replace(text, F.lit(" "), F.lit(""))) + 1).cast("long")


def surface_topic(text) -> F.Column:
    """The tables carry no topic: four surface genres stand in for one."""
    text = F.coalesce(text, F.lit(""))
    return (
        F.when(F.contains(text, F.lit("icense")), "legal")
        .when(F.contains(text, F.lit("@")) | F.contains(text, F.lit("http")), "contact")
        .when(F.contains(text, F.lit("|")), "tabular")
        .otherwise("prose")
    )


def unit_draw(key, seed: int) -> F.Column:
    """Uniform in [0, 1) from 48 bits of an MD5, the same in any engine."""
    word = F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(key.cast("string"), F.lit("null"))).cast("binary")), 1, 12)
    return F.conv(word, 16, 10).cast("double") / F.lit(float(2**48))


def _let(value, body) -> F.Column:
    """body(value) with value computed once: an array of one element binds it to a lambda's variable."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _wanted(cells: DataFrame, d: str, targets: dict[str, DataFrame] | None, temper: float) -> DataFrame:
    """(d, mix_t): the share that each value of a dimension is to have; values without a stated one get none."""
    sums = cells.groupBy(d).agg(F.sum("mix_n").cast("double").alias("mix_s"))
    if targets and d in targets:
        return sums.join(targets[d].select(d, F.col("share").cast("double").alias("mix_t")), d, "left").select(d, F.coalesce("mix_t", F.lit(0.0)).alias("mix_t"))
    scale = sums.agg(F.sum(F.pow("mix_s", F.lit(temper))).alias("mix_all"))
    share = F.when(F.col("mix_s") > 0, F.pow("mix_s", F.lit(temper)) / F.col("mix_all")).otherwise(0.0)
    return sums.crossJoin(F.broadcast(scale)).select(d, share.alias("mix_t"))


class _Row:
    """All cells as one row: per cell its tokens n, its factor g and, per dimension, the place of its value."""

    def __init__(self, cells: DataFrame, dims: list[str], wanted: dict[str, DataFrame]):
        self.dims = dims
        row = cells.agg(F.sort_array(F.collect_list(F.struct(*dims, "mix_n"))).alias("cells"))
        for i, d in enumerate(dims):
            row = row.crossJoin(F.broadcast(wanted[d].agg(F.sort_array(F.collect_list(F.struct(d, "mix_t"))).alias(f"w{i}"))))
        row = row.withColumns({"n": F.transform("cells", lambda c: c["mix_n"].cast("double")), "g": F.transform("cells", lambda c: F.lit(1.0))})
        for i, d in enumerate(dims):
            values = F.transform(f"w{i}", lambda w: w[d])
            row = row.withColumns({
                f"at{i}": _let(values, lambda v: F.transform("cells", lambda c: F.array_position(v, c[d]).cast("int"))),
                f"t{i}": F.transform(f"w{i}", lambda w: w["mix_t"]),
            })
            places = F.transform(f"t{i}", lambda t, v: F.filter(F.sequence(F.lit(1), F.size("cells")), lambda c: F.element_at(f"at{i}", c) == v + 1))
            row = row.withColumn(f"in{i}", places)
        self.frame = cut(row, "mix-row")

    def _sums(self, i: int, g) -> F.Column:
        return F.transform(f"in{i}", lambda own: F.aggregate(own, F.lit(0.0), lambda s, c: s + F.element_at("n", c) * F.element_at(g, c)))

    def _sweep(self, g) -> F.Column:
        for i in range(len(self.dims)):
            g = self._step(i, g)
        return g

    def _step(self, i: int, g) -> F.Column:
        def scaled(now):
            steps = F.transform(self._sums(i, now), lambda s, v: F.when(s > 0, F.element_at(f"t{i}", v + 1) / s).otherwise(1.0))
            return _let(steps, lambda f: F.transform(now, lambda x, c: x * F.element_at(f, F.element_at(f"at{i}", c + 1))))

        return _let(g, scaled)

    def sweep(self, times: int) -> float:
        """``times`` sweeps; returns the largest distance of a marginal from its target."""
        g = F.aggregate(F.sequence(F.lit(1), F.lit(times)), F.col("g"), lambda now, _: self._sweep(now))
        swept = self.frame.withColumn("g", g)
        off = [F.array_max(F.transform(self._sums(i, F.col("g")), lambda s, v: F.abs(s - F.element_at(f"t{i}", v + 1)))) for i in range(len(self.dims))]
        swept = cut(swept.withColumn("off", F.array_max(F.array(*off))), "mix-row")
        discard(self.frame)
        self.frame = swept.drop("off")
        return swept.select("off").first()["off"]  # one number

    def cells(self, off: float) -> DataFrame:
        fitted = self.frame.select(F.explode(F.arrays_zip("cells", "g")).alias("c"))
        return fitted.select("c.cells.*", F.col("c.g").alias("mix_g"), F.lit(off).alias("mix_off"))


def _wide_sweep(out: DataFrame, dims: list[str], wanted: dict[str, DataFrame]) -> DataFrame:
    for d in dims:
        now = out.groupBy(d).agg(F.sum(F.col("mix_n") * F.col("mix_g")).alias("mix_s"))
        step = now.join(wanted[d], d).select(d, F.when(F.col("mix_s") > 0, F.col("mix_t") / F.col("mix_s")).otherwise(1.0).alias("mix_step"))
        out = out.join(step, d).withColumn("mix_g", F.col("mix_g") * F.col("mix_step")).drop("mix_step")
    return out


def _off(out: DataFrame, dims: list[str], wanted: dict[str, DataFrame]) -> float:
    most = 0.0
    for d in dims:
        now = out.groupBy(d).agg(F.sum(F.col("mix_n") * F.col("mix_g")).alias("mix_s")).join(wanted[d], d)
        most = max(most, now.agg(F.max(F.abs(F.col("mix_s") - F.col("mix_t"))).alias("x")).first()["x"] or 0.0)
    return most


def rake(cells: DataFrame, dims: list[str], targets: dict[str, DataFrame] | None = None, temper: float = 0.7, residual: float = RESIDUAL, narrow: int = NARROW) -> DataFrame:
    """Cells (dims..., mix_n) with the fitted factor mix_g and mix_off, the largest distance of a marginal from its target.

    targets: per dimension a frame (dim, share)."""
    count = cells.count()
    wanted = {d: cut(_wanted(cells, d, targets, temper), "mix-target") for d in dims}
    last = float("inf")
    if count <= narrow:
        row = _Row(cells, dims, wanted)
        off = 0.0 if not count else row.sweep(SERIES)
        for _ in range(MOST):
            if off <= residual or off > 0.99 * last:
                break
            last, off = off, row.sweep(SERIES)
        out = row.cells(off)
    else:
        out = cells.withColumn("mix_g", F.lit(1.0))
        for _ in range(MOST):
            swept = cut(_wide_sweep(out, dims, wanted), "mix-sweep")
            discard(out)
            out, off = swept, _off(swept, dims, wanted)
            if off <= residual or off > 0.99 * last:
                break
            last = off
        out = out.withColumn("mix_off", F.lit(off))
    return out


def calibrate(cells: DataFrame, keep_share: float) -> DataFrame:
    """Adds mix_w = level * mix_g, the expected copies, and mix_p = min(1, mix_w), the chance of one at least.

    The level is such that keep_share of all tokens is expected to stay, repeats not counted. Tokens times mix_w have
    the targets' shares at any level; cells without tokens, which repeats can't help, are not repeated. Each round
    sets the level for the cells that the last one left below one, so rounds end when no cell is added."""
    level, open_cells, held = 0.0, cells.filter("mix_n > 0"), -1
    while True:
        full = F.col("mix_g") * F.lit(level) >= 1
        s = open_cells.agg(
            F.sum("mix_n").alias("all"),
            F.count_if(full).alias("cells"),
            F.sum(F.when(full, F.col("mix_n")).otherwise(0)).alias("full"),
            F.sum(F.when(full, 0.0).otherwise(F.col("mix_n") * F.col("mix_g"))).alias("rest"),
        ).first()  # one row
        if not s["all"] or not s["rest"] or s["cells"] == held:
            break
        held = s["cells"]
        now = (keep_share * s["all"] - s["full"]) / s["rest"]
        if now <= level:
            break
        level = now
    copies = F.lit(level) * F.col("mix_g")
    once = F.least(F.lit(1.0), copies)
    return cells.withColumns({"mix_p": once, "mix_w": F.when(F.col("mix_n") > 0, copies).otherwise(once)})


def mixing_plan(docs: DataFrame, dims: dict[str, F.Column], targets=None, temper: float = 0.7, keep_share: float = 0.8, text_col: str = "text", **how) -> DataFrame:
    """Fitted cells: dims..., mix_n, mix_g, mix_off, mix_p, mix_w."""
    keyed = docs.select(*[F.coalesce(c.cast("string"), F.lit(NONE)).alias(d) for d, c in dims.items()], token_weight(F.col(text_col)).alias("mix_w"))
    cells = cut(keyed.groupBy(*dims).agg(F.sum("mix_w").alias("mix_n")), "mix-cells")
    return calibrate(cut(rake(cells, list(dims), targets, temper, **how), "mix-fitted"), keep_share)


def _drawn(docs: DataFrame, dims: dict[str, F.Column], seed: int, id_col: str, text_col: str, **fit) -> DataFrame:
    """row (all of docs), the dimensions, mix_p, mix_w, mix_kept and mix_copies: no name of docs meets one of these."""
    plan = mixing_plan(docs, dims, text_col=text_col, **fit).select(*dims, "mix_p", "mix_w")
    packed = docs.select(*[F.coalesce(c.cast("string"), F.lit(NONE)).alias(d) for d, c in dims.items()], unit_draw(F.col(id_col), seed).alias("mix_draw"), F.struct("*").alias("row"))
    whole = F.floor("mix_w")
    copies = whole + (F.col("mix_draw") < F.col("mix_w") - whole).cast("long")
    return packed.join(plan, list(dims)).withColumns({"mix_kept": F.col("mix_draw") < F.col("mix_p"), "mix_copies": copies})


def _default_dims(text_col: str) -> dict[str, F.Column]:
    return {"mix_source": F.col("source"), "mix_lang": F.col("lang"), "mix_topic": surface_topic(F.col(text_col))}


def _own(name: str) -> F.Column:
    return F.col(f"row.`{name}`")


def mix(docs: DataFrame, dims: dict[str, F.Column] | None = None, seed: int = 7, id_col: str = "doc_id", text_col: str = "text", **fit) -> DataFrame:
    """All columns of docs with the dimensions, mix_p (keep probability), mix_w (expected copies), mix_kept and mix_copies."""
    dims = dims or _default_dims(text_col)
    added = [*dims, "mix_p", "mix_w", "mix_kept", "mix_copies"]
    return _drawn(docs, dims, seed, id_col, text_col, **fit).select(*[_own(c) for c in docs.columns if c not in added], *added)


def keep_mixed(docs: DataFrame, dims: dict[str, F.Column] | None = None, seed: int = 7, id_col: str = "doc_id", text_col: str = "text", **fit) -> DataFrame:
    """The drawn rows of docs, each as often as it is drawn, with just their own columns, whatever these are called."""
    drawn = _drawn(docs, dims or _default_dims(text_col), seed, id_col, text_col, **fit).filter("mix_copies > 0")
    return drawn.select("row", F.explode(F.sequence(F.lit(1), F.col("mix_copies").cast("int")))).select("row.*")


def mixing_report(docs: DataFrame, seed: int = 7) -> DataFrame:
    """The query's rows: every document's cell, probability, decision and number of copies."""
    return mix(docs.select("doc_id", "text", "lang", "source"), seed=seed).select("doc_id", "mix_source", "mix_lang", "mix_topic", F.round("mix_p", 6).alias("keep_probability"), F.col("mix_kept").alias("kept"), F.col("mix_copies").alias("copies"))


def oracle(source: str = "documents", columns: str | None = None, temper: float = 0.7, sweeps: int = 64, keep_share: float = 0.8, seed: int = 7, rounds: int = 12) -> str:
    """The same fit in DuckDB: sweeps and water levels unrolled. columns: what to return of rows drawn once at least; None: the report."""
    dims = ("mix_source", "mix_lang", "mix_topic")
    sql = [
        f"""k AS (SELECT *, coalesce(source, '{NONE}') AS mix_source, coalesce(lang, '{NONE}') AS mix_lang,
 CASE WHEN contains(coalesce(text,''), 'icense') THEN 'legal' WHEN contains(coalesce(text,''), '@') OR contains(coalesce(text,''), 'http') THEN 'contact' WHEN contains(coalesce(text,''), '|') THEN 'tabular' ELSE 'prose' END AS mix_topic,
 CASE WHEN coalesce(text,'') = '' THEN 0 ELSE length(text) - length(replace(text, ' ', '')) + 1 END AS w FROM {source})""",
        f"c0 AS MATERIALIZED (SELECT {', '.join(dims)}, CAST(sum(w) AS DOUBLE) AS n, CAST(1 AS DOUBLE) AS g FROM k GROUP BY ALL)",
    ]
    for d in dims:
        sql.append(f"t_{d} AS MATERIALIZED (SELECT {d}, CASE WHEN s > 0 THEN pow(s, {temper}) / sum(pow(s, {temper})) OVER () ELSE 0 END AS t FROM (SELECT {d}, sum(n) AS s FROM c0 GROUP BY {d}))")
    at = 0
    for _ in range(sweeps):
        for d in dims:
            sql.append(f"c{at + 1} AS MATERIALIZED (SELECT c.{', c.'.join(dims)}, c.n, c.g * CASE WHEN s.s > 0 THEN t.t / s.s ELSE 1 END AS g FROM c{at} c JOIN (SELECT {d}, sum(n * g) AS s FROM c{at} GROUP BY {d}) s ON c.{d} = s.{d} JOIN t_{d} t ON c.{d} = t.{d})")
            at += 1
    sql.append("l0 AS (SELECT CAST(0 AS DOUBLE) AS v)")
    for i in range(rounds):
        sql.append(f"l{i + 1} AS MATERIALIZED (SELECT greatest(max(l.v), coalesce(({keep_share} * sum(n) - sum(CASE WHEN g * l.v >= 1 THEN n ELSE 0 END)) / nullif(sum(CASE WHEN g * l.v >= 1 THEN 0 ELSE n * g END), 0), max(l.v))) AS v FROM c{at}, l{i} l WHERE n > 0)")
    sql.append(f"p AS (SELECT {', '.join(dims)}, least(1, l.v * g) AS mix_p, CASE WHEN n > 0 THEN l.v * g ELSE least(1, l.v * g) END AS mix_w FROM c{at}, l{rounds} l)")
    draw = f"(CAST('0x' || substr(md5('{seed}:' || coalesce(CAST(doc_id AS VARCHAR), 'null')), 1, 12) AS BIGINT) / CAST(281474976710656 AS DOUBLE))"
    sql.append(f"r AS (SELECT k.*, p.mix_p, {draw} < p.mix_p AS mix_kept, CAST(floor(p.mix_w) AS BIGINT) + CASE WHEN {draw} < p.mix_w - floor(p.mix_w) THEN 1 ELSE 0 END AS copies FROM k JOIN p USING ({', '.join(dims)}))")
    head = f"SELECT {columns} FROM r WHERE copies > 0" if columns else f"SELECT doc_id, {', '.join(dims)}, round(mix_p, 6) AS keep_probability, mix_kept AS kept, CAST(copies AS BIGINT) AS copies FROM r"
    return "WITH " + ",\n".join(sql) + "\n" + head
