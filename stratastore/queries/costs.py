"""The cost model, the measures, and the experiments."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import rolling, udfs
from ..operators import chunkers, measures, tree
from ..params import SCHEMES, StoreParams
from ..plans import analytic, lineage, workloads
from ..sources import contents as src
from ..sources import random_source
from . import oracle as o
from . import query
from .core import CDC, CUT, FIXED, TOP

# ---- the model ----------------------------------------------------------------------------------

SIZES = (64, 128, 256, 1024)
LENGTHS = (1, 64, 129, 4096, 16384, 131072, 1048576, 10485760)
_CELLS = "(VALUES " + ", ".join(f"({s})" for s in SIZES) + ") a(s), (VALUES " + ", ".join(f"({n})" for n in LENGTHS) + ") b(n)"


def _cells(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(s, n) for s in SIZES for n in LENGTHS], "s int, n int")


def _given_cells(spark: SparkSession, d: str) -> DataFrame:
    lengths = src.documents(spark, d).where("n > 0").select("n").distinct()
    return lengths.select(F.explode(F.array(*[F.lit(s) for s in SIZES])).alias("s"), "n")


def _height_sql(n: str = "n", s: str = "s") -> str:
    return "CASE " + " ".join(f"WHEN {n} <= {s} * pow({s} / 32.0, {h}) THEN {h}" for h in range(24)) + " ELSE 24 END"


_H = f"(SELECT s, n, {_height_sql()} AS h FROM {_CELLS})"
#: The same cells with the lengths of the given documents, each length once.
_GIVEN_H = _H.replace(_CELLS, "(VALUES " + ", ".join(f"({s})" for s in SIZES) + ") a(s), (SELECT DISTINCT octet_length(encode(text)) AS n FROM documents WHERE text <> '') b")
_NEW = "(1 + list_sum(list_transform(range(h), lambda k: 1 + 144 * (1 - 1 / (s * pow(s / 32.0, k))) / (s * pow(s / 32.0, k)))))"
_NEW = f"coalesce({_NEW}, 1.0)"


def _model(name: str, value: str, column, given: bool = False) -> None:
    """given: over the lengths of the documents, not over those of ``LENGTHS``."""

    @query(f"SELECT s, n, CAST({value} AS DOUBLE) AS value FROM {_GIVEN_H if given else _H}", name)
    def cell(spark: SparkSession, d: str) -> DataFrame:
        return (_given_cells(spark, d) if given else _cells(spark)).select("s", "n", column(F.col("n"), F.col("s")).cast("double").alias("value"))


_model("model_height", "h", lambda n, s: analytic.height_col(n, s))
_model("model_expected_nodes", "ceil(2.0 * n / s)", lambda n, s: F.ceil(n * 2 / s), True)
_model("model_storage_full", "(32 + s) * ceil(2.0 * n / s)", analytic.storage_full_col)
_model("model_added_fixed", "(32 + s) * (h + 1)", analytic.added_fixed_col, True)
_model("model_new_nodes_cdc", _NEW, analytic.new_nodes_cdc_col)
_model("model_added_cdc", f"(32 + 2 * s) * {_NEW}", analytic.added_cdc_col, True)


@query(f"SELECT s, n, delta, CAST(CASE WHEN delta = 1 THEN (32 + 2 * s) * {_NEW} WHEN delta >= n THEN (32 + s) * ceil(2.0 * n / s) ELSE 2 * (32 + 2 * s) * {_NEW} + (32 + s) * ceil(2.0 * (delta - 2) / s) END AS DOUBLE) AS cdc, CAST(CASE WHEN delta = 1 THEN (32 + s) * (h + 1) WHEN delta >= n THEN (32 + s) * ceil(2.0 * n / s) ELSE 2 * (32 + s) * (h + 1) + (32 + s) * ceil(2.0 * (delta - 2) / s) END AS DOUBLE) AS fixed FROM {_GIVEN_H}, (VALUES (1), (2), (16), (256), (4096)) c(delta)")
def model_added_delta(spark: SparkSession, d: str) -> DataFrame:
    deltas = spark.createDataFrame([(x,) for x in (1, 2, 16, 256, 4096)], "delta int")
    n, s, x = F.col("n"), F.col("s"), F.col("delta")
    return _given_cells(spark, d).crossJoin(F.broadcast(deltas)).select("s", "n", "delta", analytic.added_delta_col(n, s, x).alias("cdc"), analytic.added_delta_col(n, s, x, True).alias("fixed"))


#: Levels at which documents are cut, and how many documents are.
_LEVELS = f"(SELECT s, k, count(*) AS contents FROM (SELECT s, n, {_height_sql()} AS h FROM (VALUES (64), (128), (256), (1024)) a(s), (SELECT octet_length(encode(text)) AS n FROM documents WHERE text <> '') b), range(24) c(k) WHERE k < h GROUP BY s, k)"
_P = "(1 / (s * pow(s / 32.0, k)))"


def _given_levels(spark: SparkSession, d: str) -> DataFrame:
    lengths = src.documents(spark, d).where("n > 0").select(F.explode(F.array(*[F.lit(s) for s in SIZES])).alias("s"), "n").groupBy("s", "n").agg(F.count("*").alias("c"))
    levels = lengths.withColumn("h", analytic.height_col(F.col("n"), F.col("s"))).where("h > 0").withColumn("k", F.explode(F.sequence(F.lit(0), F.col("h") - 1)))
    return levels.groupBy("s", "k").agg(F.sum("c").alias("contents"))


@query(f"SELECT s, CAST(k AS INTEGER) AS k, contents, {_P} AS p, (1 - {_P}) * {_P} AS flip, 2 / {_P} - 1 AS mean_at_random, 2 * s AS size_at_random FROM {_LEVELS}")
def model_boundary_prob(spark: SparkSession, d: str) -> DataFrame:
    """Chances of a boundary, of a gained one, and the chunk at a random place, by level of the documents' trees."""
    length = F.col("s").cast("double") * F.pow(F.col("s").cast("double") / 32, F.col("k"))
    return _given_levels(spark, d).select("s", "k", "contents", (1 / length).alias("p"), ((1 - 1 / length) / length).alias("flip"), (2 * length - 1).alias("mean_at_random"), (2 * F.col("s")).alias("size_at_random"))


@query("SELECT s, CAST(h AS INTEGER) AS h, CAST(floor(s * pow(s / 32.0, h)) AS BIGINT) AS longest FROM (VALUES (64), (128), (256), (1024)) a(s), range(6) b(h)")
def model_height_thresholds(spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame([(s, h, t) for s in SIZES for h, t in enumerate(analytic.height_thresholds(s, 5))], "s int, h int, longest bigint")


@query("SELECT CAST(c AS INTEGER) AS c, (1 / 256.0) * pow(1 - 1 / 256.0, c - 1) AS law, c * pow(1 / 256.0, 2) * pow(1 - 1 / 256.0, c - 1) AS share FROM range(1, 2049) r(c)")
def model_length_law(spark: SparkSession, d: str) -> DataFrame:
    """The law of chunk lengths at S = 256, and the share of bytes by length."""
    c, p = F.col("id").cast("double"), F.lit(1 / 256)
    return spark.range(1, 2049).select(F.col("id").cast("int").alias("c"), (p * F.pow(1 - p, c - 1)).alias("law"), (c * p * p * F.pow(1 - p, c - 1)).alias("share"))


@query(f"SELECT s, CAST(k AS INTEGER) AS k, contents, (1 - {_P}) * {_P} AS gained, 1 + 144 * (1 - {_P}) * {_P} AS new_chunks FROM {_LEVELS}")
def model_cut_flip(spark: SparkSession, d: str) -> DataFrame:
    """Chance that a changed window gains a boundary, and the chunks that one changed byte makes anew, by level."""
    p = 1 / (F.col("s").cast("double") * F.pow(F.col("s").cast("double") / 32, F.col("k")))
    return _given_levels(spark, d).select("s", "k", "contents", ((1 - p) * p).alias("gained"), (1 + F.lit(144.0) * (1 - p) * p).alias("new_chunks"))


@query(o.with_(o.cdc_spans(o.DOCUMENTS, CUT, 1)) + """SELECT CAST(x AS BIGINT) AS longest, any_value(share) AS share, sum(CASE WHEN e - s <= x THEN e - s ELSE 0 END) / sum(e - s) AS found FROM n,
  (SELECT x, sum(c * pow(1 / 256.0, 2) * pow(1 - 1 / 256.0, c - 1)) AS share FROM range(1, 2049) r(c), (VALUES (64), (256), (512), (1024), (2048)) t(x) WHERE c <= x GROUP BY x) WHERE level = 0 GROUP BY x""")
def length_biased_share(spark: SparkSession, d: str) -> DataFrame:
    """Share of bytes in chunks up to some lengths, S = 256: by the law, and of the documents' chunks."""
    shares = [(x, sum(analytic.length_biased_share(c, 0, 256) for c in range(1, x + 1))) for x in (64, 256, 512, 1024, 2048)]
    size, total = F.col("end_pos") - F.col("start_pos"), F.sum("size")
    lengths = chunkers.cdc(src.documents(spark, d), CUT).select(size.alias("size"))
    found = lengths.agg(*[(F.sum(F.when(F.col("size") <= x, F.col("size")).otherwise(0)) / total).alias(str(x)) for x, _ in shares], total.alias("total")).where("total IS NOT NULL")
    rows = F.array(*[F.struct(F.lit(x).cast("long").alias("longest"), F.lit(share).alias("share"), F.col(str(x)).alias("found")) for x, share in shares])
    return found.select(F.inline(rows))


# ---- measures -----------------------------------------------------------------------------------

EXACT = ("whole", "fixed", "fixed_tree")


def _grid(schemes: tuple[str, ...], sizes: tuple[int, ...] = (256,)) -> list[StoreParams]:
    return [StoreParams(chunk=s, scheme=x, ring="m31") for x in schemes for s in sizes]


#: Levels spelled out by chunk size.
TOPS = {64: 16, 128: 8, 256: 6, 512: 4, 1024: 4, 2048: 3, 4096: 3}


def _grid_sql(contents: str, schemes: tuple[str, ...], sizes: tuple[int, ...] = (256,), longest: int | None = None) -> str:
    """longest: length of the longest content, where it is known: its height is all the levels there are."""
    tops = TOPS if longest is None else {s: StoreParams(chunk=s).height(longest) for s in sizes}
    return o.grid(contents, _grid(schemes, sizes), tops)[0]


_DISTINCT = "(SELECT DISTINCT scheme, s, key, size FROM grid)"
_COST = f"SELECT scheme, s, count(*) AS pairs, CAST(sum(size + 32) AS BIGINT) AS cost FROM {_DISTINCT} GROUP BY scheme, s"


@query(_grid_sql(o.DOCUMENTS, SCHEMES) + _COST)
def storage_cost(spark: SparkSession, d: str) -> DataFrame:
    return measures.storage_cost(tree.build_grid(src.documents(spark, d), _grid(SCHEMES)), ["scheme", "s"])


@query(_grid_sql(o.DOCUMENTS, EXACT, (64, 128, 256, 1024)) + _COST)
def storage_cost_sizes(spark: SparkSession, d: str) -> DataFrame:
    return measures.storage_cost(tree.build_grid(src.documents(spark, d), _grid(EXACT, (64, 128, 256, 1024))), ["scheme", "s"])


@query(o.with_(o.keyed(o.DOCUMENTS, CDC, TOP, "_a"), o.keyed(o.PAGES, CDC, TOP, "_b")) + "SELECT count(*) AS pairs, CAST(sum(size + 32) AS BIGINT) AS cost FROM (SELECT DISTINCT key, size FROM k_b WHERE key NOT IN (SELECT key FROM k_a))")
def added_cost(spark: SparkSession, d: str) -> DataFrame:
    """What all pages add to all documents."""
    return measures.added_cost(tree.build(src.documents(spark, d), CDC), tree.build(src.pages(spark, d), CDC))


@query(_grid_sql(o.PAGES, EXACT) + "SELECT scheme, s, content_id, CAST(sum(size + 32) AS BIGINT) AS cost, sum(size + 32) / octet_length(any_value(body)) AS expansion FROM (SELECT DISTINCT scheme, s, content_id, key, size FROM grid) JOIN (SELECT content_id, body FROM (" + o.PAGES + ")) USING (content_id) GROUP BY scheme, s, content_id")
def expansion_factor(spark: SparkSession, d: str) -> DataFrame:
    return workloads.expansion_experiment(src.pages(spark, d), _grid(EXACT)).drop("n")


_FIRST = """, first AS (SELECT scheme, s, key, min(version) AS version, any_value(size) AS size FROM grid GROUP BY scheme, s, key),
per AS (SELECT scheme, s, version, CAST(sum(size + 32) AS BIGINT) AS added FROM first GROUP BY scheme, s, version),
have AS (SELECT DISTINCT scheme, s, version FROM grid),
cum AS (SELECT scheme, s, version, coalesce(added, 0) AS added, CAST(sum(coalesce(added, 0)) OVER (PARTITION BY scheme, s ORDER BY version) AS BIGINT) AS cost FROM have LEFT JOIN per USING (scheme, s, version))
"""


def _cumulative_sql(contents: str, schemes: tuple[str, ...] = EXACT, sizes: tuple[int, ...] = (256,), longest: int | None = None) -> str:
    return _grid_sql(contents, schemes, sizes, longest).rstrip() + _FIRST


@query(_cumulative_sql(o.EVENTS) + "SELECT * FROM cum")
def cumulative_cost(spark: SparkSession, d: str) -> DataFrame:
    return workloads.history_costs(src.event_history(spark, d), _grid(EXACT))


@query(_cumulative_sql(o.EVENTS, ("fixed", "fixed_tree"), (128, 256)) + "SELECT s, min(a.version) AS version FROM cum a JOIN cum b USING (s, version) WHERE a.scheme = 'fixed_tree' AND b.scheme = 'fixed' AND a.cost <= b.cost GROUP BY s")
def break_even(spark: SparkSession, d: str) -> DataFrame:
    """From which day the tree is no dearer than the flat scheme."""
    costs = workloads.history_costs(src.event_history(spark, d), _grid(("fixed", "fixed_tree"), (128, 256)))
    return measures.break_even(costs.where("scheme = 'fixed_tree'"), costs.where("scheme = 'fixed'"), ["s"])


@query(_cumulative_sql(o.EVENTS, ("whole", "fixed_tree")) + "SELECT s, min(a.version) AS version FROM cum a JOIN cum b USING (s, version) WHERE a.scheme = 'fixed_tree' AND b.scheme = 'whole' AND 2 * a.cost <= b.cost GROUP BY s")
def break_even_half(spark: SparkSession, d: str) -> DataFrame:
    """From which day the tree costs at most half of whole contents."""
    costs = workloads.history_costs(src.event_history(spark, d), _grid(("whole", "fixed_tree")))
    return measures.break_even(costs.where("scheme = 'fixed_tree'"), costs.where("scheme = 'whole'"), ["s"], 0.5)


_BYTES = f"(SELECT sum(octet_length(body)) FROM ({o.DOCUMENTS}))"


@query(_grid_sql(o.DOCUMENTS, SCHEMES) + f"SELECT scheme, CAST(sum(size + 32) - {_BYTES} AS BIGINT) AS overhead FROM {_DISTINCT} GROUP BY scheme")
def dedup_overhead(spark: SparkSession, d: str) -> DataFrame:
    docs = src.documents(spark, d)
    cost = measures.storage_cost(tree.build_grid(docs, _grid(SCHEMES)), ["scheme"])
    return cost.crossJoin(docs.agg(F.sum("n").alias("n"))).select("scheme", (F.col("cost") - F.col("n")).alias("overhead"))


@query(o.with_(o.keyed(o.DOCUMENTS, CDC, TOP)) + f"SELECT CAST({_BYTES} AS BIGINT) AS bytes_in, CAST(sum(size + 32) AS BIGINT) AS cost, {_BYTES} / sum(size + 32) AS ratio, 1 - sum(size + 32) / {_BYTES} AS saved FROM (SELECT DISTINCT key, size FROM k)")
def dedup_ratio(spark: SparkSession, d: str) -> DataFrame:
    docs = src.documents(spark, d)
    return measures.dedup_ratio(tree.build(docs, CDC), docs)


@query(o.with_(o.keyed(o.DOCUMENTS, CDC, TOP)) + "SELECT level, count(*) AS nodes, count(DISTINCT key) AS distinct_nodes, avg(e - s) AS avg_length, avg(size) AS avg_size, avg(children) AS avg_children FROM k GROUP BY level")
def level_profile(spark: SparkSession, d: str) -> DataFrame:
    return measures.level_profile(tree.build(src.documents(spark, d), CDC))


@query(o.with_(o.cdc_spans(o.DOCUMENTS, CUT, 1)) + "SELECT (e - s) // 32 AS bin, count(*) AS chunks, CAST(sum(e - s) AS BIGINT) AS bytes FROM n WHERE level = 0 GROUP BY 1")
def chunk_length_histogram(spark: SparkSession, d: str) -> DataFrame:
    """Chunk lengths in bins of 32 bytes, by chunks and by bytes."""
    size = F.col("end_pos") - F.col("start_pos")
    return chunkers.cdc(src.documents(spark, d), CUT).groupBy(F.floor(size / 32).cast("long").alias("bin")).agg(F.count("*").alias("chunks"), F.sum(size).alias("bytes"))


@query(o.with_(o.cdc_spans(o.DOCUMENTS, CUT, 1)) + "SELECT avg(e - s) AS mean, sum((e - s) * (e - s)) / sum(e - s) AS mean_at_random FROM n WHERE level = 0")
def length_biased_mean(spark: SparkSession, d: str) -> DataFrame:
    """Mean chunk length, and that of the chunk under a random byte."""
    size = F.col("end_pos") - F.col("start_pos")
    return chunkers.cdc(src.documents(spark, d), CUT).agg(F.avg(size).alias("mean"), (F.sum(size * size) / F.sum(size)).alias("mean_at_random"))


_RANDOM = o.random_contents(0, 16384, 20)


def _loess_sql(points: str, x: str) -> str:
    return f"""WITH p AS ({points}),
r AS (SELECT a.x0, p.x, p.y, row_number() OVER (PARTITION BY a.x0 ORDER BY abs(p.x - a.x0), p.x, p.y) AS rk, (SELECT count(*) FROM p) AS t FROM p, (SELECT DISTINCT x AS x0 FROM p) a),
q AS (SELECT x0, y, x, abs(x - x0) AS dd, max(abs(x - x0)) OVER (PARTITION BY x0) AS reach FROM r WHERE rk <= greatest(ceil(t * 0.75), 1)),
w AS (SELECT x0, y, CASE WHEN reach > 0 THEN pow(1 - pow(dd / reach / 1.0000001, 3), 3) ELSE 1.0 END AS w, CASE WHEN reach > 0 THEN (x - x0) / reach ELSE 0.0 END AS u FROM q),
m AS (SELECT x0, sum(w) s0, sum(w * u) s1, sum(w * u * u) s2, sum(w * pow(u, 3)) s3, sum(w * pow(u, 4)) s4, sum(w * y) b0, sum(w * y * u) b1, sum(w * y * u * u) b2 FROM w GROUP BY x0)
SELECT x0 AS {x}, round(CASE WHEN abs(s0 * (s2 * s4 - s3 * s3) - s1 * (s1 * s4 - s2 * s3) + s2 * (s1 * s3 - s2 * s2)) > 1e-9
  THEN (b0 * (s2 * s4 - s3 * s3) - s1 * (b1 * s4 - b2 * s3) + s2 * (b1 * s3 - b2 * s2)) / (s0 * (s2 * s4 - s3 * s3) - s1 * (s1 * s4 - s2 * s3) + s2 * (s1 * s3 - s2 * s2))
  WHEN abs(s0 * s2 - s1 * s1) > 1e-9 THEN (b0 * s2 - s1 * b1) / (s0 * s2 - s1 * s1) ELSE b0 / s0 END, 3) AS fit FROM m"""


@query(_loess_sql("SELECT CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS DOUBLE) AS x, CAST(count(*) AS DOUBLE) AS y FROM events GROUP BY CAST(ts AS DATE)", "day"))
def loess_events(spark: SparkSession, d: str) -> DataFrame:
    """LOESS of events a day."""
    per = src.table(spark, d, "events").groupBy(F.to_date("ts").alias("day")).agg(F.count("*").alias("events"))
    points = per.select(F.datediff("day", F.lit("2024-01-01").cast("date")).cast("double").alias("day"), F.col("events").cast("double").alias("events"))
    return measures.loess(points, [], "day", "events").select("day", F.round("fit", 3).alias("fit"))


@query()
def loess_cost(spark: SparkSession, d: str) -> DataFrame:
    """LOESS of the mean cost added by one changed byte of the documents over their length class, by chunk size."""
    means = _one_byte_given(spark, d).groupBy("s", F.col("longest").alias("n")).agg(F.avg("added").alias("added"))
    return measures.loess(means, ["s"], "n", "added")


@query("""WITH c AS (SELECT lang, CAST(octet_length(encode(text)) AS DOUBLE) AS y FROM documents WHERE text IS NOT NULL),
q AS (SELECT lang, count(*) AS samples, quantile_cont(y, 0.25) AS q1, quantile_cont(y, 0.5) AS q2, quantile_cont(y, 0.75) AS q3 FROM c GROUP BY lang)
SELECT lang, samples, q1, q2, q3, min(CASE WHEN y BETWEEN q1 - 1.5 * (q3 - q1) AND q3 + 1.5 * (q3 - q1) THEN y END) AS low, max(CASE WHEN y BETWEEN q1 - 1.5 * (q3 - q1) AND q3 + 1.5 * (q3 - q1) THEN y END) AS high,
  CAST(sum(CASE WHEN y BETWEEN q1 - 1.5 * (q3 - q1) AND q3 + 1.5 * (q3 - q1) THEN 0 ELSE 1 END) AS BIGINT) AS outliers FROM c JOIN q USING (lang) GROUP BY lang, samples, q1, q2, q3""")
def boxplot_lengths(spark: SparkSession, d: str) -> DataFrame:
    docs = src.table(spark, d, "documents").where("text IS NOT NULL").select("lang", F.octet_length(F.encode("text", "utf-8")).cast("double").alias("y"))
    return measures.boxplot(docs, ["lang"], "y")


@query(_grid_sql(o.ORDERS, EXACT, (256, 1024, 4096)) + f", t AS (SELECT scheme, s, CAST(sum(size + 32) AS BIGINT) AS cost FROM {_DISTINCT} GROUP BY scheme, s) SELECT scheme, arg_min(s, cost * 100000 + s) AS s, min(cost) AS cost FROM t GROUP BY scheme")
def best_chunk_size(spark: SparkSession, d: str) -> DataFrame:
    costs = workloads.history_totals(src.order_history(spark, d), _grid(EXACT, (256, 1024, 4096)))
    return measures.best_chunk_size(costs, ["scheme"])


# ---- experiments --------------------------------------------------------------------------------


def _one_byte(spark: SparkSession, lengths: tuple[int, ...] = (4096, 16384, 65536, 131072), sizes: tuple[int, ...] = (64, 128, 256), runs: int = 20) -> DataFrame:
    params = [StoreParams(chunk=s) for s in sizes]
    out = None
    for n in lengths:
        part = workloads.edit_experiment(spark, "overwrite", 1, n, params, runs)
        out = part if out is None else out.unionByName(part)
    return out


def _one_byte_given(spark: SparkSession, d: str, sizes: tuple[int, ...] = (64, 128, 256)) -> DataFrame:
    """(scheme, s, n, run, added, model, longest): one byte changed in each document; longest: the power of two from its length on."""
    docs = src.documents(spark, d).where("n > 0")
    cells = workloads.edit_costs_in_place(workloads.edited(docs, "overwrite", 1), [StoreParams(chunk=s) for s in sizes])
    return cells.withColumn("longest", F.pow(F.lit(2.0), F.length(F.bin(F.col("n") - 1)) - (F.col("n") == 1).cast("int")).cast("long"))


@query()
def bound_check(spark: SparkSession, d: str) -> DataFrame:
    """Whether the mean added cost of one changed byte of the documents is under the model's bound, by length class."""
    return measures.bound_check(_one_byte_given(spark, d), ["s", "longest"], "added", "model").select("s", F.col("longest").alias("n"), "samples", "under", "mean", "mean_bound", "holds")


@query()
def boxplot_cost(spark: SparkSession, d: str) -> DataFrame:
    """Box plots of the added cost of one changed byte of the documents, by length class."""
    cells = _one_byte_given(spark, d).select("s", F.col("longest").alias("n"), "added")
    return measures.boxplot(cells, ["s", "n"], "added")


def _cells_of(spark: SparkSession, kind: str, deltas: tuple[int, ...], lengths: tuple[int, ...], params: list[StoreParams], runs: int = 20) -> DataFrame:
    """All cells and runs of an edit experiment over several lengths; a delta of 0 is the whole content."""
    out = None
    for n in lengths:
        for delta in {min(x or n, n) for x in deltas}:
            part = workloads.edit_experiment(spark, kind, delta, n, params, runs).withColumn("delta", F.lit(delta))
            out = part if out is None else out.unionByName(part)
    return out


def _curve(cells: DataFrame, y: str) -> DataFrame:
    """(scheme, s, n, mean, fit): means of the runs and LOESS over content length."""
    means = cells.groupBy("scheme", "s", "n").agg(F.avg(y).alias("mean"))
    return means.join(measures.loess(cells, ["scheme", "s"], "n", y).withColumn("n", F.col("n").cast("long")), ["scheme", "s", "n"])


@query()
def wl_overwrite_delta(spark: SparkSession, d: str) -> DataFrame:
    """Runs of overwriting delta random bytes of random contents, one to all: mean added cost by scheme, S, length and delta, with the model's."""
    params = [StoreParams(chunk=s, scheme=x) for s in (64, 128, 256) for x in ("fixed_tree", "cdc_tree")]
    cells = _cells_of(spark, "overwrite", (1, 16, 256, 4096, 0), (4096, 32768), params)
    return cells.groupBy("scheme", "s", "n", "delta").agg(F.count("*").alias("runs"), F.avg("added").alias("mean"), F.stddev("added").alias("deviation"), F.first("model").alias("model"))


@query()
def wl_fig_one_byte(spark: SparkSession, d: str) -> DataFrame:
    """The curve of the added cost of one changed byte: mean, model and LOESS by length and S."""
    cells = _one_byte(spark, sizes=(64, 128, 256, 512, 1024))
    curve = measures.loess(cells, ["s"], "n", "added")
    return cells.groupBy("s", "n").agg(F.avg("added").alias("mean"), F.first("model").alias("model")).join(curve, ["s", "n"])


@query()
def wl_fig_delta_box(spark: SparkSession, d: str) -> DataFrame:
    """S = 128: box plots of the added cost by length and delta up to the whole content, the model's bound, and how many runs are above it."""
    out = _cells_of(spark, "overwrite", (1, 64, 1024, 16384, 0), (1024, 4096, 32768, 131072), [StoreParams(chunk=128)])
    box = measures.boxplot(out, ["n", "delta"], "added")
    bound = out.groupBy("n", "delta").agg(F.first("model").alias("model"), F.sum((F.col("added") > F.col("model")).cast("long")).alias("above"))
    return box.join(bound, ["n", "delta"])


CURVE_LENGTHS = (1024, 4096, 16384, 65536, 262144)


@query()
def wl_fig_expansion(spark: SparkSession, d: str) -> DataFrame:
    """Expansion of random contents over their length, all schemes, 20 runs: means and LOESS."""
    out = None
    for n in CURVE_LENGTHS:
        part = workloads.expansion_experiment(src.random_contents(spark, 0, n, 20), workloads.grid(SCHEMES, (64, 128, 256)))
        out = part if out is None else out.unionByName(part)
    return _curve(out, "expansion")


@query()
def wl_fig_overwrite(spark: SparkSession, d: str) -> DataFrame:
    """One byte overwritten, over content length, all schemes, 20 runs: means and LOESS."""
    return _curve(_cells_of(spark, "overwrite", (1,), CURVE_LENGTHS, workloads.grid(SCHEMES, (64, 256, 1024))), "added")


@query()
def wl_fig_insert(spark: SparkSession, d: str) -> DataFrame:
    """One byte put in, over content length, all schemes, 20 runs: means and LOESS."""
    return _curve(_cells_of(spark, "insert", (1,), CURVE_LENGTHS, workloads.grid(SCHEMES, (64, 256, 1024))), "added")


def _expansion_sql(contents: str, schemes: tuple[str, ...] = EXACT, longest: int | None = None) -> str:
    return _grid_sql(contents, schemes, (64, 128, 256), longest) + "SELECT scheme, s, avg(cost / n) AS expansion FROM (SELECT scheme, s, content_id, sum(size + 32) AS cost FROM (SELECT DISTINCT scheme, s, content_id, key, size FROM grid) GROUP BY scheme, s, content_id) JOIN (SELECT content_id, octet_length(body) AS n FROM (" + contents + ") WHERE octet_length(body) > 0) USING (content_id) GROUP BY scheme, s"


def _mean_expansion(contents: DataFrame, schemes: tuple[str, ...]) -> DataFrame:
    return workloads.expansion_experiment(contents, _grid(schemes, (64, 128, 256))).groupBy("scheme", "s").agg(F.avg("expansion").alias("expansion"))


@query(_expansion_sql(_RANDOM, SCHEMES, 16384))
def wl_expansion(spark: SparkSession, d: str) -> DataFrame:
    """Expansion of random contents of 16 KiB, 20 runs, all schemes in the ring that SQL can follow."""
    return _mean_expansion(src.random_contents(spark, 0, 16384, 20), SCHEMES)


@query()
def wl_expansion_all(spark: SparkSession, d: str) -> DataFrame:
    """The same with all five schemes."""
    return _mean_expansion(src.random_contents(spark, 0, 65536, 20), SCHEMES)


@query(_expansion_sql(o.EMBEDDINGS))
def wl_expansion_embeddings(spark: SparkSession, d: str) -> DataFrame:
    return _mean_expansion(src.embedding_blobs(spark, d), EXACT)


@query(_expansion_sql(o.PAGES))
def wl_expansion_pages(spark: SparkSession, d: str) -> DataFrame:
    return _mean_expansion(src.pages(spark, d), EXACT)


def _place_sql(seed: str, n: str) -> str:
    return f"(CAST('0x' || sha256(CAST({seed} AS VARCHAR) || ':place')[1:12] AS BIGINT) % ({n}))"


def _edit_sql(kind: str) -> str:
    base = f"SELECT version AS run, body, octet_length(body) AS n FROM ({_RANDOM})"
    new = "unhex(sha256(CAST(run AS VARCHAR) || ':new:0')[1:2])"
    if kind == "overwrite":
        flip = "unhex(translate(hex(body[pos + 1:pos + 1]), '0123456789ABCDEF', 'FEDCBA9876543210'))"
        other = f"CASE WHEN {new} = body[pos + 1:pos + 1] THEN {flip} ELSE {new} END"
        after = f"SELECT CAST(run AS VARCHAR) AS content_id, 1 AS version, body[1:pos] || {other} || body[pos + 2:] AS body FROM (SELECT run, body, {_place_sql('run', 'n')} AS pos FROM ({base}))"
    else:
        after = f"SELECT CAST(run AS VARCHAR) AS content_id, 1 AS version, body[1:pos] || {new} || body[pos + 1:] AS body FROM (SELECT run, body, {_place_sql('run', 'n + 1')} AS pos FROM ({base}))"
    before = f"SELECT CAST(run AS VARCHAR) AS content_id, 0 AS version, body FROM ({base})"
    return _grid_sql(f"{before} UNION ALL {after}", SCHEMES, (64, 256), 16385) + """SELECT scheme, s, run, CAST(sum(CASE WHEN version = 1 THEN size + 32 ELSE 0 END) AS BIGINT) AS added FROM
  (SELECT scheme, s, CAST(content_id AS BIGINT) AS run, key, min(version) AS version, any_value(size) AS size FROM grid GROUP BY scheme, s, content_id, key) GROUP BY scheme, s, run"""


@query(_edit_sql("overwrite"))
def wl_overwrite_one(spark: SparkSession, d: str) -> DataFrame:
    """One byte of 16 KiB of random bytes changed: added cost, run by run, all schemes in the ring that SQL can follow."""
    return workloads.edit_experiment(spark, "overwrite", 1, 16384, _grid(SCHEMES, (64, 256))).select("scheme", "s", "run", "added")


@query(_edit_sql("insert"))
def wl_insert_one(spark: SparkSession, d: str) -> DataFrame:
    return workloads.edit_experiment(spark, "insert", 1, 16384, _grid(SCHEMES, (64, 256))).select("scheme", "s", "run", "added")


def _all_schemes(spark: SparkSession, kind: str) -> DataFrame:
    cells = workloads.edit_experiment(spark, kind, 1, 131072, workloads.grid(SCHEMES, (64, 256, 1024)))
    return measures.summarise_runs(cells, ["scheme", "s", "n"], "added")


@query()
def wl_overwrite_schemes(spark: SparkSession, d: str) -> DataFrame:
    """All five schemes: one byte changed in 128 KiB."""
    return _all_schemes(spark, "overwrite")


@query()
def wl_insert_schemes(spark: SparkSession, d: str) -> DataFrame:
    """All five schemes: one byte put into 128 KiB."""
    return _all_schemes(spark, "insert")


@query()
def wl_overwrite_documents(spark: SparkSession, d: str) -> DataFrame:
    """One byte changed in each document, every document a cell of its own."""
    docs = src.documents(spark, d).where("n > 0")
    cells = workloads.edit_costs(workloads.edited(docs, "overwrite", 1), workloads.grid(SCHEMES, (128, 256)))
    return cells.groupBy("scheme", "s").agg(F.count("*").alias("contents"), F.avg("added").alias("mean"), F.avg("n").alias("mean_length"))


@query()
def wl_scattered(spark: SparkSession, d: str) -> DataFrame:
    """x single bytes changed at distinct places of 64 KiB."""
    out = None
    for x in (1, 4, 16, 64):
        part = workloads.edit_experiment(spark, "scatter", x, 65536, workloads.grid(("fixed_tree", "cdc_tree"), (128,)), 10).withColumn("edits", F.lit(x))
        out = part if out is None else out.unionByName(part)
    return out.groupBy("scheme", "s", "edits").agg(F.avg("added").alias("mean"))


def _version_means(spark: SparkSession, n: int, versions: int, runs: int, sizes: tuple[int, ...], kind: str = "insert") -> DataFrame:
    """(scheme, s, version, cost, fit): mean cost over the runs after each version, and its LOESS over the versions; run by run in a store of its own."""
    series = workloads.edited_versions(spark, 1, n, versions, runs, kind)
    costs = workloads.version_costs(series, workloads.grid(("whole", "cdc", "cdc_tree"), sizes), ["run"])
    means = costs.groupBy("scheme", "s", "version").agg(F.avg("cost").alias("cost"))
    return means.join(measures.loess(means, ["scheme", "s"], "version", "cost").withColumn("version", F.col("version").cast("long")), ["scheme", "s", "version"])


VERSION_SIZES = (64, 128, 256, 512, 1024, 2048, 4096, 8192)


@query()
def wl_versions_random(spark: SparkSession, d: str) -> DataFrame:
    """Random contents of 64 KiB and 99 modifications of each by one inserted byte, 4 runs: mean cost after each version. bench.py has the large form."""
    return _version_means(spark, 65536, 100, 4, VERSION_SIZES)


@query()
def wl_break_even_random(spark: SparkSession, d: str) -> DataFrame:
    """From how many versions on the content-defined tree costs no more than the best flat content-defined scheme, and at most half, by S."""
    means = _version_means(spark, 65536, 100, 4, VERSION_SIZES).select("scheme", "s", "version", F.col("fit").alias("cost"))
    even, half = (workloads.break_even_versions(means, f).select("s", F.col("version").alias(name), F.col("flat_s").alias(f"flat_s_{name}")) for f, name in ((1.0, "even"), (0.5, "half")))
    return even.join(half, "s", "full")


_LABEL = "CAST(run AS VARCHAR) || ':' || CAST(version AS VARCHAR)"
_MODIFIED = f"""SELECT 'x' AS content_id, version, CASE WHEN version = 0 THEN body ELSE body[1:pos] || unhex(sha256({_LABEL} || ':new:0')[1:2]) || body[pos + 1:] END AS body
  FROM (SELECT r.version AS run, v.version, body, {_place_sql("CAST(r.version AS VARCHAR) || ':' || CAST(v.version AS VARCHAR)", "octet_length(body) + 1")} AS pos FROM ({o.random_contents(1, 8192, 1)}) r, (SELECT unnest(range(10)) AS version) v)"""


@query(_cumulative_sql(_MODIFIED, SCHEMES, (64, 256, 1024), 8193) + "SELECT * FROM cum")
def wl_versions_small(spark: SparkSession, d: str) -> DataFrame:
    """A random content of 8 KiB and nine modifications: cost after each version, all schemes in the ring that SQL can follow."""
    return workloads.version_costs(workloads.edited_versions(spark, 1, 8192, 10, kind="insert"), _grid(SCHEMES, (64, 256, 1024)))


@query(_cumulative_sql(o.CONVERSATIONS, ("cdc", "cdc_tree"), (64, 256, 1024)) + "SELECT a.s, min(a.version) AS version FROM cum a JOIN (SELECT version, min(cost) AS best FROM cum WHERE scheme = 'cdc' GROUP BY version) b USING (version) WHERE a.scheme = 'cdc_tree' AND a.cost <= b.best GROUP BY a.s")
def break_even_cdc(spark: SparkSession, d: str) -> DataFrame:
    """From which turn of the conversations on the content-defined tree is no dearer than the best flat content-defined scheme, by S."""
    costs = lineage.cut(workloads.version_costs(src.conversation_versions(spark, d), _grid(("cdc", "cdc_tree"), (64, 256, 1024))))
    return workloads.break_even_versions(costs, 1.0).select("s", "version")


def _series(name: str, sql: str, source, sizes: tuple[int, ...] = (256, 1024)) -> None:
    @query(_cumulative_sql(sql, EXACT, sizes) + "SELECT * FROM cum", f"wl_{name}")
    def exact(spark: SparkSession, d: str) -> DataFrame:
        rows = source(spark, d)
        return (workloads.history_costs if isinstance(rows, src.History) else workloads.version_costs)(rows, _grid(EXACT, sizes))

    @query(None, f"wl_{name}_all")
    def every(spark: SparkSession, d: str) -> DataFrame:
        rows = source(spark, d)
        return (workloads.history_totals if isinstance(rows, src.History) else workloads.total_costs)(rows, workloads.grid(SCHEMES, HISTORY_SIZES))


#: Chunk sizes of the histories: up to where the tree has one level and meets the flat scheme.
HISTORY_SIZES = (64, 128, 256, 512, 1024, 2048, 8192, 32768)

_series("versions_conversations", o.CONVERSATIONS, src.conversation_versions)
_series("history_orders", o.ORDERS, src.order_history)
_series("history_lineitem", o.LINEITEM, src.lineitem_history, (1024,))
_series("history_events", o.EVENTS, src.event_history)
_series("history_documents", o.DOCUMENTS, src.documents)
_series("history_pages", o.PAGES, src.pages)


@query()
def wl_backups_orders(spark: SparkSession, d: str) -> DataFrame:
    """Twelve monthly backups of the whole orders table, in key order: all schemes and sizes."""
    return workloads.history_totals(src.order_history(spark, d, 1, 12), workloads.grid(SCHEMES, HISTORY_SIZES))


@query(o.with_(o.keyed(o.DOCUMENTS, CUT.with_(chunk=64), 1, "_a"), o.keyed(o.PASSAGES, CUT.with_(chunk=64), 1, "_b")) + "SELECT content_id, count(*) AS chunks, count(CASE WHEN key IN (SELECT key FROM k_a WHERE level = 0) THEN 1 END) AS found FROM k_b WHERE level = 0 GROUP BY content_id")
def wl_passage_overlap(spark: SparkSession, d: str) -> DataFrame:
    """How many of each passage's chunks stand in the documents' trees."""
    return workloads.passage_overlap(src.documents(spark, d), src.passages(spark, d), CUT.with_(chunk=64))


def _dedup_sql(column: str, join: str) -> str:
    return _grid_sql(o.DOCUMENTS, EXACT) + f""", t AS (SELECT g, sum(octet_length(body)) AS bytes_in FROM (SELECT content_id, body FROM ({o.DOCUMENTS})) JOIN (SELECT CAST(doc_id AS VARCHAR) AS content_id, {column} AS g FROM {join}) USING (content_id) GROUP BY g),
x AS (SELECT g, scheme, s, sum(size + 32) AS cost FROM (SELECT DISTINCT g, scheme, s, key, size FROM grid JOIN (SELECT CAST(doc_id AS VARCHAR) AS content_id, {column} AS g FROM {join}) USING (content_id)) GROUP BY g, scheme, s)
SELECT g AS {column}, scheme, s, CAST(bytes_in AS BIGINT) AS bytes_in, CAST(cost AS BIGINT) AS cost, bytes_in / cost AS ratio FROM x JOIN t USING (g)"""


@query(_dedup_sql("lang", "documents"))
def wl_dedup_by_lang(spark: SparkSession, d: str) -> DataFrame:
    docs = src.documents(spark, d).join(src.table(spark, d, "documents").select(F.col("doc_id").cast("string").alias("content_id"), "lang"), "content_id")
    return workloads.dedup_by(docs, _grid(EXACT), ["lang"])


@query(_dedup_sql("quality", "labels"))
def wl_dedup_by_label(spark: SparkSession, d: str) -> DataFrame:
    docs = src.documents(spark, d).join(src.table(spark, d, "labels").select(F.col("doc_id").cast("string").alias("content_id"), "quality"), "content_id")
    return workloads.dedup_by(docs, _grid(EXACT), ["quality"])


# ---- variants of the rolling hash ---------------------------------------------------------------


def _variant_costs(spark: SparkSession, d: str, variants: dict[str, StoreParams]) -> DataFrame:
    out = None
    for name, p in variants.items():
        part = measures.storage_cost(tree.build(src.documents(spark, d), p)).select(F.lit(name).alias("variant"), "pairs", "cost")
        out = part if out is None else out.unionByName(part)
    return out


@query(o.with_(o.cdc_spans(o.PASSAGES, CUT, 1)) + f"""SELECT content_id, count(*) AS windows, CAST(sum(h) AS BIGINT) AS hashes FROM
  (SELECT content_id, ((ps - coalesce(lag(ps, {CUT.window}) OVER (PARTITION BY content_id, version ORDER BY i), 0)) % {rolling.M31}) * d2 % {rolling.M31} AS h FROM bt) GROUP BY content_id""")
def cdc_sql_hash(spark: SparkSession, d: str) -> DataFrame:
    """The rolling hash of every byte of the passages by a window frame of W rows."""
    rows = src.passages(spark, d)
    m = rolling.M31
    own = Window.partitionBy("content_id").orderBy("i").rowsBetween(1 - CUT.window, 0)
    terms = chunkers.byte_table(rows).join(chunkers.power_table(rows, CUT), "i").withColumn("t", (F.col("v") + 1) * F.col("down") % m)
    hashed = terms.withColumn("h", F.sum("t").over(own) % m * F.col("up") % m)
    return hashed.groupBy("content_id").agg(F.count("*").alias("windows"), F.sum("h").alias("hashes"))


@query()
def cdc_window_sweep(spark: SparkSession, d: str) -> DataFrame:
    return _variant_costs(spark, d, {str(w): StoreParams(window=w) for w in (16, 32, 48, 64)})


@query()
def cdc_head_modes(spark: SparkSession, d: str) -> DataFrame:
    return _variant_costs(spark, d, {h: StoreParams(head=h) for h in ("partial", "skip", "context")})


@query()
def cdc_length_limits(spark: SparkSession, d: str) -> DataFrame:
    return _variant_costs(spark, d, {"none": StoreParams(), "64 to 1024": StoreParams(min_len=64, max_len=1024)})


@query(f"SELECT content_id, sha256(body) AS digest, octet_length(body) AS n FROM ({o.random_contents(7, 5000, 30)})")
def random_contents(spark: SparkSession, d: str) -> DataFrame:
    """The Python data source of random contents."""
    random_source.register(spark)
    rows = spark.read.format("random_contents").option("seed", "7").option("n", "5000").option("count", "30").load()
    return rows.select("content_id", F.sha2("body", 256).alias("digest"), "n")


@query(o.with_(o.cdc_spans(o.DOCUMENTS, CDC, TOP)) + "SELECT content_id, count(*) AS nodes, max(level) AS height, CAST(sum(s) AS BIGINT) AS starts FROM n GROUP BY content_id")
def udf_rolling_cuts(spark: SparkSession, d: str) -> DataFrame:
    """All cuts of a content as one column, by the Arrow function."""
    docs = src.documents(spark, d).where("body IS NOT NULL")
    rows = docs.select("content_id", F.explode(udfs.rolling_cuts(CDC)("body")).alias("x"))
    return rows.groupBy("content_id").agg(F.count("*").alias("nodes"), F.max("x.level").alias("height"), F.sum("x.start_pos").alias("starts"))


@query(o.with_(o.cdc_spans(o.DOCUMENTS, CUT, 1)) + "SELECT content_id, row_number() OVER (PARTITION BY content_id ORDER BY s) - 1 AS seq, s AS start_pos, e AS end_pos FROM n WHERE level = 0")
def udtf_chunk_table(spark: SparkSession, d: str) -> DataFrame:
    """chunk_table in SQL, by LATERAL."""
    udfs.register(spark)
    src.documents(spark, d).where("octet_length(body) > 0").createOrReplaceTempView("_chunk_contents")
    return spark.sql("SELECT c.content_id, t.seq, t.start_pos, t.end_pos FROM _chunk_contents c, LATERAL chunk_table(c.body, 'cdc', 256) t")


@query(f"SELECT content_id, {o.tag('body', FIXED)} AS key, true AS opened FROM ({o.DOCUMENTS})")
def sql_functions(spark: SparkSession, d: str) -> DataFrame:
    """mac, seal and unseal from SQL."""
    from ..functions import crypto

    crypto.register_functions(spark, FIXED)
    src.documents(spark, d).where("body IS NOT NULL").createOrReplaceTempView("_sealed_contents")
    return spark.sql("SELECT content_id, lower(hex(mac(body))) AS key, unseal(mac(body), seal(body)) = body AS opened FROM _sealed_contents")


@query(_cumulative_sql(o.CONVERSATIONS) + "SELECT scheme, s, version, cost FROM cum")
def sequential_cost(spark: SparkSession, d: str) -> DataFrame:
    """The version costs by a store that is filled in order, one scheme in one task: the check of the set-wise form."""
    import pandas as pd

    grid = tree.build_grid(src.conversation_versions(spark, d), _grid(EXACT), ["version"])

    def fill(key, frame: pd.DataFrame) -> pd.DataFrame:
        have: set[bytes] = set()
        rows, cost = [], 0
        for version, part in frame.sort_values("version", kind="stable").groupby("version"):
            for k, size in zip(part["key"], part["size"], strict=True):
                if (k := bytes(k)) not in have:
                    have.add(k)
                    cost += 32 + int(size)
            rows.append((key[0], key[1], version, cost))
        return pd.DataFrame(rows, columns=["scheme", "s", "version", "cost"])

    return grid.groupBy("scheme", "s").applyInPandas(fill, "scheme string, s int, version long, cost long")


