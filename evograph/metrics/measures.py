"""Cost and accuracy measures, and the evaluation protocols they are taken under."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evograph.windows.fixed import members

#: Epochs per window, per batch, in the ablation without dependencies, and timed.
EPOCHS = {"window": 20, "batch": 100, "ablation": 80, "timing": 10}


def auc(df: DataFrame, score: str = "score", y: str = "y", by: list[str] = ()) -> DataFrame:
    """Area under the curve by rank sums, average ranks for ties, null where a class is absent."""
    part = Window.partitionBy(*by) if by else Window.partitionBy(F.lit(0))
    r = F.rank().over(part.orderBy(score)) + (F.count("*").over(Window.partitionBy(*by, score)) - 1) / 2
    ranked = df.withColumn("r", r)
    pos = F.sum(F.col(y).cast("long"))
    neg = F.count("*") - pos
    value = F.when((pos > 0) & (neg > 0), (F.sum(F.when(F.col(y) == 1, F.col("r"))) - pos * (pos + 1) / 2) / (pos * neg))
    return (ranked.groupBy(*by) if by else ranked.groupBy()).agg(value.alias("auc"), F.count("*").alias("n"))


def auc_histogram(df: DataFrame, score: str = "score", y: str = "y", by: list[str] = (), bins: int = 65_536) -> DataFrame:
    """The same over a fixed number of bins of scores in [0, 1]: no sort of the rows; ties inside a bin count half."""
    b = F.least(F.floor(F.col(score) * bins), F.lit(bins - 1)).cast("int")
    h = df.groupBy(*by, b.alias("bin")).agg(F.sum(F.col(y).cast("long")).alias("p"), F.sum(1 - F.col(y).cast("long")).alias("q"))
    part = Window.partitionBy(*by) if by else Window.partitionBy(F.lit(0))
    below = F.coalesce(F.sum("q").over(part.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    h = h.withColumn("won", F.col("p") * (below + F.col("q") / 2))
    g = h.groupBy(*by) if by else h.groupBy()
    return g.agg(F.when((F.sum("p") > 0) & (F.sum("q") > 0), F.sum("won") / (F.sum("p") * F.sum("q"))).alias("auc"))


def mean_of_best(log: DataFrame, by: list[str] = ("model", "method")) -> DataFrame:
    """Mean over windows of the best AUC seen for each; windows without an AUC do not count."""
    best = log.groupBy(*by, "window_id").agg(F.max("auc").alias("auc"))
    return best.groupBy(*by).agg(F.avg("auc").alias("auc"), F.count("auc").alias("windows"))


def gain(table: DataFrame, baseline: str = "batch", method: str = "adaptive") -> DataFrame:
    """``model, data, points``: gain over the baseline in percentage points."""
    p = table.groupBy("model", "data").pivot("method", [baseline, method]).agg(F.first("auc"))
    return p.select("model", "data", F.round((F.col(method) - F.col(baseline)) * 100, 6).alias("points"))


def speedup(times: DataFrame, baseline: str) -> DataFrame:
    """``times(model, data, method, seconds)`` as multiples of the baseline's speed."""
    base = times.where(F.col("method") == baseline).select("model", "data", F.col("seconds").alias("base"))
    return times.join(base, ["model", "data"]).select("model", "data", "method", F.round(F.col("base") / F.col("seconds"), 6).alias("speedup"))


def stage_share(times: DataFrame, stage: str) -> DataFrame:
    """``times(data, stage, seconds)``: share of one stage in all."""
    return times.groupBy("data").agg(F.round(F.sum(F.when(F.col("stage") == stage, F.col("seconds")).otherwise(0)) / F.sum("seconds"), 6).alias("share"))


def parallelism(waves: DataFrame) -> DataFrame:
    """``window_id, n, levels, parallelism, widest`` of leveled windows."""
    w = waves.groupBy("window_id", "level").agg(F.count("*").alias("width"))
    return w.groupBy("window_id").agg(F.sum("width").alias("n"), F.max("level").alias("levels"), F.round(F.sum("width") / F.max("level"), 6).alias("parallelism"), F.max("width").alias("widest"))


def dep_density(deps: DataFrame, ev: DataFrame, win: DataFrame) -> DataFrame:
    """``window_id, possible, pairs, density``: dependent pairs among all pairs of a window."""
    m = members(ev, win).groupBy("window_id").agg(F.count("*").alias("n"))
    c = deps.groupBy("window_id").agg(F.count("*").alias("c"))
    possible, pairs = (F.col("n") * (F.col("n") - 1) / 2).cast("long"), F.coalesce("c", F.lit(0))
    return m.join(c, "window_id", "left").select("window_id", possible.alias("possible"), pairs.alias("pairs"), F.round(pairs / possible, 6).alias("density"))


def iterations_per_event(ev: DataFrame, parts: DataFrame, epochs: int) -> DataFrame:
    """``pos, iterations``: epochs over all training parts that hold the event."""
    m = members(ev, parts).groupBy("pos").agg((F.count("*") * epochs).alias("iterations"))
    return ev.select("pos").join(m, "pos", "left").select("pos", F.coalesce("iterations", F.lit(0)).alias("iterations"))


def stream_stats(ev: DataFrame, initial: float) -> DataFrame:
    """``nodes, initial_edges, final_edges, events`` of a stream."""
    n = ev.count()
    first = int(initial * n)
    pairs = ev.where("dst IS NOT NULL").groupBy("src", "dst").agg(F.min("pos").alias("at"))
    edges = pairs.agg(F.count("*").alias("final_edges"), F.coalesce(F.sum((F.col("at") < first).cast("long")), F.lit(0)).alias("initial_edges"))
    nodes = ev.select(F.explode(F.filter(F.array("src", "dst"), lambda x: x.isNotNull())).alias("x")).distinct().agg(F.count("*").alias("nodes"))
    return nodes.crossJoin(edges).withColumn("events", F.lit(n).cast("long"))  # one row each


def staleness(ev: DataFrame, win: DataFrame) -> DataFrame:
    """``pos, staleness``: events from arrival to the end of the first window that trains on it."""
    m = members(ev, win).join(win.select("window_id", "end_pos"), "window_id")
    return m.groupBy("pos").agg((F.min("end_pos") - F.col("pos")).alias("staleness"))


def store_bytes(versions: DataFrame) -> DataFrame:
    """``versions, bytes``: stored vectors and their size at four bytes a number."""
    return versions.agg(F.count("*").alias("versions"), F.sum(F.size("z") * 4).alias("bytes"))


def accuracy(df: DataFrame, score: str = "score", y: str = "y", cut: float = 0.5) -> DataFrame:
    return df.agg(F.round(F.avg((((F.col(score) >= cut).cast("int")) == F.col(y)).cast("double")), 6).alias("accuracy"))


def bce(df: DataFrame, score: str = "score", y: str = "y") -> DataFrame:
    """Mean binary cross-entropy of probabilities, kept off 0 and 1."""
    p = F.least(F.greatest(F.col(score), F.lit(1e-12)), F.lit(1 - 1e-12))
    return df.agg(F.round(F.avg(-(F.col(y) * F.log(p) + (1 - F.col(y)) * F.log(1 - p))), 6).alias("bce"))


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """``max_diff`` of vectors of equal nodes of two runs."""
    both = a.select("node_id", F.col("z").alias("za")).join(b.select("node_id", F.col("z").alias("zb")), "node_id")
    return both.agg(F.max(F.array_max(F.zip_with("za", "zb", lambda x, y: F.abs(x - y)))).alias("max_diff"))


def batch_units(spark: SparkSession, n: int, size: int = 200, units: int = 5) -> DataFrame:
    """``batch_id, unit, start_pos, end_pos``: test units of each batch, cut from the events that follow it."""
    step = size // units
    b = spark.range(0, n // size).select(F.col("id").alias("batch_id"), F.explode(F.sequence(F.lit(0), F.lit(units - 1))).alias("unit"))
    b = b.withColumn("start_pos", F.col("batch_id") * size + size + F.col("unit") * step)
    return b.withColumn("end_pos", F.col("start_pos") + step).where(F.col("end_pos") <= n)


def next_stride(win: DataFrame, stride: int, n: int) -> DataFrame:
    """``window_id, start_pos, end_pos``: the events right after each window."""
    return win.where(F.col("end_pos") + stride <= n).select("window_id", F.col("end_pos").alias("start_pos"), (F.col("end_pos") + stride).alias("end_pos"))


def tail_fraction(win: DataFrame, share: float = 0.2) -> DataFrame:
    """``window_id, start_pos, train_end, end_pos``: a window's last events are its test part."""
    test = F.greatest(F.lit(1), F.floor((F.col("end_pos") - F.col("start_pos")) * share + 1e-9))
    return win.select("window_id", "start_pos", (F.col("end_pos") - test).alias("train_end"), "end_pos")


def holdout(ev: DataFrame, share: float = 0.8) -> DataFrame:
    """The stream with ``part``: train before the given share of positions, test after."""
    cut = int(share * ev.count())
    return ev.withColumn("part", F.when(F.col("pos") < cut, "train").otherwise("test"))


def leaks(ev: DataFrame, train: DataFrame, test: DataFrame) -> DataFrame:
    """``window_id, pos``: events of a window's test range that its training range has, too; must be empty."""
    return members(ev, test).join(members(ev, train), ["window_id", "pos"], "left_semi").select("window_id", "pos")
