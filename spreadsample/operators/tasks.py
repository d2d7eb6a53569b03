"""Reading tasks over plots, answered by fixed readers: regression, density, clustering; success tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadsample.functions import kernels
from spreadsample.operators import measures, render

#: Zoom boxes (x0, x1, y0, y1) and the mark inside each, by a low-discrepancy rule.
RADIUS, SIDE = 0.03, 0.25


def marks(spark: SparkSession, points: DataFrame, n: int) -> DataFrame:
    """(question, mx, my): n places inside the data, the rows of smallest hash."""
    rows = points.orderBy(F.md5(F.concat(F.lit("mark:"), F.col("id"))), "id").select("x", "y").limit(n).collect()
    return spark.createDataFrame([(i, r["x"], r["y"]) for i, r in enumerate(rows)], "question int, mx double, my double")


def places(points: DataFrame, n: int, radius: float = 0.02) -> DataFrame:
    """(question, mx, my): n places spread over the area that the data covers, crowded or not, as marks in zoomed regions are."""
    return measures.domain_probes(points, n, radius, oversample=40).select(F.col("probe_id").cast("int").alias("question"), F.col("px").alias("mx"), F.col("py").alias("my"))


def around(rows: DataFrame, at: DataFrame, radius: float) -> DataFrame:
    """rows within radius of a mark, with its question and their squared distance d2: an equi-join on cells, marks in nine of them."""
    cell = lambda c: F.floor(F.col(c) / radius).cast("long")
    near = F.array(*[F.lit(d) for d in (-1, 0, 1)])
    marked = at.withColumn("dx", F.explode(near)).withColumn("dy", F.explode(near)).select("question", "mx", "my", (cell("mx") + F.col("dx")).alias("cx"), (cell("my") + F.col("dy")).alias("cy"))
    met = rows.withColumns({"cx": cell("x"), "cy": cell("y")}).join(F.broadcast(marked), ["cx", "cy"])
    return met.withColumn("d2", kernels.squared("x", "y", "mx", "my")).where(F.col("d2") <= radius * radius)


def values_near(rows: DataFrame, at: DataFrame, radius: float = RADIUS) -> DataFrame:
    """(question, v): the value of the row nearest to the mark, where one lies within the radius."""
    return around(rows, at, radius).groupBy("question").agg(F.min_by("value", F.struct("d2", "id")).alias("v"))


def regression_truth(points: DataFrame, at: DataFrame, radius: float = RADIUS) -> DataFrame:
    """(question, truth, span): what regression asks of all rows, the same for every sample of them."""
    span = points.agg((F.max("value") - F.min("value")).alias("span"))
    return values_near(points, at, radius).withColumnRenamed("v", "truth").crossJoin(F.broadcast(span))


def regression(points: DataFrame, sample: DataFrame, at: DataFrame, radius: float = RADIUS, truth: DataFrame | None = None) -> DataFrame:
    """(question, correct): from the nearest drawn row within the reading radius the reader takes its value, and is right if that is nearer to the
    truth (the value at the mark) than to two wrong options, a tenth of the value range away; no row near means not sure. truth: the rows
    of regression_truth, if they are there already."""
    truth = regression_truth(points, at, radius) if truth is None else truth
    return at.join(truth, "question").join(values_near(sample, at, radius), "question", "left").select("question", F.coalesce(F.abs(F.col("v") - F.col("truth")) < F.col("span") / 20, F.lit(False)).alias("correct"))


def crowds(rows: DataFrame, at: DataFrame, weight: str | None = None, marks_each: int = 4, radius: float = RADIUS) -> DataFrame:
    """(q, most, least, clear_top, clear_low): the marks of each question with the most and the fewest rows (or weights) around them, and whether each is alone."""
    w = F.col(weight) if weight else F.lit(1)
    met = at.join(around(rows, at, radius).groupBy("question").agg(F.sum(w).alias("n")), "question", "left").select("question", F.coalesce("n", F.lit(0)).alias("n"))
    by = met.withColumns({"q": F.floor(F.col("question") / marks_each).cast("int")})
    ends = by.groupBy("q").agg(F.max_by("question", "n").alias("most"), F.min_by("question", "n").alias("least"), F.max("n").alias("hi"), F.min("n").alias("lo"))
    return by.join(ends, "q").groupBy("q", "most", "least").agg((F.sum((F.col("n") == F.col("hi")).cast("int")) == 1).alias("clear_top"), (F.sum((F.col("n") == F.col("lo")).cast("int")) == 1).alias("clear_low"))


def density(points: DataFrame, sample: DataFrame, at: DataFrame, weight: str | None = None, marks_each: int = 4, radius: float = RADIUS, truth: DataFrame | None = None) -> DataFrame:
    """(question, correct): of each question's marks the reader names the densest and the sparsest by drawn rows (or their weights) within
    the radius; both must be those of the data, a tie is wrong. truth: the crowds of all rows, if they are there already."""
    a = crowds(points, at, None, marks_each, radius) if truth is None else truth
    b = crowds(sample, at, weight, marks_each, radius).withColumnsRenamed({"most": "most2", "least": "least2", "clear_top": "ct2", "clear_low": "cl2"})
    return a.join(b, "q").select(F.col("q").alias("question"), ((F.col("most") == F.col("most2")) & (F.col("least") == F.col("least2")) & F.col("ct2") & F.col("cl2")).alias("correct"))


def clusters(sample: DataFrame, side: int = 16, share: float = 0.35, weight: str | None = None, least: int = 3) -> DataFrame:
    """(n): clusters that a reader of the raster sees: pixels smoothed over their neighbours, above a share of the fullest, joined by
    eight-neighbour adjacency, those of at least `least` pixels counted. Only the raster, side * side pixels at most, comes to
    the driver."""
    w = F.col(weight) if weight else F.lit(1)
    pixel = lambda c: F.least(F.lit(side - 1), F.floor(F.col(c) * side).cast("int"))
    px = sample.groupBy(pixel("x").alias("px"), pixel("y").alias("py")).agg(F.sum(w).cast("double").alias("n"))
    raw = {(r["px"], r["py"]): r["n"] for r in px.collect()}
    around = [(a, b) for a in (-1, 0, 1) for b in (-1, 0, 1)]
    smooth: dict[tuple[int, int], float] = {}
    for (x, y), n in sorted(raw.items()):
        for a, b in around:
            smooth[x + a, y + b] = smooth.get((x + a, y + b), 0.0) + n / (1 + abs(a) + abs(b))
    top = max(smooth.values(), default=0.0)
    full, found = {p for p, n in smooth.items() if n >= share * top}, 0
    while full:
        todo, size = [full.pop()], 0
        while todo:
            x, y = todo.pop()
            size += 1
            near = {(x + a, y + b) for a, b in around} & full
            full -= near
            todo += near
        found += size >= least
    return sample.sparkSession.createDataFrame([(found,)], "n int")


def success_table(answers: DataFrame) -> DataFrame:
    """Fraction right per k and method, with the average row (k null)."""
    right = F.avg(F.col("correct").cast("double"))
    methods = sorted(r[0] for r in answers.select("method").distinct().collect())
    return answers.groupBy("k").pivot("method", methods).agg(right).unionByName(answers.groupBy().pivot("method", methods).agg(right).withColumn("k", F.lit(None).cast("int")))


def overview(points: DataFrame, sample: DataFrame, box, side: int = 64) -> DataFrame:
    """(kept, total): pixels of a zoomed raster that the sample still shows."""
    seen = render.raster(sample, side, side, box).select("px", "py")
    every = render.raster(points, side, side, box).select("px", "py")
    return every.agg(F.count("*").alias("total")).crossJoin(every.join(seen, ["px", "py"], "left_semi").agg(F.count("*").alias("kept")))
