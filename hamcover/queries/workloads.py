"""The experiments: every method on the same points and queries, one row for each method, radius and size.

Results are small tables of counts or seconds. Sizes follow the data: an experiment of n points uses the keys below n, as far as there are any.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hamcover.functions import encoders
from hamcover.operators import hashers, measures, search
from hamcover.plans.params import P61, CoverPlan, SamplePlan, SubstringPlan, expected_collisions, expected_far, hash_cost, min_family_size, plan_bit_sampling, plan_cover, plan_multi_index, rho
from hamcover.queries import fixtures as fx
from hamcover.queries.searches import PAGE_TEXT
from hamcover.sources import load, spread
from hamcover.sources.shared import written

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


COUNTS = "name string, method string, n bigint, d int, r int, tables int, n_collisions bigint, n_candidates bigint, found bigint, true_pairs bigint, recall double, precision double"
COSTS = "name string, method string, n bigint, d int, r int, tables int, queries bigint, runs int, hash_ms double, search_ms double, cpu_ms_per_query double, n_collisions bigint, n_candidates bigint"
SAMPLED = (0.1, 0.01)


@dataclass(frozen=True)
class Row:
    """A method of an experiment at one radius."""

    label: str
    method: str
    r: int
    cover: tuple[tuple[str, object], ...] = ()
    delta: float = 0.0
    T: int | None = None

    def plan(self, d: int, n: int):
        cover = plan_cover(d, n, self.r, **dict(self.cover)) if self.method != "multi_index" else None
        if self.method == "bit_sampling":  # as many tables as the covering family has
            return plan_bit_sampling(d, n, self.r, self.delta, tables=cover.total_tables)
        return cover or plan_multi_index(d, n, self.r, T=self.T)

    def masks(self, k: int, d: int) -> str:
        if self.method == "multi_index":
            return fx.sql_substring_masks(k, d, self.r, self.T)
        plan = self.plan(d, 1000)  # the size sets primes only
        return fx.sql_sample_masks(k, plan) if self.method == "bit_sampling" else fx.sql_cover_masks(k, plan)


def methods(r: int, cover: dict, T: int | None = None, substrings: bool = True, deltas: tuple[float, ...] = SAMPLED, masked: str | None = "general") -> list[Row]:
    """The compared methods at a radius. The plain covering baseline has labels drawn at random, or (`masked='same'`) the same labels and so the same buckets."""
    options = tuple(cover.items())
    found = [Row("transform_cover", "transform_cover", r, options)]
    if masked == "general":
        found.append(Row("masked_cover random", "masked_cover", r, (*options, ("construction", "general"))))
    elif masked:
        found.append(Row("masked_cover", "masked_cover", r, options))
    found += [Row(f"bit_sampling {delta}", "bit_sampling", r, options, delta) for delta in deltas]
    return found + [Row("multi_index", "multi_index", r, T=T)] * substrings


def sql_counts(name: str, ctes: str, d: int, rows: list[Row]) -> str:
    return fx.sql_counts(name, ctes, d, [(x.label, x.r, None if x.method == "multi_index" else tables_of(x.plan(d, 1000)), x.masks(k, d)) for k, x in enumerate(rows)])


def kept(points: DataFrame) -> DataFrame:
    """Points, written once in as many files as there are cores, if their source has fewer."""
    return written(spread(points), "points")


def tables_of(plan) -> int:
    return plan.total_tables if isinstance(plan, CoverPlan) else plan.tables


def in_one_pass(plans: list) -> bool:
    """Whether sparse points are looked up for all these plans together: masks of labels, or sampled positions."""
    return all(isinstance(plan, SamplePlan) or isinstance(plan, CoverPlan) and max(map(plan.bits, range(plan.parts))) <= hashers.CODE_BITS for plan in plans)


def planes_of(spark: SparkSession, plans: list) -> DataFrame | None:
    return written(hashers.sampled_planes(spark, plans), "planes") if any(isinstance(plan, SamplePlan) for plan in plans) else None


def compared_sets(name: str, points: DataFrame, asked: DataFrame, d: int, rows: list[Row], plans: list, n: int, truth: DataFrame) -> list[tuple]:
    """`compared` of sparse points, all methods together."""
    spark = points.sparkSession
    met = hashers.sparse_met(points, asked, plans, planes_of(spark, plans), counted=True).groupBy("plan", "qid", "id").agg(F.sum("n").alias("n"))
    radii = F.broadcast(spark.createDataFrame([(k, x.r) for k, x in enumerate(rows)], "plan int, r int"))
    hit = F.count(F.when(F.col("distance") <= F.col("r"), 1))
    found = {x[0]: x[1:] for x in met.join(truth, ["qid", "id"], "left").join(radii, "plan").groupBy("plan").agg(F.sum("n"), F.count("*"), hit).collect()}
    near = truth.groupBy("distance").count().collect()
    out = []
    for k, (x, plan) in enumerate(zip(rows, plans, strict=True)):
        total = sum(y["count"] for y in near if y["distance"] <= x.r)
        c, m, f = found.get(k, (0, 0, 0))
        out.append((name, x.label, n, d, x.r, tables_of(plan), c, m, f, total, round(f / total, 6) if total else None, round(f / m, 6) if m else None))
    return out


def compared(name: str, points: DataFrame, asked: DataFrame, d: int, rows: list[Row]) -> list[tuple]:
    """Counts of each method, one job each, against the pairs that a scan finds. Keys are of the larger prime, so that they count masked codes and no accidents."""
    n, out = points.count(), []
    truth = written(search.linear_scan(points, asked, max(x.r for x in rows), d), "truth")
    if "ones" in points.columns and in_one_pass(plans := [x.plan(d, n) for x in rows]):
        return compared_sets(name, points, asked, d, rows, plans, n, truth)
    for x in rows:
        plan = x.plan(d, n)
        plan = plan if isinstance(plan, SubstringPlan) else replace(plan, prime=P61)
        near = truth.where(F.col("distance") <= x.r).select("qid", "id", F.lit(1).alias("hit"))
        total = near.count()
        pairs = search.hits_of(points, asked, x.method, plan).groupBy("qid", "id").agg(F.count("*").alias("n"))
        c, k, f = pairs.join(near, ["qid", "id"], "left").agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*"), F.count("hit")).first()
        out.append((name, x.label, n, d, x.r, tables_of(plan), c, k, f, total, round(f / total, 6) if total else None, round(f / k, 6) if k else None))
    return out


def hashed_tables(points: DataFrame, plan: CoverPlan) -> int:
    """Tables for which points really get keys: the keys of one point, over all parts. An error if points differ in them, or none is there."""
    by_part = hashers.transform_cover_hash(points, plan, layout="array").groupBy("part").agg(F.min(F.size("buckets")).alias("least"), F.max(F.size("buckets")).alias("most")).collect()
    if len(by_part) != plan.parts or any(x["least"] != x["most"] for x in by_part):
        raise ValueError("points without keys, or with unlike numbers of them")
    return sum(x["most"] for x in by_part)


def hashed_orders(spark: SparkSession, sf_dir: str, d: int) -> DataFrame:
    """Codes drawn from the orders' keys, as far as the published size goes."""
    return kept(fx.uniform(spark, sf_dir, d, below=65_536))


def counted(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, COUNTS)


#: Runs of each timing, and codes that are hashed for the time of one.
RUNS, HASHED_CODES = 5, 512
#: Searches that are prepared at a time.
AT_ONCE = 4


def costs(name: str, points: DataFrame, asked: DataFrame, d: int, rows: list[Row]) -> list[tuple]:
    """CPU milliseconds of a query, mean of `RUNS` runs: hashing it, and finding and verifying its candidates in a stored index.

    Of the index only the buckets that a query meets are stored: what a reader of files clustered by bucket reads of it.
    Methods with the same buckets share them. Lookups run as many queries at a time; hashing is timed in one thread."""
    n, queries, out, told = points.count(), asked.count(), [], {}
    plans = [x.plan(d, n) for x in rows]
    met = list(dict.fromkeys(plan for plan in plans if not isinstance(plan, SubstringPlan)))
    planes: dict = {}
    if "code" in points.columns:
        indexes = dict(zip(met, measures.met_indexes(points, asked, met), strict=True))
    elif in_one_pass(met):
        drawn = planes_of(points.sparkSession, met)
        planes = {plan: drawn.where(F.col("plan") == k) for k, plan in enumerate(met) if isinstance(plan, SamplePlan)}
        found = hashers.sparse_met(points, asked, met, drawn, counted=False)
        indexes = {plan: found.where(F.col("plan") == k).drop("plan") for k, plan in enumerate(met)}
    else:
        indexes = {}
    searches = {(plan, x.r): "transform_cover" if isinstance(plan, CoverPlan) else x.method for x, plan in zip(rows, plans, strict=True)}
    # Small jobs, so several at a time; what is timed runs alone.
    prepare = inheritable_thread_target(points.sparkSession)(lambda key: measures.prepared_search(points, asked, searches[key], key[0], key[1], d, indexes.get(key[0]), planes.get(key[0])))
    with ThreadPoolExecutor(AT_ONCE if indexes else 1) as pool:
        ready = dict(zip(searches, pool.map(prepare, searches), strict=True))
    hashed = measures.hash_costs_ms(points, [(x.method, plan) for x, plan in zip(rows, plans, strict=True)], RUNS, HASHED_CODES, planes)
    for x, plan, hash_ms in zip(rows, plans, hashed, strict=True):
        found, collisions, candidates = ready[plan, x.r]
        if (plan, x.r) not in told:
            told[plan, x.r] = measures.search_cost(found, RUNS)
        search_ms = told[plan, x.r]
        out.append((name, x.label, n, d, x.r, tables_of(plan), queries, RUNS, hash_ms, search_ms / queries, hash_ms + search_ms / queries, collisions, candidates))
    return out


def _uniform(spark, sf_dir, below, radii, copies=1):
    points, asked = encoders.hold_out(fx.uniform(spark, sf_dir, below=below), fx.QUERIES)
    points = kept(fx.with_planted(points, asked, radii, copies, 128))
    return points, written(asked, "queries")


def _uniform_ctes(below: int | str | None, radii: list[int], copies: int = 1, where: str = "true") -> str:
    return f"""points AS (SELECT * FROM ({fx.sql_uniform128(below)}) WHERE {where}),{fx.sql_hold_out('points', fx.QUERIES)},{fx.sql_planted(radii, copies, 128)},
all_ AS MATERIALIZED (SELECT id, w0, w1 FROM pts UNION ALL SELECT id, w0, w1 FROM planted)"""


#: Planted neighbours of each query: balls of all radii.
BALLS = list(range(1, 129))
RAW_SIZES = (10_000, 20_000, 30_000, 40_000, 50_000)
RAW = methods(6, {"mode": "none"})
_HAVE = "(SELECT count(*) FROM orders)"


@query(
    "w_uniform_raw",
    "\nUNION ALL ".join(
        [sql_counts("uniform raw", _uniform_ctes(below, BALLS, where=f"{below} < {_HAVE}"), 128, RAW) for below in RAW_SIZES]
        + [sql_counts("uniform raw", _uniform_ctes(_HAVE, BALLS, where=f"{_HAVE} <= {RAW_SIZES[0]}"), 128, RAW)]
    ),
)
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Uniform 128-bit codes, radius 6, no pre-processing: growing sizes."""
    rows = []
    have = load(spark, sf_dir, "orders").count()
    for below in [x for x in RAW_SIZES if x < have] or [have]:
        points, asked = _uniform(spark, sf_dir, below, BALLS)
        rows += compared("uniform raw", points, asked, 128, RAW)
    return counted(spark, rows)


REPLICATED = [x for r, t in ((2, 4), (3, 3), (4, 2), (5, 2)) for x in methods(r, {"mode": "replicate", "t": t}, 8)]
PARTED = [x for r in (10, 12, 14, 16) for x in methods(r, {"mode": "partition", "t": 2}, 8)]

for name, label, listed in (("w_uniform_replicate", "uniform replicated", REPLICATED), ("w_uniform_partition", "uniform parts", PARTED)):

    @query(name, sql_counts(label, _uniform_ctes(65_536, BALLS), 128, listed))
    def _(spark: SparkSession, sf_dir: str, label=label, listed=listed) -> DataFrame:
        """Small radii, replicated; large radii, in two parts."""
        points, asked = _uniform(spark, sf_dir, 65_536, BALLS)
        return counted(spark, compared(label, points, asked, 128, listed))


@query("w_hash_time")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds to hash all points, keys kept as arrays, and CPU milliseconds of one: by radius at 128 bits, and by width at radius 5."""
    rows, ready = [], {}
    for d, r in [(128, r) for r in (3, 4, 5, 6, 7)] + [(d, 5) for d in (32, 64, 256, 512)]:
        if d not in ready:
            ready[d] = kept(fx.uniform(spark, sf_dir, d, below=65_536))
            n = ready[d].count()
        plan = plan_cover(d, n, r, mode="none", prime=(1 << 31) - 1)
        for method in ("transform_cover", "masked_cover"):
            rows.append((method, n, d, r, plan.total_tables, RUNS, measures.time_hash(ready[d], method, plan, RUNS), measures.hash_cost_ms(ready[d], method, plan, RUNS, HASHED_CODES)))
    return spark.createDataFrame(rows, "method string, n bigint, d int, r int, tables int, runs int, seconds double, cpu_ms_per_query double")


def _hist(name: str, points: DataFrame, asked: DataFrame, d: int) -> DataFrame:
    return measures.distance_histogram(points, asked, d).select(F.lit(name).alias("name"), "distance", "pairs")


PAGES = f"SELECT page_id AS id, {PAGE_TEXT} AS text FROM pages"


def _histogram_sql(name: str, bits: int, source: str | None = None) -> str:
    codes = fx.sql_text_codes(bits, *([source] if source else []))
    far = fx.sql_distance(bits // 64)
    return f"SELECT * FROM (WITH points AS MATERIALIZED ({codes}),{fx.sql_hold_out('points', fx.QUERIES)} SELECT '{name}' AS name, {far} AS distance, count(*) AS pairs FROM pts p, queries q GROUP BY ALL)"


@query("w_distance_histogram", "\nUNION ALL ".join([_histogram_sql("documents 64", 64), _histogram_sql("documents 256", 256), _histogram_sql("pages 256", 256, PAGES)]))
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs by distance: documents at 64 and 256 bits, pages at 256."""
    parts = [_hist(f"documents {b}", *encoders.hold_out(fx.docs(spark, sf_dir, b), fx.QUERIES), b) for b in (64, 256)]
    parts.append(_hist("pages 256", *encoders.hold_out(fx.pages(spark, sf_dir, 256), fx.QUERIES), 256))
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


RATES = ((64, 1.5), (64, 3.0), (256, 1.5), (256, 3.0))


def _rate_sql(bits: int, c: float) -> str:
    share = lambda cond: f"round(sum(CASE WHEN {cond} THEN pairs ELSE 0 END) / sum(pairs), 6)"
    return f"SELECT CAST({bits} AS INT) AS bits, CAST({c} AS DOUBLE) AS c, {share('distance <= 10')} AS near_share, {share(f'distance > 10 AND distance <= {10 * c}')} AS c_near_share, {share(f'distance > {10 * c}')} AS far_share FROM ({_histogram_sql('', bits)})"


@query("w_filter_rates", "\nUNION ALL ".join(_rate_sql(*x) for x in RATES))
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of pairs that a perfect filter spares at radius 10."""
    parts = None
    for bits, c in RATES:
        rate = measures.filter_rate(measures.distance_histogram(*encoders.hold_out(fx.docs(spark, sf_dir, bits), fx.QUERIES), bits), 10, c)
        rate = rate.select(F.lit(bits).alias("bits"), F.lit(c).alias("c"), "near_share", "c_near_share", "far_share")
        parts = rate if parts is None else parts.unionByName(rate)
    return parts


def _images(spark, sf_dir, bits, radii, copies=2):
    codes = fx.images(spark, sf_dir, bits, projected=bits == 128)
    points, asked = encoders.hold_out(codes, fx.QUERIES)
    return kept(fx.with_planted(points, asked, radii, copies, bits)), written(asked, "queries")


def _image_ctes(bits: int, radii: list[int], copies: int = 2) -> str:
    source, words = (fx.sql_image64(), "id, w0") if bits == 64 else (fx.sql_image_projected(bits), "id, w0, w1")
    return f"points AS MATERIALIZED ({source}),{fx.sql_hold_out('points', fx.QUERIES)},{fx.sql_planted(radii, copies, bits)},\nall_ AS MATERIALIZED (SELECT {words} FROM pts UNION ALL SELECT {words} FROM planted)"


RECALL_RADII = (5, 6, 7, 8, 9)
RECALLED = [x for r in RECALL_RADII for x in methods(r, {"mode": "none"}, 4, deltas=(0.1,), masked=None)]
RECALL_IMAGES_SQL = sql_counts("recall images", _image_ctes(64, list(range(1, 11))), 64, RECALLED)


@query("w_recall_images", RECALL_IMAGES_SQL)
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall on 64-bit image codes, radii 5 to 9."""
    points, asked = _images(spark, sf_dir, 64, list(range(1, 11)))
    return counted(spark, compared("recall images", points, asked, 64, RECALLED))


def recall_table(counts: DataFrame, columns: dict[str, str]) -> DataFrame:
    """Radii, with the recall of each method in a column."""
    return counts.groupBy("r").agg(*(F.max(F.when(F.col("method") == method, F.col("recall"))).alias(name) for name, method in columns.items()))


def sql_recall_table(counts: str, columns: dict[str, str]) -> str:
    return f"SELECT r, {', '.join(f"max(CASE WHEN method = '{method}' THEN recall END) AS {name}" for name, method in columns.items())} FROM ({counts}) GROUP BY r"


IMAGE_RECALLS = {"cover": "transform_cover", "substrings": "multi_index", "sampling": "bit_sampling 0.1"}


@query("recall_table_images", sql_recall_table(RECALL_IMAGES_SQL, IMAGE_RECALLS))
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    return recall_table(QUERIES["w_recall_images"](spark, sf_dir), IMAGE_RECALLS)


IMAGE_RADII = (5, 6, 7, 8, 9, 10)
IMAGE_COUNTS = [x for r in IMAGE_RADII for x in methods(r, {"policy": "low"}, deltas=(0.1,))]
_PLANTED_IMAGES = list(range(1, 12))


@query("w_counts_images", "\nUNION ALL ".join(sql_counts(f"images {bits}", _image_ctes(bits, _PLANTED_IMAGES), bits, IMAGE_COUNTS) for bits in (64, 128)))
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Collisions and candidates on image codes; substrings in their standard number."""
    rows = []
    for bits in (64, 128):
        points, asked = _images(spark, sf_dir, bits, _PLANTED_IMAGES)
        rows += compared(f"images {bits}", points, asked, bits, IMAGE_COUNTS)
    return counted(spark, rows)


def timed_points(spark: SparkSession, sf_dir: str, codes: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Codes grown to seven times the orders: about a million at sf0.1."""
    points, asked = encoders.hold_out(fx.grown(written(codes, "codes"), 7 * load(spark, sf_dir, "orders").count()), fx.QUERIES)
    return kept(points), written(asked, "queries")


def cpu_images(spark: SparkSession, sf_dir: str, radii: tuple[int, ...] = IMAGE_RADII) -> DataFrame:
    """CPU of a query; substrings in the number that is best for them."""
    rows = []
    for bits, T in ((64, 4), (128, 8)):
        points, asked = timed_points(spark, sf_dir, fx.images(spark, sf_dir, bits, projected=bits == 128))
        rows += costs(f"images {bits}", points, asked, bits, [x for r in radii for x in methods(r, {"policy": "low"}, T, deltas=(0.1,), masked="same")])
    return spark.createDataFrame(rows, COSTS)


query("w_cpu_images")(cpu_images)

TEXT_RADII = {256: (3, 4, 5, 6, 7, 8), 512: (10, 11, 12, 13, 14, 15)}
TEXT_COUNTS = {bits: [x for r in radii for x in methods(r, {"policy": "low"}, deltas=(0.1,))] for bits, radii in TEXT_RADII.items()}


def _text_ctes(bits: int, *source: str) -> str:
    return f"points AS MATERIALIZED ({fx.sql_text_codes(bits, *source)}),{fx.sql_hold_out('points', fx.QUERIES)},\nall_ AS MATERIALIZED (SELECT * FROM pts)"


@query("w_counts_text", "\nUNION ALL ".join([sql_counts(f"text {bits}", _text_ctes(bits), bits, TEXT_COUNTS[bits]) for bits in TEXT_RADII] + [sql_counts("pages 256", _text_ctes(256, PAGES), 256, TEXT_COUNTS[256])]))
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Texts at both widths, and web pages as a second source; substrings in their standard number."""
    rows = []
    for bits in TEXT_RADII:
        points, asked = encoders.hold_out(fx.docs(spark, sf_dir, bits), fx.QUERIES)
        rows += compared(f"text {bits}", kept(points), written(asked, "queries"), bits, TEXT_COUNTS[bits])
    points, asked = encoders.hold_out(fx.pages(spark, sf_dir, 256), fx.QUERIES)
    return counted(spark, rows + compared("pages 256", kept(points), written(asked, "queries"), 256, TEXT_COUNTS[256]))


def cpu_text(spark: SparkSession, sf_dir: str, radii: dict[int, tuple[int, ...]] | None = None) -> DataFrame:
    rows = []
    for bits, own in (radii or TEXT_RADII).items():
        points, asked = timed_points(spark, sf_dir, fx.docs(spark, sf_dir, bits))
        rows += costs(f"text {bits}", points, asked, bits, [x for r in own for x in methods(r, {"policy": "low"}, {256: 4, 512: 8}[bits], deltas=(0.1,), masked="same")])
    return spark.createDataFrame(rows, COSTS)


query("w_cpu_text")(cpu_text)


def _sets(spark, sf_dir, codes, width, planted=()):
    """`planted`: radii at which the data has hardly any neighbours get some, made of the queries by toggling positions."""
    sets, d = fx.sized_words(spark, sf_dir) if (codes, width) == (fx.words, fx.vocabulary_size) else (codes(spark, sf_dir), width(spark, sf_dir))
    points, asked = encoders.hold_out(written(sets, "sets"), fx.SET_QUERIES)
    if planted:
        points = points.select("id", "ones").unionByName(encoders.plant_sets(asked, list(planted), 2, d).select("id", "ones"))
    return kept(points), written(asked, "queries"), d


def set_methods(radii: tuple[int, ...], policy: str, masked: str | None) -> list[Row]:
    return [x for r in radii for x in methods(r, {"policy": policy, "construction": "general"}, substrings=False, deltas=(0.1,), masked=masked)]


RATING_RECALL_RADII, PLANTED_RATINGS = (3, 4, 5, 6, 7), (2, 3, 4, 5, 6, 7)
RATING_RADII = tuple(range(2, 14))
WORD_RADII = (5, 7, 9, 10, 13, 16, 19, 20, 23, 26, 29)
RATING_RECALLS = {"cover": "transform_cover", "sampling": "bit_sampling 0.1"}
RECALL_RATINGS_SQL = fx.sql_set_counts("recall ratings", fx.sql_rating_sets(), fx.SET_QUERIES, [(x.label, x.method, x.r, x.plan(10**6, 1000), x.delta) for x in set_methods(RATING_RECALL_RADII, "ratings", None)], PLANTED_RATINGS)


@query("w_recall_ratings", RECALL_RATINGS_SQL)
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    points, asked, d = _sets(spark, sf_dir, fx.ratings, fx.items, PLANTED_RATINGS)
    return counted(spark, compared("recall ratings", points, asked, d, set_methods(RATING_RECALL_RADII, "ratings", None)))


@query("recall_table_ratings", sql_recall_table(RECALL_RATINGS_SQL, RATING_RECALLS))
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    return recall_table(QUERIES["w_recall_ratings"](spark, sf_dir), RATING_RECALLS)


@query("w_counts_ratings", fx.sql_set_counts("ratings", fx.sql_rating_sets(), fx.SET_QUERIES, [(x.label, x.method, x.r, x.plan(10**6, 1000), x.delta) for x in set_methods(RATING_RADII, "ratings", None)]))
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    points, asked, d = _sets(spark, sf_dir, fx.ratings, fx.items)
    return counted(spark, compared("ratings", points, asked, d, set_methods(RATING_RADII, "ratings", None)))


@query("w_counts_words")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One part up to radius 9, two up to 19, three up to 29."""
    points, asked, d = _sets(spark, sf_dir, fx.words, fx.vocabulary_size)
    return counted(spark, compared("words", points, asked, d, set_methods(WORD_RADII, "words", None)))


for name, label, codes, width, radii, policy in (("w_cpu_ratings", "ratings", fx.ratings, fx.items, RATING_RADII, "ratings"), ("w_cpu_words", "words", fx.words, fx.vocabulary_size, WORD_RADII, "words")):

    @query(name)
    def _(spark: SparkSession, sf_dir: str, label=label, codes=codes, width=width, radii=radii, policy=policy) -> DataFrame:
        points, asked, d = _sets(spark, sf_dir, codes, width)
        return spark.createDataFrame(costs(label, points, asked, d, set_methods(radii, policy, "same")), COSTS)


@query("w_scan_crossover")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of one pass over uniform codes, by the number of queries: where a search without an index overtakes a scan."""
    points = kept(fx.grown(fx.uniform(spark, sf_dir), 7 * load(spark, sf_dir, "orders").count()))
    n, rows = points.count(), []
    for queries in (50, 500, 5_000):
        rest, asked = encoders.hold_out(points, queries)
        rest, asked = written(rest, "points"), written(asked, "queries")
        for r in (3, 6):
            seconds = {m: measures.timed(search.report_near(rest, asked, r, 128, m, n=n, mode="none") if m != "linear_scan" else search.linear_scan(rest, asked, r, 128)) for m in ("transform_cover", "linear_scan")}
            rows.append((n, queries, r, seconds["transform_cover"], seconds["linear_scan"]))
    return spark.createDataFrame(rows, "n bigint, queries int, r int, search_seconds double, scan_seconds double")


@query("w_step_costs")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of hashing queries, finding candidates and verifying, over stored bucket rows."""
    points, asked = encoders.hold_out(fx.docs(spark, sf_dir, 64), fx.QUERIES)
    points, asked, rows = kept(points), written(asked, "queries"), []
    n = points.count()
    for x in methods(6, {"mode": "none"}, 4, masked=None):
        plan = x.plan(64, n)
        cost = measures.cost_breakdown(points, asked, x.method, plan, 6, 64)
        rows.append((x.label, tables_of(plan), *(float(cost[k]) for k in ("s1_hash", "s2_candidates", "s3_verify"))))
    return spark.createDataFrame(rows, "method string, tables int, s1_hash double, s2_candidates double, s3_verify double")


@query(
    "w_typical_plan",
    "SELECT 'none' AS mode, CAST(127 AS INT) AS tables, CAST(1 AS INT) AS copies, CAST(1 AS INT) AS parts, power(2, 7 - 24) / 127 * 127 <= 1.0 / power(2, 17) AS rarely, power(2.0, 24) * power(2.0, 6) / power(2.0, 24) AS far",
)
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """2 ** 24 points of 128 bits, radius 6, ratio 4: no pre-processing, 127 tables, and a far point collides once in 2 ** 17 over all of them."""
    plan = plan_cover(128, 2**24, 6, 4.0)
    rarely = expected_collisions(plan, 24) <= 2.0**-17
    tables = hashed_tables(hashed_orders(spark, sf_dir, 128), plan)
    return spark.createDataFrame([(plan.mode, tables, plan.copies, plan.parts, rarely, expected_far(2**24, 6, 4.0)[0])], "mode string, tables int, copies int, parts int, rarely boolean, far double")


@query(
    "w_analytic_costs",
    "SELECT d, r, (1 << (r + 1)) - 1 AS tables, round(d + ((1 << (r + 1)) - 1) * log2((1 << (r + 1)) - 1), 6) AS transform_cover, CAST(d * ((1 << (r + 1)) - 1) AS DOUBLE) AS masked_cover, CAST(d AS DOUBLE) AS multi_index, round(ln(1 - r / d) / ln(1 - 2.0 * r / d), 6) AS rho FROM (SELECT CAST(unnest([64, 128, 256, 512]) AS INT) AS d), (SELECT CAST(unnest([3, 5, 7]) AS INT) AS r)",
)
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Closed-form costs of hashing a point, with the tables that the orders' codes are hashed to."""
    rows = []
    for d in (64, 128, 256, 512):
        points = hashed_orders(spark, sf_dir, d)
        for r in (3, 5, 7):
            L = hashed_tables(points, plan_cover(d, 65_536, r, mode="none"))
            rows.append((d, r, L, round(hash_cost("transform_cover", d, L), 6), float(hash_cost("masked_cover", d, L)), float(hash_cost("multi_index", d, L)), round(rho(d, r, 2.0), 6)))
    return spark.createDataFrame(rows, "d int, r int, tables int, transform_cover double, masked_cover double, multi_index double, rho double")


@query("w_table_counts", "SELECT * FROM (VALUES ('replicate', 2, 4, 511), ('replicate', 3, 3, 1023), ('replicate', 4, 2, 511), ('replicate', 5, 2, 2047), ('partition', 10, 2, 126), ('partition', 12, 2, 254), ('partition', 14, 2, 510), ('partition', 16, 2, 1022)) AS t(mode, r, t, tables)")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tables of the published settings at 65,536 points, as hashed; their multi-index has eight."""
    points = hashed_orders(spark, sf_dir, 128)
    rows = [(mode, r, t, hashed_tables(points, plan_cover(128, 65_536, r, mode=mode, t=t))) for mode, r, t in [("replicate", 2, 4), ("replicate", 3, 3), ("replicate", 4, 2), ("replicate", 5, 2)] + [("partition", r, 2) for r in (10, 12, 14, 16)]]
    return spark.createDataFrame(rows, "mode string, r int, t int, tables int")


@query("w_family_bounds", "SELECT CAST(r AS INT) AS r, round(product((power(2, r + 1) - i) / (power(2, r) - i)), 6) AS least, round(product((power(2, r + 1) - i) / (power(2, r) - i)), 6) >= power(2, r) AS reached FROM (SELECT r, unnest(range(r)) AS i FROM (SELECT unnest([1, 2, 3, 4, 5, 6]) AS r)) GROUP BY r")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The least family has 2 ** r tables or more, and the one that points are hashed by no fewer than the least."""
    points = hashed_orders(spark, sf_dir, 128)
    tables = {r: hashed_tables(points, plan_cover(128, 65_536, r, mode="none")) for r in range(1, 7)}
    return spark.createDataFrame([(r, round(min_family_size(r), 6), tables[r] >= min_family_size(r) >= 2**r) for r in range(1, 7)], "r int, least double, reached boolean")


@query("w_recommend")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which method is advised for documents at 64 and 256 bits."""
    rows = []
    for bits in (64, 256):
        points, asked = encoders.hold_out(fx.docs(spark, sf_dir, bits), fx.QUERIES)
        for indexed in (False, True):
            advice, told = search.recommend(points, asked, 6, 2.0, bits, fraction=0.5, indexed=indexed)
            rows.append((bits, indexed, advice, round(float(told["near"]), 6), round(float(told["far"]), 6)))
    return spark.createDataFrame(rows, "bits int, indexed boolean, advice string, near double, far double")


SEEDS = range(5)
_SEED_PLANS = [plan_cover(64, 1000, 6, mode="none", seed=seed) for seed in SEEDS]
_BOUNDS = ", ".join(f"({k}, {float(expected_collisions(_SEED_PLANS[0], k))!r}::DOUBLE)" for k in range(65))


@query(
    "w_seed_means",
    f"""WITH {_text_ctes(64)},
masks AS MATERIALIZED ({" UNION ALL ".join(fx.sql_cover_masks(k, plan) for k, plan in enumerate(_SEED_PLANS))}),
h AS (SELECT {fx.sql_distance(1)} AS distance, count(*) AS pairs FROM all_ p, queries q GROUP BY 1)
SELECT CAST(row AS INT) AS seed, count(*) AS n_collisions, (SELECT round(sum(pairs * bound), 6) FROM h JOIN (VALUES {_BOUNDS}) AS b(distance, bound) USING (distance)) AS expected_collisions
FROM all_ p, queries q, masks WHERE xor(p.w0, q.w0) & k0 = 0 GROUP BY row""",
)
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Collisions over five seeds, beside what the bound expects."""
    points, asked = encoders.hold_out(fx.docs(spark, sf_dir, 64), fx.QUERIES)
    points, asked = kept(points), written(asked, "queries")
    n = points.count()
    one = lambda seed: search.hits_of(points, asked, "transform_cover", _SEED_PLANS[seed].sized(n)).agg(F.count("*").alias("n_collisions"))
    expected = measures.estimate_collisions(measures.distance_histogram(points, asked, 64), _SEED_PLANS[0])
    return measures.repeat(one, SEEDS).crossJoin(expected)  # one row
