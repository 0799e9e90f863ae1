"""Points and queries made of the given tables, in Spark and, by the same definitions, in DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hamcover.functions import encoders
from hamcover.functions.bits import words_of
from hamcover.plans import draws
from hamcover.plans.params import CoverPlan, SamplePlan
from hamcover.sources import load, spread
from hamcover.sources.shared import written

SEED = draws.SEED
QUERIES = 50
SET_QUERIES = 100
RATING_SCORE = 2.5


def uniform(spark: SparkSession, sf_dir: str, d: int = 128, below: int | None = None) -> DataFrame:
    rows = load(spark, sf_dir, "orders").select("o_orderkey")
    if below is not None:
        rows = rows.where(F.col("o_orderkey") < below)  # the size of the experiment
    return spread(rows).select(F.col("o_orderkey").alias("id"), encoders.uniform_code("o_orderkey", d).alias("code"))


def docs(spark: SparkSession, sf_dir: str, bits: int) -> DataFrame:
    """Codes of all documents, written once: a search reads codes several times and texts never again."""
    return written(encoders.text_fingerprint(spread(load(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")), "text", bits), "codes")


def pages(spark: SparkSession, sf_dir: str, bits: int) -> DataFrame:
    rows = spread(load(spark, sf_dir, "pages").select("page_id", "html")).select(F.col("page_id").alias("id"), encoders.strip_html("html").alias("text"))
    return written(encoders.text_fingerprint(rows, "text", bits), "codes")


def benchmark(spark: SparkSession, sf_dir: str, bits: int = 64) -> DataFrame:
    rows = load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("id"), "text")
    return encoders.text_fingerprint(rows, "text", bits).withColumnRenamed("id", "qid")


def images(spark: SparkSession, sf_dir: str, bits: int = 64, projected: bool = False) -> DataFrame:
    rows = load(spark, sf_dir, "embeddings").where("embedding is not null").select(F.col("vec_id").alias("id"), "embedding")
    if projected:
        return encoders.sign_projection(rows, "embedding", bits)
    return rows.select("id", encoders.sign_code("embedding", bits).alias("code"))


def words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encoders.word_sets(load(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text"), stop_words=encoders.STOP_WORDS)


def sized_words(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    """`words` and `vocabulary_size`, of one pass over the texts."""
    docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")
    sets, known = encoders.sized_word_sets(docs, stop_words=encoders.STOP_WORDS)
    return sets, known.count()


def vocabulary_size(spark: SparkSession, sf_dir: str) -> int:
    return encoders.vocabulary(load(spark, sf_dir, "documents").select("text"), stop_words=encoders.STOP_WORDS).count()


def ratings(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders, lines = load(spark, sf_dir, "orders"), load(spark, sf_dir, "lineitem")
    rows = orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey")).select(F.col("o_custkey").alias("user"), F.col("l_partkey").alias("item"), (F.col("l_quantity") / 10).alias("score"))
    return encoders.rating_sets(rows, RATING_SCORE)


def items(spark: SparkSession, sf_dir: str) -> int:
    """Width of rating sets: the largest item and one."""
    return load(spark, sf_dir, "part").agg(F.max("p_partkey")).first()[0] + 1


def grown(points: DataFrame, to: int) -> DataFrame:
    """Codes of whole words, multiplied to about `to` points: every copy but the first has about eight bits flipped. For timing."""
    n = points.count()
    copies = max(1, to // max(1, n))
    words = len(points.first()["code"]) if n else 1
    at = points.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))

    def moved(w: int):
        mask = F.lit(-1).cast("bigint")
        for j in range((8 * words).bit_length() - 1):  # each halves the chance of a flip
            mask = mask.bitwiseAND(F.xxhash64("id", "copy", F.lit(w), F.lit(j)))
        return F.when(F.col("copy") == 0, F.col("code")[w]).otherwise(F.col("code")[w].bitwiseXOR(mask))

    return at.select((F.col("id") * copies + F.col("copy")).alias("id"), F.array(*map(moved, range(words))).alias("code"))


def with_planted(points: DataFrame, queries: DataFrame, radii: list[int], copies: int, d: int) -> DataFrame:
    return points.unionByName(encoders.plant(queries, radii, copies, d).select("id", "code"))


# The same in DuckDB. Codes are columns w0, w1, ... of unsigned 64-bit integers.


def sql_word(hex16: str) -> str:
    return f"CAST('0x' || {hex16} AS UBIGINT)"


def sql_number(text: str) -> str:
    return f"CAST('0x' || substr(md5({text}), 1, 15) AS BIGINT)"


def sql_image_projected(bits: int) -> str:
    """id, w0, ...: signs of integer dot products with planes of +1 and -1."""
    word = ", ".join(f"CAST(sum(CASE WHEN j // 64 = {w} AND s > 0 THEN 1::HUGEINT << (j % 64)::INT ELSE 0 END) AS UBIGINT) AS w{w}" for w in range(words_of(bits)))
    return f"""
SELECT id, {word} FROM (
  SELECT id, j, sum(x * s) AS s
  FROM (SELECT vec_id AS id, unnest(range(len(embedding))) AS i, CAST(round_even(unnest(embedding)::DOUBLE * {encoders.QUANTUM}, 0) AS BIGINT) AS x FROM embeddings WHERE embedding IS NOT NULL)
  JOIN (SELECT j, i, 1 - 2 * ({sql_number(f"'{SEED}:h:' || j || ':' || i")} & 1) AS s FROM range({bits}) AS a(j), range(64) AS b(i)) USING (i) GROUP BY ALL
) GROUP BY id"""


def sql_uniform128(below: int | str | None = None) -> str:
    where = f" WHERE o_orderkey < {below}" if below is not None else ""
    return f"SELECT o_orderkey AS id, {sql_word('substr(h, 1, 16)')} AS w0, {sql_word('substr(h, 17, 16)')} AS w1 FROM (SELECT o_orderkey, md5('u:' || o_orderkey) AS h FROM orders{where})"


def sql_text_codes(bits: int, source: str = "SELECT doc_id AS id, text FROM documents") -> str:
    """id, w0, ...: for each document and bit, the sum over its tokens."""
    n = words_of(bits)
    key = "token" if n == 1 else "j || ':' || token"
    word = ", ".join(f"CAST(coalesce(sum(CASE WHEN j = {j} AND s > 0 THEN 1::HUGEINT << b ELSE 0 END), 0) AS UBIGINT) AS w{j}" for j in range(n))
    return f"""
SELECT id, {word} FROM (
  SELECT id, j, b, sum(n * (2 * CAST((h >> b) & 1 AS BIGINT) - 1)) AS s FROM (
    SELECT id, n, j, {sql_word(f"substr(md5({key}), 1, 16)")} AS h FROM (
      SELECT id, token, count(*) AS n FROM (
        SELECT id, unnest(CASE WHEN len(t) = 0 THEN [''] ELSE t END) AS token FROM (SELECT id, regexp_extract_all(lower(coalesce(text, '')), '[\\p{{L}}\\p{{N}}]+') AS t FROM ({source}))
      ) GROUP BY ALL
    ), range({n}) AS r(j)
  ), range(64) AS q(b) GROUP BY ALL
) GROUP BY id"""


def sql_image64() -> str:
    bits = " + ".join(f"(CASE WHEN embedding[{i + 1}] > 0 THEN {1 << i}::UBIGINT ELSE 0 END)" for i in range(64))
    return f"SELECT vec_id AS id, CAST({bits} AS UBIGINT) AS w0 FROM embeddings WHERE embedding IS NOT NULL"


def sql_hold_out(points: str, k: int) -> str:
    """CTEs pts, queries (with qid) of CTE `points`."""
    return f"""
queries AS (SELECT id AS qid, * EXCLUDE (id) FROM {points} ORDER BY md5('{SEED}:q:' || id), id LIMIT {k}),
pts AS (SELECT * FROM {points} WHERE id NOT IN (SELECT qid FROM queries))"""


def sql_planted(radii: list[int], copies: int, d: int) -> str:
    """CTE planted of CTE queries: id, w0, ..."""
    n = words_of(d)
    flips = ", ".join(f"xor(any_value(w{w}), CAST(coalesce(bit_xor(CASE WHEN i // 64 = {w} AND k <= distance THEN 1::UBIGINT << (i % 64)::INT ELSE 0 END), 0) AS UBIGINT)) AS w{w}" for w in range(n))
    return f"""
ranked AS (
  SELECT qid, copy, i, {", ".join(f"w{w}" for w in range(n))}, row_number() OVER (PARTITION BY qid, copy ORDER BY md5('{SEED}:p:' || qid || ':' || copy || ':' || i), i) AS k
  FROM queries, range({copies}) AS c(copy), range({d}) AS b(i)
),
planted AS (
  SELECT 1000000000 - 1 + row_number() OVER (ORDER BY qid, distance, copy) AS id, {", ".join(f"w{w}" for w in range(n))}
  FROM (SELECT qid, distance, copy, {flips} FROM ranked, (SELECT unnest({radii}) AS distance) GROUP BY qid, distance, copy)
)"""


def sql_distance(n_words: int, a: str = "p", b: str = "q") -> str:
    return "(" + " + ".join(f"CAST(bit_count(xor({a}.w{i}, {b}.w{i})) AS INT)" for i in range(n_words)) + ")"


def sql_links(r: int, group: str | None = None, also: str = "true") -> str:
    """a, b, distance of CTE points (one word): unlike codes within r by their least ids, and the other points of each code at distance 0. `group`: a column within which codes are paired; `also`: what else unlike codes p and q have to meet."""
    own = f", {group}" if group else ""
    both = f" AND p.{group} = q.{group}" if group else ""
    reps = f"(SELECT min(id) AS id, w0{own} FROM points GROUP BY w0{own})"
    near = f"SELECT p.id AS a, q.id AS b, {sql_distance(1)} AS distance FROM {reps} p JOIN {reps} q ON p.id < q.id{both} WHERE {sql_distance(1)} <= {r} AND {also}"
    return f"{near} UNION ALL SELECT p.id AS a, q.id AS b, CAST(0 AS INT) AS distance FROM {reps} p JOIN points q ON p.w0 = q.w0{both} AND p.id < q.id"


def sql_word_sets() -> str:
    """CTEs vocab (pos, word) and points (id, ones)."""
    stop = ", ".join(f"'{w}'" for w in encoders.STOP_WORDS)
    return rf"""
tok AS (SELECT doc_id AS id, unnest(regexp_extract_all(lower(coalesce(text, '')), '[\p{{L}}\p{{N}}]+')) AS word FROM documents),
vocab AS (SELECT row_number() OVER (ORDER BY word) - 1 AS pos, word FROM (SELECT word FROM tok WHERE word NOT IN ({stop}) GROUP BY word HAVING count(*) > 10)),
points AS (SELECT id, list_sort(list(DISTINCT CAST(pos AS INT))) AS ones FROM tok JOIN vocab USING (word) GROUP BY id)"""


def sql_rating_sets() -> str:
    return f"""
points AS (
  SELECT o_custkey AS id, list_sort(list(DISTINCT CAST(l_partkey AS INT))) AS ones FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_quantity / 10 >= {RATING_SCORE} GROUP BY o_custkey
)"""


SQL_SET_DISTANCE = "CAST(len(p.ones) + len(q.ones) - 2 * len(list_intersect(p.ones, q.ones)) AS INT)"


def sql_columns(plan: CoverPlan) -> str:
    """CTEs perm (part, i, pos) and cols (part, i, pos, label, b) of a plan with one copy: drawn from md5 in SQL."""
    d, t, s = plan.d, plan.parts, plan.seed
    size = d // t
    if t == 1:
        perm = f"perm AS (SELECT 0 AS part, i, i AS pos FROM range({d}) AS r(i))"
    else:
        perm = f"""perm AS (
  SELECT part, row_number() OVER (PARTITION BY part ORDER BY k) - 1 AS i, pos FROM (
    SELECT least(k // {size}, {t - 1}) AS part, k, pos FROM (SELECT i AS pos, row_number() OVER (ORDER BY md5('{s}:perm:' || i), i) - 1 AS k FROM range({d}) AS r(i))
  )
)"""
    bits = [plan.bits(p) for p in range(t)]
    if len(set(bits)) > 1 or plan.copies > 1:
        raise ValueError("one radius for all parts, one copy")
    n = 1 << bits[0]
    if plan.permuted(0):
        labels = f"labels AS (SELECT part, i, row_number() OVER (PARTITION BY part ORDER BY md5('{s}:m:' || part || ':' || i), i) - 1 AS label FROM range({t}) AS p(part), range({n}) AS r(i))"
    else:
        labels = f"labels AS (SELECT part, i, {sql_number(f"'{s}:m:' || part || ':0:' || i")} % {n} AS label FROM perm)"
    seeds = sql_number(f"'{s}:b:' || part || ':0:' || i")
    return f"{perm},\n{labels},\ncols AS (SELECT part, i, pos, label, {seeds} % {plan.prime} AS b FROM perm JOIN labels USING (part, i))"


def sql_bit(pos: str, n_words: int, row: str = "x") -> str:
    """The bit of a code at a position."""
    if n_words == 1:
        word = f"{row}.w0"
    else:
        word = "CASE " + " ".join(f"WHEN {pos} // 64 = {w} THEN {row}.w{w}" for w in range(n_words)) + " END"
    return f"CAST(({word} >> CAST({pos} % 64 AS INT)) & 1 AS INT)"


def sql_hashes(name: str, source: str, key: str, plan: CoverPlan) -> str:
    """CTE `name`: key, part, v, bucket by direct sums over the kept bits that are set."""
    n = words_of(plan.d)
    tables = plan.tables(0)
    return f"""
{name} AS (
  SELECT {key}, part, v, CAST(sum(b * one * (bit_count(label & v) & 1)) % {plan.prime} AS BIGINT) AS bucket
  FROM (SELECT x.{key}, c.part, c.label, c.b::HUGEINT AS b, {sql_bit('c.pos', n)} AS one FROM {source} x, cols c), (SELECT CAST(unnest(range(1, {tables + 1})) AS BIGINT) AS v)
  GROUP BY ALL
)"""


def sql_masks(name: str, source: str, key: str, plan: CoverPlan) -> str:
    """CTE `name`: key, part, v and the masked words m0, ...: free of accidents of integer keys."""
    n = words_of(plan.d)
    masks = ", ".join(f"CAST(coalesce(sum(CASE WHEN pos // 64 = {w} AND bit_count(label & v) & 1 = 1 THEN 1::HUGEINT << (pos % 64)::INT ELSE 0 END), 0) AS UBIGINT) AS k{w}" for w in range(n))
    own = ", ".join(f"x.w{w} & k.k{w} AS m{w}" for w in range(n))
    return f"""
{name} AS (
  SELECT x.{key}, k.part, k.v, {own} FROM {source} x, (
    SELECT part, v, {masks} FROM cols, (SELECT CAST(unnest(range(1, {plan.tables(0) + 1})) AS BIGINT) AS v) GROUP BY ALL
  ) k
)"""


def sql_samples(name: str, source: str, key: str, plan: SamplePlan) -> str:
    """CTE `name`: key, v and the sampled bits as a string."""
    n = words_of(plan.d)
    pos = sql_number(f"'{plan.seed}:s:' || t || ':' || j")
    return f"""
{name} AS (
  SELECT {key}, t + 1 AS v, string_agg(CAST(one AS VARCHAR), '' ORDER BY j) AS bits
  FROM (SELECT x.{key}, t, j, {sql_bit('pos', n)} AS one FROM {source} x, (SELECT t, j, {pos} % {plan.d} AS pos FROM range({plan.tables}) AS a(t), range({plan.k}) AS c(j)))
  GROUP BY ALL
)"""


# Counts of whole experiments: every method is a set of masks, and a pair collides in a table if it differs in at most `radius` places of its mask.


def _sql_mask_words(d: int, kept: str = "true") -> str:
    return ", ".join(f"CAST(coalesce(bit_or(CASE WHEN pos // 64 = {w} AND {kept} THEN 1::UBIGINT << (pos % 64)::INT ELSE 0 END), 0) AS UBIGINT) AS k{w}" for w in range(words_of(d)))


def sql_cover_masks(row: int, plan: CoverPlan) -> str:
    """SELECT row, radius, k0, ... of a covering plan of equal radii, copies included."""
    d, t, s, bits = plan.d, plan.parts, plan.seed, plan.bits()
    if t == 1:
        perm = f"SELECT 0 AS part, i, i AS pos FROM range({d}) AS r(i)"
    else:
        order = f"SELECT i AS pos, row_number() OVER (ORDER BY md5('{s}:perm:' || i), i) - 1 AS k FROM range({d}) AS r(i)"
        perm = f"SELECT part, row_number() OVER (PARTITION BY part ORDER BY k) - 1 AS i, pos FROM (SELECT least(k // {d // t}, {t - 1}) AS part, k, pos FROM ({order}))"
    copies = f"range({plan.copies}) AS c(copy)"
    if plan.permuted(0):
        ranks = f"SELECT part, i, row_number() OVER (PARTITION BY part ORDER BY md5('{s}:m:' || part || ':' || i), i) - 1 AS label FROM range({t}) AS p(part), range({1 << bits}) AS r(i)"
        cols = f"SELECT p.part, p.pos, l.label FROM ({perm}) p, {copies} JOIN ({ranks}) l ON l.part = p.part AND l.i = p.i + c.copy * {d // t}"
    else:
        label = sql_number(f"'{s}:m:' || part || ':' || copy || ':' || i")
        cols = f"SELECT part, pos, {label} % {1 << bits} AS label FROM ({perm}), {copies}"
    return f"SELECT {row} AS row, 0 AS radius, {_sql_mask_words(d, 'bit_count(label & v) & 1 = 1')} FROM ({cols}), (SELECT CAST(unnest(range(1, {1 << bits})) AS BIGINT) AS v) GROUP BY part, v"


def sql_sample_masks(row: int, plan: SamplePlan) -> str:
    pos = sql_number(f"'{plan.seed}:s:' || t || ':' || j")
    return f"SELECT {row} AS row, 0 AS radius, {_sql_mask_words(plan.d)} FROM (SELECT t, {pos} % {plan.d} AS pos FROM range({plan.tables}) AS a(t), range({plan.k}) AS c(j)) GROUP BY t"


def sql_substring_masks(row: int, d: int, r: int, T: int | None) -> str:
    """By the standard number of substrings where T is not given."""
    given = f"{T}" if T else f"least({d}, greatest(1, CAST(ceil({d} / log2(greatest((SELECT count(*) FROM all_), 2))) AS BIGINT)))"
    return f"SELECT {row} AS row, {r} // t AS radius, {_sql_mask_words(d)} FROM range({d}) AS p(pos), (SELECT {given} AS t) GROUP BY least(pos // ({d} // t), t - 1), t"


def sql_counts(name: str, ctes: str, d: int, rows: list[tuple[str, int, int | None, str]]) -> str:
    """The count table of an experiment. ctes: CTEs all_ and queries; rows: label, radius, tables (null: counted) and masks of each method."""
    n = words_of(d)
    words = range(n)
    masks = "\nUNION ALL ".join(x for *_, x in rows)
    info = ", ".join(f"({k}, '{label}', {r}, {tables if tables is not None else 'NULL'})" for k, (label, r, tables, _) in enumerate(rows))
    side = lambda table, key: f"SELECT {key}, m, {', '.join(f'w{w} & k{w} AS a{w}' for w in words)} FROM {table}, masks WHERE radius = 0"
    same = " AND ".join(f"p.a{w} = q.a{w}" for w in words)
    differ = " + ".join(f"CAST(bit_count(xor(p.w{w}, q.w{w}) & k{w}) AS INT)" for w in words)
    return f"""SELECT * FROM (WITH {ctes},
masks AS MATERIALIZED (SELECT row_number() OVER () AS m, * FROM ({masks})),
info AS (SELECT * FROM (VALUES {info}) AS i(row, method, r, tables)),
pairs AS MATERIALIZED (SELECT q.qid, p.id, {sql_distance(n)} AS distance FROM all_ p, queries q WHERE {sql_distance(n)} <= (SELECT max(r) FROM info)),
met AS (SELECT q.qid, p.id, p.m FROM ({side('all_', 'id')}) p JOIN ({side('queries', 'qid')}) q ON p.m = q.m AND {same}
  UNION ALL SELECT q.qid, p.id, m FROM all_ p, queries q, masks WHERE radius > 0 AND {differ} <= radius),
cand AS (SELECT row, qid, id, count(*) AS c FROM met JOIN masks USING (m) GROUP BY ALL),
told AS (SELECT cand.row, CAST(sum(c) AS BIGINT) AS n_collisions, count(*) AS n_candidates, count(pairs.id) AS found FROM cand JOIN info USING (row) LEFT JOIN pairs ON pairs.qid = cand.qid AND pairs.id = cand.id AND pairs.distance <= info.r GROUP BY cand.row),
truth AS (SELECT info.row, count(pairs.id) AS true_pairs FROM info LEFT JOIN pairs ON pairs.distance <= info.r GROUP BY info.row),
sizes AS (SELECT row, count(*) AS counted FROM masks GROUP BY row)
SELECT '{name}' AS name, method, (SELECT count(*) FROM all_) AS n, CAST({d} AS INT) AS d, CAST(r AS INT) AS r, CAST(coalesce(tables, counted) AS INT) AS tables,
  coalesce(n_collisions, 0) AS n_collisions, coalesce(n_candidates, 0) AS n_candidates, coalesce(found, 0) AS found, true_pairs,
  round(coalesce(found, 0) / nullif(true_pairs, 0), 6) AS recall, round(coalesce(found, 0) / nullif(coalesce(n_candidates, 0), 0), 6) AS precision
FROM info JOIN truth USING (row) JOIN sizes USING (row) LEFT JOIN told USING (row) WHERE (SELECT count(*) FROM queries) > 0)"""


def sql_planted_sets(radii: tuple[int, ...], copies: int) -> str:
    """CTE planted of CTEs queries (qid, ones) and width (d): id, ones."""
    return f"""
drawn AS (SELECT qid, copy, distance, i, {sql_number(f"'{SEED}:p:' || qid || ':' || copy || ':' || i")} % d AS pos FROM width, queries, (SELECT unnest({list(radii)}) AS distance), range({copies}) AS c(copy), range({4 * max(radii) + 9}) AS r(i) WHERE i <= 4 * distance + 8),
firsts AS (SELECT qid, copy, distance, pos, row_number() OVER (PARTITION BY qid, copy, distance ORDER BY min(i)) AS k FROM drawn GROUP BY qid, copy, distance, pos),
flipped AS (SELECT qid, copy, distance, list(CAST(pos AS INT)) AS flips FROM firsts WHERE k <= distance GROUP BY ALL),
planted AS (
  SELECT 1000000000 - 1 + row_number() OVER (ORDER BY qid, distance, copy) AS id,
    list_sort(list_concat(list_filter(ones, lambda x: NOT list_contains(flips, x)), list_filter(flips, lambda x: NOT list_contains(ones, x)))) AS ones
  FROM flipped JOIN queries USING (qid)
)"""


def sql_set_counts(name: str, sets: str, k: int, rows: list[tuple], planted: tuple[int, ...] = ()) -> str:
    """The count table of an experiment on rating sets. rows: label, method, radius, plan (whose width is not looked at) and miss chance of each method.

    A bucket is told by the kept positions that a set has, and one more that every set has. Labels are random ones, as the width is larger than their number."""
    kept, info = [], []
    for row, (label, method, r, plan, delta) in enumerate(rows):
        if method == "bit_sampling":
            tables = plan.tables
            bits = f"greatest(1, CAST(ceil(ln(1 - power({delta!r}, 1.0 / {tables})) / ln(1 - {r}.0 / d)) AS BIGINT))"
            pos = sql_number(f"'{plan.seed}:s:' || t || ':' || j")
            kept.append(f"SELECT DISTINCT {row} AS row, t AS m, {pos} % d AS pos FROM range({tables}) AS a(t), (SELECT d, unnest(range({bits})) AS j FROM width)")
        else:
            tables, t, n = plan.total_tables, plan.parts, 1 << plan.bits()
            order = f"SELECT i AS pos, row_number() OVER (ORDER BY md5('{plan.seed}:perm:' || i), i) - 1 AS k, d FROM spots" if t > 1 else "SELECT i AS pos, i AS k, d FROM spots"
            cols = f"SELECT pos, part, {sql_number(f"'{plan.seed}:m:' || part || ':0:' || (k - part * (d // {t}))")} % {n} AS label FROM (SELECT *, least(k // (d // {t}), {t - 1}) AS part FROM ({order}))"
            kept.append(f"SELECT {row} AS row, part * {n} + v AS m, pos FROM ({cols}), (SELECT CAST(unnest(range(1, {n})) AS BIGINT) AS v) WHERE bit_count(label & v) & 1 = 1")
        info.append(f"({row}, '{label}', {r}, {tables})")
    more = f",{sql_planted_sets(planted, 2)}" if planted else ""
    everyone = "SELECT id, ones FROM pts" + (" UNION ALL SELECT id, ones FROM planted" if planted else "")
    union = "\nUNION ALL ".join(kept)
    return f"""SELECT * FROM (WITH {sets},{sql_hold_out('points', k)},
width AS (SELECT max(p_partkey) + 1 AS d FROM part), spots AS (SELECT unnest(range(d)) AS i, d FROM width){more},
all_ AS MATERIALIZED ({everyone}),
info AS (SELECT * FROM (VALUES {", ".join(info)}) AS i(row, method, r, tables)),
kept AS MATERIALIZED ({union}),
masks AS MATERIALIZED (SELECT * FROM kept UNION ALL SELECT DISTINCT row, m, -1 FROM kept),
pairs AS MATERIALIZED (SELECT q.qid, p.id, {SQL_SET_DISTANCE} AS distance FROM all_ p, queries q WHERE {SQL_SET_DISTANCE} <= (SELECT max(r) FROM info)),
pk AS (SELECT id, row, m, sum(CAST(hash(pos + 2) AS HUGEINT)) AS h FROM (SELECT id, unnest(list_append(ones, -1)) AS pos FROM all_) JOIN masks USING (pos) GROUP BY ALL),
qk AS (SELECT qid, row, m, sum(CAST(hash(pos + 2) AS HUGEINT)) AS h FROM (SELECT qid, unnest(list_append(ones, -1)) AS pos FROM queries) JOIN masks USING (pos) GROUP BY ALL),
cand AS (SELECT row, q.qid, p.id, count(*) AS c FROM pk p JOIN qk q USING (row, m, h) GROUP BY ALL),
told AS (SELECT cand.row, CAST(sum(c) AS BIGINT) AS n_collisions, count(*) AS n_candidates, count(pairs.id) AS found FROM cand JOIN info USING (row) LEFT JOIN pairs ON pairs.qid = cand.qid AND pairs.id = cand.id AND pairs.distance <= info.r GROUP BY cand.row),
truth AS (SELECT info.row, count(pairs.id) AS true_pairs FROM info LEFT JOIN pairs ON pairs.distance <= info.r GROUP BY info.row)
SELECT '{name}' AS name, method, (SELECT count(*) FROM all_) AS n, CAST((SELECT d FROM width) AS INT) AS d, CAST(r AS INT) AS r, CAST(tables AS INT) AS tables,
  coalesce(n_collisions, 0) AS n_collisions, coalesce(n_candidates, 0) AS n_candidates, coalesce(found, 0) AS found, true_pairs,
  round(coalesce(found, 0) / nullif(true_pairs, 0), 6) AS recall, round(coalesce(found, 0) / nullif(coalesce(n_candidates, 0), 0), 6) AS precision
FROM info JOIN truth USING (row) LEFT JOIN told USING (row))"""
