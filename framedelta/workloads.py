"""The experiments on the given tables, a query each, with DuckDB SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import oracles
from .functions import vector as V
from .model import EncoderSpec
from .operators import measures, search, tasks
from .plans.reference import add_halo, plan_frames, training_groups
from .pretrained import modules
from .sources import frames as S
from .sources.frames import table

Query = Callable[[SparkSession, str], DataFrame]
TINY = EncoderSpec.preset("tiny")
PROSE = EncoderSpec.preset("tiny", n_tokens=9, in_dim=16)
SHIP = EncoderSpec.preset("tiny", n_tokens=7, in_dim=7)
MORPH = EncoderSpec.preset("tiny", n_tokens=9, in_dim=8)
PLAN = ("video_id", "frame_no", "epoch_no", "segment_no", "ftype", "past_ref", "future_ref", "wavefront", "exec_order")
SQL: dict[str, str] = {}
QUERIES: dict[str, Query] = {}


def query(sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


def token_rows(frames: DataFrame, dim: int) -> DataFrame:
    """video_id, frame_no, token_no and the token's total and squared length, rounded: frames in a form any engine can compare."""
    n = F.size("tokens") / dim
    t = frames.select("video_id", "frame_no", F.posexplode(F.transform(F.sequence(F.lit(0), n.cast("int") - 1), lambda i: F.slice("tokens", i * dim + 1, dim))).alias("token_no", "v"))
    return t.select("video_id", "frame_no", "token_no", F.round(F.aggregate("v", F.lit(0.0), lambda a, x: a + x), 5).alias("total"), F.round(V.dot(F.col("v"), F.col("v")), 5).alias("squares"))


# ---- frames -----------------------------------------------------------------------------------------------------

ACT = """
bd AS (SELECT date_trunc('day', min(ts))::TIMESTAMP AS t0, CAST(floor(epoch(max(ts) - date_trunc('day', min(ts))::TIMESTAMP) / 21600) AS INT) AS last FROM events WHERE user_id IS NOT NULL),
cells AS (SELECT user_id, list_position(['click', 'error', 'purchase', 'signup', 'view'], event_type) AS kind,
    CAST(floor(epoch(ts - t0) / 21600) AS INT) AS b, sum(value) AS s FROM events, bd GROUP BY ALL),
cell AS (SELECT user_id, kind, b, ln(1 + s) AS v FROM cells WHERE kind > 0),
ks AS (SELECT unnest(range(0, last + 1)) AS k FROM bd),
grid AS (SELECT user_id, k, kind, slot FROM (SELECT DISTINCT user_id FROM events), ks, range(1, 6) t(kind), range(0, 12) c(slot)),
patch AS (SELECT g.user_id, g.k, g.kind, g.slot, coalesce(c.v, 0) AS v FROM grid g LEFT JOIN cell c
    ON c.user_id = g.user_id AND c.kind = g.kind AND c.b = g.k - (g.k - g.slot + 12) % 12),
slots AS (SELECT * FROM patch UNION ALL SELECT user_id, k, 0, slot, avg(v) FROM patch GROUP BY user_id, k, slot)
"""


@query(f"WITH {ACT} SELECT user_id AS video_id, CAST(k + 1 AS INT) AS frame_no, CAST(kind AS INT) AS token_no, round(sum(v), 5) AS total, round(sum(v * v), 5) AS squares FROM slots GROUP BY user_id, k, kind")
def frames_activity(spark, sf):
    return token_rows(S.activity(spark, sf), S.RING)


def ship_sql(lineitem: str = "lineitem") -> str:
    return f"""
i AS (SELECT l_suppkey, year(l_shipdate) * 12 + month(l_shipdate) AS m, (list_position(['A', 'N', 'R'], l_returnflag) - 1) * 2 + (l_linestatus = 'O')::INT + 1 AS t, l_linenumber AS s, sum(l_quantity) AS q FROM {lineitem} GROUP BY ALL),
fm AS (SELECT l_suppkey, m, row_number() OVER (PARTITION BY l_suppkey ORDER BY m) AS n FROM (SELECT DISTINCT l_suppkey, m FROM i)),
p AS (SELECT fm.l_suppkey, n, t.t, s.s, ln(1 + coalesce(i.q, 0)) AS v FROM fm CROSS JOIN range(1, 7) t(t) CROSS JOIN range(1, 8) s(s) LEFT JOIN i ON i.l_suppkey = fm.l_suppkey AND i.m = fm.m AND i.t = t.t AND i.s = s.s),
slots AS (SELECT * FROM p UNION ALL SELECT l_suppkey, n, 0, s, avg(v) FROM p GROUP BY l_suppkey, n, s)"""


@query(f"WITH {ship_sql()} SELECT l_suppkey AS video_id, CAST(n AS INT) AS frame_no, CAST(t AS INT) AS token_no, round(sum(v), 5) AS total, round(sum(v * v), 5) AS squares FROM slots GROUP BY ALL")
def frames_shipping(spark, sf):
    return token_rows(S.shipping(spark, sf), 7)


@query("""
WITH k AS (SELECT label, embedding AS e, lead(embedding) OVER w AS a, row_number() OVER w AS n FROM embeddings WINDOW w AS (PARTITION BY label ORDER BY vec_id)),
x AS (SELECT label, (n - 1) * 8 + j + 1 AS f, i, CAST(e[i] AS DOUBLE) * (8 - j) / 8 + CAST(a[i] AS DOUBLE) * j / 8 AS v FROM k, range(0, 8) c(j), range(1, 65) d(i) WHERE a IS NOT NULL),
t AS (SELECT label, f, (i - 1) // 8 + 1 AS t, (i - 1) % 8 AS s, v FROM x),
p AS (SELECT * FROM t UNION ALL SELECT label, f, 0, s, avg(v) FROM t GROUP BY label, f, s)
SELECT CAST(label AS BIGINT) AS video_id, CAST(f AS INT) AS frame_no, CAST(t AS INT) AS token_no, round(sum(v), 5) AS total, round(sum(v * v), 5) AS squares FROM p GROUP BY ALL""")
def frames_morph(spark, sf):
    return token_rows(S.morph(spark, sf), 8)


def scrolled_sql(units: str, block: int) -> str:
    """Frames of u (doc_id, w: bucket numbers) in windows of eight blocks, hop two."""
    return f"""u AS ({units}),
n AS (SELECT doc_id, w, greatest(1, CAST(ceil((len(w) - {8 * block}) / {2.0 * block}) AS INT) + 1) AS n FROM u),
f AS (SELECT doc_id, w, unnest(range(1, n + 1)) AS f FROM n),
h AS (SELECT doc_id, f, w[(f - 1) * {2 * block} + i] AS b, ((i - 1) // {block} + (f - 1) * 2) % 8 + 1 AS t FROM f, range(1, {8 * block + 1}) c(i) WHERE (f - 1) * {2 * block} + i <= len(w)),
c AS (SELECT doc_id, f, t, b, count(*) AS v FROM h GROUP BY ALL),
e AS (SELECT doc_id, f, t, b FROM (SELECT DISTINCT doc_id, f FROM f), range(1, 9) r(t), range(0, 16) q(b)),
p AS (SELECT e.doc_id, e.f, e.t, e.b, coalesce(c.v, 0)::DOUBLE AS v FROM e LEFT JOIN c ON c.doc_id = e.doc_id AND c.f = e.f AND c.t = e.t AND c.b = e.b),
slots AS (SELECT * FROM p UNION ALL SELECT doc_id, f, 0, b, avg(v) FROM p GROUP BY doc_id, f, b)"""


WORDS = "SELECT doc_id, list_transform(string_split(text, ' '), lambda x: CAST('0x' || substr(md5(lower(x)), 1, 6) AS BIGINT) % 16) AS w FROM documents WHERE text IS NOT NULL"
LETTERS = "SELECT page_id AS doc_id, list_transform(range(1, length(html) + 1), lambda i: unicode(substr(html, i, 1)) % 16) AS w FROM pages WHERE html IS NOT NULL"
SHOWN = "SELECT doc_id AS video_id, CAST(f AS INT) AS frame_no, CAST(t AS INT) AS token_no, round(sum(v), 5) AS total, round(sum(v * v), 5) AS squares FROM slots GROUP BY ALL"


@query(f"WITH {scrolled_sql(WORDS, 8)} {SHOWN}")
def frames_prose(spark, sf):
    return token_rows(S.prose(spark, sf), 16)


@query(f"WITH {scrolled_sql(LETTERS, 64)} {SHOWN}")
def frames_pages(spark, sf):
    return token_rows(S.pages(spark, sf), 16)


TALK = """
u AS (SELECT conv_id AS doc_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS f, list_transform(string_split(text, ' '), lambda x: CAST('0x' || substr(md5(lower(x)), 1, 6) AS BIGINT) % 16) AS w FROM conversations WHERE conv_id IS NOT NULL AND text IS NOT NULL),
h AS (SELECT doc_id, f, i AS t, unnest(w[CAST(floor(len(w) * (i - 1) / 8.0) AS INT) + 1:CAST(floor(len(w) * i / 8.0) AS INT)]) AS b FROM u, range(1, 9) r(i)),
c AS (SELECT doc_id, f, t, b, count(*) AS v FROM h GROUP BY ALL),
e AS (SELECT doc_id, f, t, b FROM u, range(1, 9) r(t), range(0, 16) q(b)),
p AS (SELECT e.doc_id, e.f, e.t, e.b, coalesce(c.v, 0)::DOUBLE AS v FROM e LEFT JOIN c ON c.doc_id = e.doc_id AND c.f = e.f AND c.t = e.t AND c.b = e.b),
slots AS (SELECT * FROM p UNION ALL SELECT doc_id, f, 0, b, avg(v) FROM p GROUP BY doc_id, f, b)
"""


@query(f"WITH {TALK} {SHOWN}")
def frames_talk(spark, sf):
    return token_rows(S.talk(spark, sf), 16)


# ---- plans -------------------------------------------------------------------------------------------------------

SHIP_FRAMES = "fr AS (SELECT l_suppkey AS v, row_number() OVER (PARTITION BY l_suppkey ORDER BY m) AS f, count(*) OVER (PARTITION BY l_suppkey) AS n FROM (SELECT DISTINCT l_suppkey, year(l_shipdate) * 12 + month(l_shipdate) AS m FROM lineitem)), ps AS (SELECT v, f, n, (f - 1) % 20 AS p, (f - 1) // 20 AS e, ((f - 1) % 20) % 4 AS q, ((f - 1) % 20) // 4 AS k FROM fr)"


def ship_frames(spark, sf) -> DataFrame:
    """video_id and frame_no of the shipping frames alone; their tokens are not made."""
    i = table(spark, sf, "lineitem").select("l_suppkey", (F.year("l_shipdate") * 12 + F.month("l_shipdate")).alias("m")).distinct()
    return i.select(F.col("l_suppkey").alias("video_id"), F.row_number().over(Window.partitionBy("l_suppkey").orderBy("m")).alias("frame_no"))


def plan_sql(tail: str, frames: str = SHIP_FRAMES) -> str:
    """The reordered plan; what an open last segment gets is the tail rule. frames ends with ps (v, f, n, p, e, q, k)."""
    own = {
        "chain": ("'P'", "f - 1", "NULL", "k + q", "4 * k + q"),
        "recompute": ("'I'", "NULL", "NULL", "0", "4 * k + q"),
        "short_anchor": ("CASE WHEN q = n - f + q THEN 'P' WHEN q = 1 THEN 'B1' ELSE 'B2' END", "CASE WHEN q = n - f + q THEN f - q WHEN q = 1 THEN f - 1 ELSE f - 2 END", "CASE WHEN q = n - f + q THEN NULL ELSE f + 1 END", "CASE WHEN q = n - f + q THEN k + 1 WHEN q = 2 OR n - f + q = 2 THEN k + 2 ELSE k + 3 END", "4 * k + CASE WHEN q = n - f + q THEN 1 WHEN q = 2 THEN 2 ELSE 3 END"),
    }[tail]
    return f"""WITH {frames}, c AS (SELECT *, f - q + 4 <= n AS closed, 1 + greatest(k, CASE WHEN p - q + 4 = 20 THEN 0 ELSE k + 1 END) AS b2 FROM ps)
SELECT v AS video_id, CAST(f AS INT) AS frame_no, CAST(e AS INT) AS epoch_no, CAST(k AS INT) AS segment_no,
 CASE WHEN p = 0 THEN 'I' WHEN q = 0 THEN 'P' WHEN closed AND q = 2 THEN 'B2' WHEN closed THEN 'B1' ELSE {own[0]} END AS ftype,
 CAST(CASE WHEN p = 0 THEN NULL WHEN q = 0 THEN f - 4 WHEN closed AND q = 2 THEN f - 2 WHEN closed THEN f - 1 ELSE {own[1]} END AS INT) AS past_ref,
 CAST(CASE WHEN q = 0 THEN NULL WHEN closed AND q = 2 THEN f + 2 WHEN closed THEN f + 1 ELSE {own[2]} END AS INT) AS future_ref,
 CAST(CASE WHEN q = 0 THEN k WHEN closed AND q = 2 THEN b2 WHEN closed THEN b2 + 1 ELSE {own[3]} END AS INT) AS wavefront,
 CAST(CASE WHEN p = 0 THEN 0 WHEN q = 0 THEN 4 * (k - 1) + 1 WHEN closed THEN 4 * k + CASE q WHEN 2 THEN 2 WHEN 1 THEN 3 ELSE 4 END ELSE {own[4]} END AS INT) AS exec_order
FROM c"""


@query(f"WITH {SHIP_FRAMES} SELECT v AS video_id, CAST(f AS INT) AS frame_no, CAST(e AS INT) AS epoch_no, CAST(p // 4 AS INT) AS segment_no, CASE WHEN p = 0 THEN 'I' ELSE 'P' END AS ftype, CAST(CASE WHEN p > 0 THEN f - 1 END AS INT) AS past_ref, CAST(NULL AS INT) AS future_ref, CAST(p AS INT) AS wavefront, CAST(p AS INT) AS exec_order FROM ps")
def plan_sequential(spark, sf):
    return plan_frames(ship_frames(spark, sf), "sequential").select(*PLAN)


@query(plan_sql("chain"))
def plan_reordered(spark, sf):
    return plan_frames(ship_frames(spark, sf)).select(*PLAN)


@query(plan_sql("short_anchor"))
def plan_tail_short_anchor(spark, sf):
    return plan_frames(ship_frames(spark, sf), tail="short_anchor").select(*PLAN)


@query(plan_sql("recompute"))
def plan_tail_recompute(spark, sf):
    return plan_frames(ship_frames(spark, sf), tail="recompute").select(*PLAN)


@query(f"WITH {SHIP_FRAMES} SELECT v AS video_id, CAST(f AS INT) AS frame_no, CAST(r AS INT) AS ref FROM ps, range(1, 4) x(i), LATERAL (SELECT f - i AS r) WHERE f - i >= f - p")
def plan_lookback3(spark, sf):
    return plan_frames(ship_frames(spark, sf), "sequential", lookback=3).select("video_id", "frame_no", F.explode("refs").alias("ref"))


@query(f"WITH {SHIP_FRAMES} SELECT v AS video_id, CAST(e AS INT) AS epoch_no, count(*) AS frames, 0 AS halo FROM ps GROUP BY ALL UNION ALL SELECT v, CAST(e - 1 AS INT), count(*), 1 FROM ps WHERE p = 0 AND e > 0 GROUP BY ALL")
def plan_halo(spark, sf):
    x = add_halo(plan_frames(ship_frames(spark, sf)))
    return x.groupBy("video_id", "epoch_no", F.col("is_halo").cast("int").alias("halo")).agg(F.count(F.lit(1)).alias("frames"))


def groups_sql(g: int) -> str:
    items = [(i, 4 * i, "P" if i else "I", 4 * i - 4 if i else None, None) for i in range(g + 1)] + [(g + 1, 4 * g - 2, "B2", 4 * g - 4, 4 * g), (g + 2, 4 * g - 1, "B1", 4 * g - 2, 4 * g)]
    null = lambda x: "NULL" if x is None else x
    rows = ", ".join(f"({s}, {o}, '{t}', {null(a)}, {null(b)})" for s, o, t, a, b in items)
    return f"WITH {SHIP_FRAMES} SELECT v AS video_id, CAST(f AS INT) AS group_id, x.step, CAST(f + x.o AS INT) AS frame_no, x.t AS ftype, CAST(f + x.a AS INT) AS past_ref, CAST(f + x.b AS INT) AS future_ref FROM ps, (VALUES {rows}) x(step, o, t, a, b) WHERE p = 0 AND f + {4 * g} <= n"


for _g in (1, 2, 3, 4):

    def _groups(spark, sf, g=_g):
        return training_groups(plan_frames(ship_frames(spark, sf)), g)

    _groups.__name__ = f"training_groups_g{_g}"
    query(groups_sql(_g))(_groups)


# ---- gates on raw tokens ------------------------------------------------------------------------------------------

TOK = f"WITH {ACT}, vec AS (SELECT user_id, k + 1 AS f, kind, list(v ORDER BY slot) AS v FROM patch GROUP BY user_id, k, kind)"


def patch_tokens(frames: DataFrame, dim: int) -> DataFrame:
    """video_id, frame_no, token_no (from 1, without the class token), v."""
    n = (F.size("tokens") / dim).cast("int")
    return frames.select("video_id", "frame_no", F.posexplode(F.transform(F.sequence(F.lit(1), n - 1), lambda i: F.slice("tokens", i * dim + 1, dim))).alias("i", "v")).select("video_id", "frame_no", (F.col("i") + 1).alias("token_no"), "v")


def with_reference(frames: DataFrame, dim: int, column: str = "past_ref", scheme: str = "sequential") -> DataFrame:
    """Patch tokens beside those of their reference frame (r): an equi-join on the frame and not on tokens."""
    p = plan_frames(frames, scheme, payload=("tokens",)).where(F.col(column).isNotNull()).select("video_id", "frame_no", "tokens", F.col(column).alias("_ref"))
    r = frames.select("video_id", F.col("frame_no").alias("_ref"), F.col("tokens").alias("r"))
    x = p.join(r, ["video_id", "_ref"])
    n = (F.size("tokens") / dim).cast("int")
    pair = F.transform(F.sequence(F.lit(1), n - 1), lambda i: F.struct(F.slice("tokens", i * dim + 1, dim).alias("v"), F.slice("r", i * dim + 1, dim).alias("r")))
    return x.select("video_id", "frame_no", F.posexplode(pair).alias("i", "x")).select("video_id", "frame_no", (F.col("i") + 1).alias("token_no"), "x.v", "x.r")


PREV = TOK + ", pr AS (SELECT a.user_id, a.f, a.kind, a.v, b.v AS r FROM vec a JOIN vec b ON b.user_id = a.user_id AND b.kind = a.kind AND b.f = a.f - 1 WHERE (a.f - 1) % 20 > 0), mse AS (SELECT user_id, f, kind, list_sum([(x[1] - x[2]) * (x[1] - x[2]) FOR x IN list_zip(v, r)]) / 12 AS m FROM pr)"


@query(PREV + " SELECT user_id AS video_id, CAST(f AS INT) AS frame_no, count(*) FILTER (WHERE round(m, 9) < 0.1) AS reused FROM mse GROUP BY ALL")
def mse_gate_map(spark, sf):
    x = with_reference(S.activity(spark, sf), S.RING).withColumn("m", V.mse(F.col("v"), F.col("r")))
    return x.groupBy("video_id", "frame_no").agg(F.count_if(F.round("m", 9) < 0.1).alias("reused"))


@query(PREV + " SELECT user_id AS video_id, CAST(f AS INT) AS frame_no, CAST(kind AS INT) AS token_no FROM (SELECT *, row_number() OVER (PARTITION BY user_id, f ORDER BY round(m, 9) DESC, kind) AS n FROM mse) WHERE n <= 2")
def budget_gate_map(spark, sf):
    x = with_reference(S.activity(spark, sf), S.RING).withColumn("m", F.round(V.mse(F.col("v"), F.col("r")), 9))
    w = Window.partitionBy("video_id", "frame_no").orderBy(F.desc("m"), "token_no")
    return x.withColumn("n", F.row_number().over(w)).where("n <= 2").select("video_id", "frame_no", "token_no")


COS = "CASE WHEN list_dot_product({0}, {0}) > 0 AND list_dot_product({1}, {1}) > 0 THEN list_dot_product({0}, {1}) / sqrt(list_dot_product({0}, {0}) * list_dot_product({1}, {1})) ELSE 0 END"


@query(PREV + f" SELECT user_id AS video_id, CAST(f AS INT) AS frame_no, round(avg({COS.format('v', 'r')}), 6) AS similarity FROM pr GROUP BY ALL")
def token_similarity(spark, sf):
    x = with_reference(S.activity(spark, sf), S.RING)
    return x.groupBy("video_id", "frame_no").agg(F.round(F.avg(V.cosine(F.col("v"), F.col("r"))), 6).alias("similarity"))


@query(PREV + ", act AS (SELECT user_id, f, kind FROM mse WHERE round(m, 9) >= 0.1) SELECT user_id AS video_id, CAST(f AS INT) AS frame_no, CAST(kind AS INT) AS token_no, (row_number() OVER (PARTITION BY (f - 1) % 20 ORDER BY user_id, f, kind) - 1) AS position FROM act")
def compaction_positions(spark, sf):
    """Where the active tokens of a wavefront go in its gathered matrix."""
    x = with_reference(S.activity(spark, sf), S.RING).where(F.round(V.mse(F.col("v"), F.col("r")), 9) >= 0.1)
    return measures.positions(x.select("video_id", "frame_no", "token_no", F.pmod(F.col("frame_no") - 1, F.lit(20)).alias("wavefront"))).drop("wavefront")


@query(PREV + ", g AS (SELECT (f - 1) % 20 AS w, count(*) AS r FROM mse WHERE round(m, 9) >= 0.1 GROUP BY ALL) SELECT count(*) AS multiplies, CAST(sum(r) AS BIGINT) AS rows, sum(r) / count(*) AS rows_per_multiply, sum(r) / sum(ceil(r / 128.0) * 128) AS tile_fill FROM g")
def compaction_stats(spark, sf):
    x = with_reference(S.activity(spark, sf), S.RING).withColumn("active", (F.round(V.mse(F.col("v"), F.col("r")), 9) >= 0.1).cast("bigint")).withColumn("w", F.pmod(F.col("frame_no") - 1, F.lit(20)))
    return measures.compaction_stats(x, "active", ["w"]).withColumn("rows_per_multiply", F.col("rows_per_multiply").cast("double"))


HINTS = PREV + f", hint AS (SELECT user_id, f, kind, {oracles.MOTION} AS motion, d0 / 12 AS residual FROM (SELECT user_id, f, kind, {oracles.hints_cte(12)} FROM (SELECT user_id, f, kind, v AS a, r AS b FROM pr)))"


@query(HINTS + " SELECT user_id AS video_id, CAST(f AS INT) AS frame_no, CAST(kind AS INT) AS token_no, motion, round(residual, 6) AS residual FROM hint")
def codec_hints(spark, sf):
    """Motion and residual of every token against the frame before."""
    motion, residual = V.codec_hints(F.col("v"), F.col("r"))
    return with_reference(S.activity(spark, sf), S.RING).select("video_id", "frame_no", "token_no", motion.alias("motion"), F.round(residual, 6).alias("residual"))


ACT_FRAMES = "fr AS (SELECT user_id AS v, k + 1 AS f, last + 1 AS n FROM (SELECT DISTINCT user_id FROM events), ks, bd), ps AS (SELECT v, f, n, (f - 1) % 20 AS p, (f - 1) // 20 AS e, ((f - 1) % 20) % 4 AS q, ((f - 1) % 20) // 4 AS k FROM fr)"


@query(f"{TOK}, pl AS ({plan_sql('chain', ACT_FRAMES)}), s AS (SELECT a.user_id, a.f, a.kind, pl.ftype, round({COS.format('a.v', 'p.v')}, 9) AS sp, round({COS.format('a.v', 'u.v')}, 9) AS su FROM pl JOIN vec a ON a.user_id = pl.video_id AND a.f = pl.frame_no JOIN vec p ON p.user_id = a.user_id AND p.kind = a.kind AND p.f = pl.past_ref JOIN vec u ON u.user_id = a.user_id AND u.kind = a.kind AND u.f = pl.future_ref) SELECT user_id AS video_id, CAST(f AS INT) AS frame_no, CAST(kind AS INT) AS token_no, ftype, CASE WHEN su > sp THEN 'future' ELSE 'past' END AS chosen FROM s")
def ref_choice(spark, sf):
    """Which of two references a token of a B frame takes: the more similar one, of equal ones the past."""
    f = S.activity(spark, sf)
    p = plan_frames(f, payload=("tokens",)).where("past_ref is not null and future_ref is not null")
    side = lambda c: f.select("video_id", F.col("frame_no").alias(f"{c}_ref"), F.col("tokens").alias(c))
    x = p.join(side("past"), ["video_id", "past_ref"]).join(side("future"), ["video_id", "future_ref"])
    part = lambda c, i: F.slice(c, i * S.RING + 1, S.RING)
    two = F.transform(F.sequence(F.lit(1), F.lit(len(S.EVENT_TYPES))), lambda i: F.round(V.cosine(part("tokens", i), part("future", i)), 9) > F.round(V.cosine(part("tokens", i), part("past", i)), 9))
    x = x.select("video_id", "frame_no", "ftype", F.posexplode(two).alias("i", "later"))
    return x.select("video_id", "frame_no", (F.col("i") + 1).alias("token_no"), "ftype", F.when(F.col("later"), "future").otherwise("past").alias("chosen"))


def _gate_sql() -> str:
    m = modules("activity")[0]
    hidden = f"list_transform(range(1, {len(m['gb1']) + 1}), lambda i: greatest(list_dot_product(feat, {oracles._literal(m['g1'])}[i]) + {oracles._literal(m['gb1'])}[i], 0))"
    return HINTS + f""", x AS (SELECT pr.user_id, pr.f, pr.kind, [{COS.format('v', 'r')}, 0.0::DOUBLE, ((pr.f - 2) % 20 = 0)::INT::DOUBLE, ((pr.f - 2) % 20 > 0)::INT::DOUBLE, 0, 0, motion, residual] AS feat FROM pr JOIN hint USING (user_id, f, kind)),
d AS (SELECT user_id, f, kind, list_dot_product({hidden}, {oracles._literal(m['g2'][:, 0])}) + {float(m['gb2'][0]):.17g}::DOUBLE AS logit FROM x)
SELECT user_id AS video_id, CAST(f AS INT) AS frame_no, CAST(kind AS INT) AS token_no, round(logit, 5) + 0 AS logit, logit > 0 AS reuse FROM d"""


@query(_gate_sql())
def gate_mlp_literal(spark, sf):
    """The trained gate of the first layer on raw tokens, as columns: similarity, reference type and codec hints; importance is 0."""
    x = with_reference(S.activity(spark, sf), S.RING)
    motion, residual = V.codec_hints(F.col("v"), F.col("r"))
    start = (F.pmod(F.col("frame_no") - 2, F.lit(20)) == 0).cast("double")
    zero = F.lit(0.0)
    feat = F.array(V.cosine(F.col("v"), F.col("r")), zero, start, 1 - start, zero, zero, motion, residual)
    d = F.transform(F.array(feat), lambda v: V.mlp(v, modules("activity")[0], "g1", "gb1", "g2", "gb2")[0])[0]  # the inputs are worked out once, not for each hidden unit
    return x.select("video_id", "frame_no", "token_no", d.alias("d")).select("video_id", "frame_no", "token_no", F.round("d", 5).alias("logit"), (F.col("d") > 0).alias("reuse"))


# ---- closed forms -------------------------------------------------------------------------------------------------

PRESETS = {n: EncoderSpec.preset(n) for n in ("small", "base", "large")}


TURNS = "turns AS (SELECT conv_id AS v, count(*) AS n FROM conversations WHERE conv_id IS NOT NULL AND text IS NOT NULL GROUP BY conv_id), tot AS (SELECT CAST(coalesce(sum(n), 0) AS BIGINT) AS frames, count(*) AS videos, CAST(coalesce(max(n), 0) AS BIGINT) AS longest FROM turns)"


def turns(spark, sf) -> DataFrame:
    """v, n: each conversation and its frames."""
    return table(spark, sf, "conversations").where("conv_id is not null and text is not null").groupBy(F.col("conv_id").alias("v")).agg(F.count(F.lit(1)).alias("n"))


def turn_totals(spark, sf) -> DataFrame:
    """frames, videos, longest of the conversations; one row, broadcast."""
    return F.broadcast(turns(spark, sf).agg(F.coalesce(F.sum("n"), F.lit(0).cast("bigint")).alias("frames"), F.count(F.lit(1)).alias("videos"), F.coalesce(F.max("n"), F.lit(0).cast("bigint")).alias("longest")))


@query(f"WITH {TURNS}, s(name, d) AS (VALUES ('small', 384), ('base', 768), ('large', 1024)), p AS (SELECT name, unnest(['qkv', 'attention', 'projection', 'ffn']) AS part, unnest([6 * 257 * d * d, 4 * 257 * 257 * d, 2 * 257 * d * d, 16 * 257 * d * d]) AS flops FROM (SELECT name, CAST(d AS BIGINT) AS d FROM s)) SELECT name, part, flops * frames AS flops, flops / sum(flops) OVER (PARTITION BY name) AS share FROM p, tot")
def layer_flops(spark, sf):
    """One layer over all frames of the conversations."""
    return measures.layer_flops(spark, PRESETS).crossJoin(turn_totals(spark, sf)).select("name", "part", (F.col("flops") * F.col("frames")).alias("flops"), "share")


@query(f"""WITH {TURNS}, l AS (SELECT CAST(r AS INT) AS layer FROM range(0, 24) t(r)), p(part, per) AS (VALUES ('qkv', 1024 * 3 * 1024 * 2), ('attention', 2 * 257 * 1024 * 2), ('projection', 1024 * 1024 * 2), ('ffn', 2 * 1024 * 4096 * 2))
SELECT layer, part, part IN ('qkv', 'ffn') AND NOT (part = 'qkv' AND layer = 0) AS reusable, CAST(per AS BIGINT) * 257 * frames AS flops FROM l, p, tot""")
def reuse_sites(spark, sf):
    """What of the large encoder's layers may be reused, over all tokens of the conversations."""
    return measures.reuse_sites(spark, PRESETS["large"]).crossJoin(turn_totals(spark, sf)).select("layer", "part", "reusable", (F.col("flops") * PRESETS["large"].n_tokens * F.col("frames")).alias("flops"))


@query(f"WITH {TURNS}, i AS (SELECT k, sum((n + k - 1) // k) AS whole FROM turns, (VALUES (4), (8), (12), (20), (40)) t(k) GROUP BY k) SELECT CAST(k AS INT) AS reset_every, (CAST(0.61 AS DOUBLE) * CAST(0.88 AS DOUBLE)) * (CAST(whole AS DOUBLE) / frames) AS overhead FROM i, tot")
def reset_overhead(spark, sf):
    """What the whole frames of the conversations, one in each begun epoch, add at several reset periods."""
    x = turns(spark, sf).select("n", F.explode(F.array(*map(F.lit, (4, 8, 12, 20, 40)))).alias("reset_every"))
    x = x.groupBy("reset_every").agg(F.sum(F.ceil(F.col("n") / F.col("reset_every"))).alias("whole"), F.sum("n").alias("frames"))
    return x.select("reset_every", (F.lit(0.61 * 0.88) * (F.col("whole").cast("double") / F.col("frames"))).alias("overhead"))


@query("SELECT CAST(count(*) * 2048 AS BIGINT) AS embedding_bytes, CAST(sum(strlen(text)) AS BIGINT) AS source_bytes, CAST(count(*) * 2048 AS DOUBLE) / sum(strlen(text)) AS share FROM conversations WHERE conv_id IS NOT NULL AND text IS NOT NULL")
def storage_overhead(spark, sf):
    """Half-precision embeddings of all conversation frames, against the texts they are made of."""
    x = table(spark, sf, "conversations").where("conv_id is not null and text is not null")
    x = x.agg((F.count(F.lit(1)) * 2 * PRESETS["large"].dim).alias("embedding_bytes"), F.sum(F.octet_length("text")).alias("source_bytes"))
    return x.withColumn("share", F.col("embedding_bytes").cast("double") / F.col("source_bytes"))


SEGMENTS = f"{TURNS}, sg AS (SELECT unnest(range(0, (longest + 2) // 4)) AS segment FROM tot WHERE longest > 1), ly AS (SELECT unnest(range(0, 24)) AS layer), st AS (SELECT layer, segment, segment * 24 + layer AS step, 4 AS alloc, 3 + (segment > 0)::INT AS free FROM sg, ly)"


def longest_segments(spark, sf) -> int:
    """The segments of four frames of the longest conversation, after its first frame."""
    return (max(1, turn_totals(spark, sf).first()["longest"]) + 2) // 4


@query(f"WITH {SEGMENTS} SELECT CAST(step AS INT) AS step, CAST(layer AS INT) AS layer, CAST(segment AS INT) AS segment, CAST(alloc AS BIGINT) AS alloc, CAST(free AS BIGINT) AS free, CAST(sum(alloc) OVER (ORDER BY step) - coalesce(sum(free) OVER (ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS live_units FROM st")
def cache_trace(spark, sf):
    """The caches of the longest conversation, its last segment taken as whole."""
    return measures.cache_trace(spark, PRESETS["large"], segments=longest_segments(spark, sf))


@query(f"""WITH {SEGMENTS}, freed AS (SELECT max(live) AS peak FROM (SELECT sum(alloc) OVER (ORDER BY step) - coalesce(sum(free) OVER (ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS live FROM st)), kept AS (SELECT sum(alloc) AS peak FROM st)
SELECT 'layer, freed' AS schedule, CAST(peak AS BIGINT) AS peak FROM freed UNION ALL SELECT 'layer, kept', CAST(peak AS BIGINT) FROM kept UNION ALL SELECT 'frame, kept', CAST(peak AS BIGINT) FROM kept""")
def cache_peak(spark, sf):
    """Peak of the longest conversation's segments in 24 layers, in cached frames x layers."""
    out, n = None, longest_segments(spark, sf)
    for name, schedule, free in (("layer, freed", "layer", True), ("layer, kept", "layer", False), ("frame, kept", "frame", False)):
        x = measures.cache_trace(spark, PRESETS["large"], segments=n, schedule=schedule, free_cache=free).agg(F.max("live_units").cast("bigint").alias("peak")).select(F.lit(name).alias("schedule"), "peak")
        out = x if out is None else out.unionAll(x)
    return out


@query(f"WITH {TURNS}, p(caches, peak_bytes) AS (VALUES ('none', CAST(5 * 24 AS BIGINT) * 257 * 4096 * 2), ('freed', CAST(28 AS BIGINT) * 257 * 4096 * 2)), m AS (SELECT *, CAST(floor((24000000000 - 600000000) / peak_bytes) AS BIGINT) AS max_batch FROM p) SELECT caches, peak_bytes, max_batch, CAST((videos + max_batch - 1) // max_batch AS BIGINT) AS batches FROM m, tot")
def max_batch(spark, sf):
    """Videos that fit at once, and how many such batches the conversations are."""
    x = measures.max_batch(spark, 24_000_000_000, PRESETS["large"], fixed_bytes=600_000_000).crossJoin(turn_totals(spark, sf))
    return x.select("caches", "peak_bytes", "max_batch", F.ceil(F.col("videos") / F.col("max_batch")).cast("bigint").alias("batches"))


@query(f"WITH {TURNS}, r AS (SELECT i / 10.0::DOUBLE AS x FROM range(0, 11) t(i)), p AS (SELECT x, unnest(['qkv', 'ffn', 'attention', 'calibrator', 'gate']) AS part, unnest([6.0 * 1048576 * (257 - x * 257), 16.0 * 1048576 * (257 - x * 257), 4.0 * 257 * 257 * 1024 + 2.0 * 257 * 1048576, x * 257 * 2 * 128 * 4096, 256 * (2 * 8 * 16 + 32 + 12 * 1024.0)])::DOUBLE AS flops FROM r) SELECT x AS reuse_rate, part, round(flops, 0) * frames AS flops, round(flops / (24.0 * 257 * 1048576 + 4.0 * 257 * 257 * 1024), 9)::DOUBLE AS share FROM p, tot")
def flops_breakdown(spark, sf):
    """One layer over all frames of the conversations, by reuse rate."""
    x = measures.flops_breakdown(spark, PRESETS["large"], [i / 10 for i in range(11)]).crossJoin(turn_totals(spark, sf))
    return x.select("reuse_rate", "part", (F.round("flops", 0) * F.col("frames")).alias("flops"), F.round("share", 9).alias("share"))


# ---- query tasks on vectors that are given -------------------------------------------------------------------------

CLIP = "emb AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings)"


@query(f"WITH {CLIP}, s AS (SELECT a.vec_id AS query_id, b.vec_id AS clip_id, round({COS.format('a.e', 'b.e')}, 9) AS score FROM emb a, emb b WHERE a.vec_id % 20 = 0), t AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, clip_id) AS rank FROM s) SELECT query_id, clip_id, CAST(rank AS INT) AS rank, round(score, 6) AS score FROM t WHERE rank <= 5")
def retrieval_top5(spark, sf):
    """Every 20th vector as a query against all vectors."""
    e = table(spark, sf, "embeddings").select(F.col("vec_id").alias("clip_id"), F.col("embedding").cast("array<double>").alias("emb"))
    q = e.where("clip_id % 20 = 0").select(F.col("clip_id").alias("query_id"), F.col("emb").alias("vec"))
    return search.nearest(q, e, 5, digits=9).select("query_id", "clip_id", "rank", F.round("score", 6).alias("score"))


@query(f"WITH {CLIP}, m AS (SELECT label, list(v ORDER BY i) AS p FROM (SELECT label, i, avg(e[i]) AS v FROM emb, range(1, 65) r(i) WHERE vec_id % 5 < 3 GROUP BY label, i) GROUP BY label), s AS (SELECT vec_id, a.label, m.label AS choice, round({COS.format('e', 'p')}, 9) AS score FROM emb a, m WHERE vec_id % 5 >= 3), b AS (SELECT vec_id, label, choice, row_number() OVER (PARTITION BY vec_id ORDER BY score DESC, choice) AS n FROM s) SELECT label, count(*) AS questions, count(*) FILTER (WHERE choice = label) AS correct FROM b WHERE n = 1 GROUP BY label")
def multiple_choice(spark, sf):
    """Which label a held-out vector has, the choices being the mean vectors of the others."""
    e = table(spark, sf, "embeddings").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("emb"))
    p = V.mean_pool(e.where("vec_id % 5 < 3"), ["label"]).select(F.col("label").alias("choice_no"), F.col("emb").alias("vec"))
    q = e.where("vec_id % 5 >= 3").select(F.col("vec_id").alias("query_id"), "emb")
    x = q.crossJoin(tasks._side(p)).select("query_id", "choice_no", F.round(V.cosine(F.col("emb"), F.col("vec")), 9).alias("score"))
    a = x.groupBy("query_id").agg(F.min_by("choice_no", F.struct(-F.col("score"), F.col("choice_no"))).alias("choice_no"))
    return a.join(e.select(F.col("vec_id").alias("query_id"), "label"), "query_id").groupBy("label").agg(F.count(F.lit(1)).alias("questions"), F.count_if(F.col("choice_no") == F.col("label")).alias("correct"))


GROUND = "tick AS (SELECT user_id AS u, CAST(floor(epoch(ts - (SELECT date_trunc('day', min(ts))::TIMESTAMP FROM events)) / 21600) AS INT) + 1 AS f, sum(value) AS s FROM events WHERE event_type = 'purchase' GROUP BY ALL)"


@query(f"WITH {GROUND}, h AS (SELECT * FROM tick WHERE s >= 50), i AS (SELECT u, f, s, f - row_number() OVER (PARTITION BY u ORDER BY f) AS g FROM h), r AS (SELECT u, g, min(f) AS lo, max(f) AS hi, round(sum(s), 6) AS total FROM i GROUP BY ALL), b AS (SELECT *, row_number() OVER (PARTITION BY u ORDER BY total DESC, lo) AS n FROM r) SELECT u AS query_id, CAST(lo AS INT) AS lo, CAST(hi AS INT) AS hi FROM b WHERE n = 1")
def grounding_spans(spark, sf):
    """For each user the run of ticks with purchases of at least 50 that has the greatest total."""
    e = table(spark, sf, "events")
    p = e.where("event_type = 'purchase'").crossJoin(F.broadcast(S.ticks_of(e)))
    s = p.groupBy(F.col("user_id").alias("query_id"), (S.tick_of(F.col("ts"), F.col("start")) + 1).alias("frame_no")).agg(F.sum("value").alias("score"))
    return tasks.ground(s, 50.0, digits=6).drop("total")


# ---- events as windows ----------------------------------------------------------------------------------------------


@query("SELECT user_id, CAST(floor(epoch(ts - TIMESTAMP '2024-01-01') / 21600) AS BIGINT) AS tick, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def event_frames_tumbling(spark, sf):
    e = table(spark, sf, "events").groupBy("user_id", F.window("ts", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return e.select("user_id", F.floor(F.timestamp_diff("SECOND", F.lit("2024-01-01").cast("timestamp_ntz"), F.col("w.start")) / 21600).alias("tick"), "n", "total")


@query("SELECT user_id, CAST(k - j AS BIGINT) AS tick, count(*) AS n, round(sum(value), 4) AS total FROM (SELECT user_id, value, CAST(floor(epoch(ts - TIMESTAMP '2024-01-01') / 21600) AS BIGINT) AS k FROM events), range(0, 12) a(j) GROUP BY ALL")
def event_frames_sliding(spark, sf):
    """Windows of 72 hours which begin every six."""
    e = table(spark, sf, "events").groupBy("user_id", F.window("ts", "72 hours", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return e.select("user_id", F.floor(F.timestamp_diff("SECOND", F.lit("2024-01-01").cast("timestamp_ntz"), F.col("w.start")) / 21600).alias("tick"), "n", "total")


@query("SELECT CAST(json_extract(props, '$.k') AS INT) AS k, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def event_props(spark, sf):
    """Totals by a number in the events' JSON."""
    e = table(spark, sf, "events").select(F.from_json("props", "k int")["k"].alias("k"), "event_type", "value")
    return e.groupBy("k", "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))


@query("WITH e AS (SELECT user_id, ts, value, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events), s AS (SELECT *, sum(CASE WHEN p IS NULL OR ts >= p + INTERVAL 12 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM e) SELECT user_id, min(ts) AS first, max(ts) AS last, count(*) AS n, round(sum(value), 4) AS total FROM s GROUP BY user_id, g")
def event_sessions(spark, sf):
    e = table(spark, sf, "events")
    return e.groupBy("user_id", F.session_window("ts", "12 hours")).agg(F.min("ts").alias("first"), F.max("ts").alias("last"), F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total")).drop("session_window")


@query("SELECT e.event_id, max(a.ts) AS anchor FROM events e LEFT JOIN events a ON a.user_id = e.user_id AND a.event_type = 'signup' AND a.ts <= e.ts GROUP BY e.event_id")
def asof_anchor(spark, sf):
    """The nearest earlier sign-up of the same user, by one window and no range join."""
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    return table(spark, sf, "events").select("event_id", F.last(F.when(F.col("event_type") == "signup", F.col("ts")), ignorenulls=True).over(w).alias("anchor"))
