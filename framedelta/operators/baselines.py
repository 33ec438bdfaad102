"""Other ways to save encoder work, for comparison: merging over time, proxies, cluster indexes, search without a video head."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import vector as V
from ..model import EncoderSpec
from . import encode, search, tasks


def temporal_merge(frames: DataFrame, spec: EncoderSpec, window: int = 4) -> DataFrame:
    """EMBEDDINGS in which each `window` frames in a row share the embedding of their mean tokens; its cost is shared too."""
    x = frames.withColumn("_w", F.floor((F.col("frame_no") - 1) / window))
    merged = V.mean_pool(x, ["video_id", "_w"], "tokens").select("video_id", F.col("_w").cast("int").alias("frame_no"), "tokens")
    z = encode.full_encode(merged, spec).select("video_id", F.col("frame_no").cast("bigint").alias("_w"), "emb", "flops")
    n = x.groupBy("video_id", "_w").agg(F.count(F.lit(1)).alias("_n"))
    y = x.select("video_id", "frame_no", "_w").join(z.join(n, ["video_id", "_w"]), ["video_id", "_w"])
    return y.select("video_id", "frame_no", "emb", F.lit(None).cast("double").alias("reuse_rate"), (F.col("flops") / F.col("_n")).alias("flops"))


def frame_search(queries: DataFrame, embeddings: DataFrame, k: int = 5) -> DataFrame:
    """query_id, video_id, frame_no, score, rank: the nearest frames themselves, with no pooling over a clip.

    Queries are broadcast up to tasks.BROADCAST_ROWS. Each task keeps the best k of its frames for every query, so no pair of a query and a frame becomes a row.
    """
    import numpy as np
    import pyarrow as pa

    spark = queries.sparkSession
    rows = queries.select("query_id", "vec").where("vec is not null").limit(tasks.BROADCAST_ROWS + 1).collect()
    if not rows or len(rows) > tasks.BROADCAST_ROWS:  # in broadcast blocks
        clips = embeddings.select(F.struct("video_id", "frame_no").alias("clip_id"), "emb")
        return tasks.retrieve(queries, clips, k).select("query_id", "clip_id.video_id", "clip_id.frame_no", "score", "rank")
    sent = spark.sparkContext.broadcast((np.array([r["query_id"] for r in rows], np.int64), np.array([r["vec"] for r in rows], float)))
    types = dict(queries.dtypes) | dict(embeddings.dtypes)

    def dots(x, y):
        """Sums of products in the order of the components, so that equal vectors have equal scores in any batch."""
        s = np.multiply.outer(x[:, 0], y[:, 0])
        for i in range(1, x.shape[1]):
            s += np.multiply.outer(x[:, i], y[:, i])
        return s

    def best(batches):
        ids, q = sent.value
        size = np.sqrt((q * q).sum(1))
        score, video, frame = np.full((len(q), k), -np.inf), np.zeros((len(q), k), np.int64), np.zeros((len(q), k), np.int64)
        for b in batches:
            x = np.array(b.column("emb").to_pylist(), float).reshape(b.num_rows, -1)
            v, f = (b.column(c).cast(pa.int64()).to_numpy() for c in ("video_id", "frame_no"))
            for c in range(0, len(x), 512):
                part = x[c : c + 512]
                own = np.sqrt((part * part).sum(1))
                for at in range(0, len(q), 512):
                    norm = np.outer(size[at : at + 512], own)
                    s = np.where(norm > 0, dots(q[at : at + 512], part) / np.where(norm > 0, norm, 1.0), 0.0)
                    better = np.flatnonzero(s.max(1) > score[at : at + 512, -1])
                    s = s[better]
                    i, line = at + better, np.arange(len(better))
                    for _ in range(min(k, len(part))):
                        j = s.argmax(1)  # the first of equals: frames come in order
                        new, s[line, j] = s[line, j], -np.inf
                        score_i, video_i, frame_i = (np.concatenate([t[i], n[:, None]], axis=1) for t, n in ((score, new), (video, v[c + j]), (frame, f[c + j])))
                        order = np.argsort(-score_i, axis=1, kind="stable")[:, :k]
                        score[i], video[i], frame[i] = (np.take_along_axis(t, order, 1) for t in (score_i, video_i, frame_i))
        n, m = np.nonzero(score > -np.inf)
        for at in range(0, len(n), 10_000):
            i, j = n[at : at + 10_000], m[at : at + 10_000]
            yield pa.RecordBatch.from_arrays([pa.array(ids[i]), pa.array(video[i, j]), pa.array(frame[i, j]), pa.array(score[i, j])], ["query_id", "video_id", "frame_no", "score"])

    dealt = embeddings.where("emb is not null").select("video_id", "frame_no", "emb").repartition(spark.sparkContext.defaultParallelism).sortWithinPartitions("video_id", "frame_no")
    x = dealt.mapInArrow(best, "query_id bigint, video_id bigint, frame_no bigint, score double")
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "video_id", "frame_no")
    x = x.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
    return x.select(*[F.col(c).cast(types[c]) for c in ("query_id", "video_id", "frame_no")], "score", "rank")


def representatives(vectors: DataFrame, k: int = 32, sample: int = 2000):
    """(ids, unit vectors) of k vectors far from each other, by farthest-first on a bounded sample of (id, emb); `sample` is its bound."""
    import numpy as np

    n = max(1, vectors.count())
    rows = vectors.where(F.pmod(F.xxhash64("id"), F.lit(1 << 20)) < (1 << 20) * min(1.0, sample / n)).orderBy(F.xxhash64("id"), "id").limit(2 * sample).collect()
    if not rows:
        return [], None
    x = np.array([r["emb"] for r in rows], float)
    x /= np.linalg.norm(x, axis=1, keepdims=True) + 1e-12
    picked, best = [0], x @ x[0]
    while len(picked) < min(k, len(x)):
        picked.append(int(best.argmin()))
        best = np.maximum(best, x @ x[picked[-1]])
    return [rows[i]["id"] for i in picked], x[picked]


def near_reps(vectors: DataFrame, column: str, ids: list, reps, probe: int, out: str = "near") -> DataFrame:
    """vectors with a column of (representative, similarity, part) of the `probe` nearest of the representatives, nearest first, of equal ones the smaller id; part is their number."""
    import numpy as np
    import pyarrow as pa

    spark = vectors.sparkSession
    encode.ship(spark)
    kind = {"int": pa.int32(), "bigint": pa.int64()}[dict(vectors.dtypes).get("id", "bigint")]
    order = sorted(range(len(ids)), key=lambda i: ids[i])
    sent = spark.sparkContext.broadcast((np.array(ids)[order], np.array(reps)[order], np.array(order)))
    probe = min(probe, len(ids))

    def run(batches):
        names, r, numbers = sent.value
        nr = search.lengths(r)
        for b in batches:
            x = search.matrix(b.column(column), r.shape[1])
            nx = search.lengths(x)
            s = np.stack([search.cosines(x, np.broadcast_to(v, x.shape), nx, n) for v, n in zip(r, nr, strict=True)], axis=1)
            near = np.argsort(-s, axis=1, kind="stable")[:, :probe]
            flat = pa.StructArray.from_arrays([pa.array(names[near].ravel(), kind), pa.array(np.take_along_axis(s, near, 1).ravel()), pa.array(numbers[near].ravel().astype(np.int32))], ["representative", "similarity", "part"])
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, near.size + 1, probe, dtype=np.int32)), flat)
            yield pa.RecordBatch.from_arrays([*b.columns, lists], [*b.schema.names, out])

    types = ", ".join(f"`{c}` {t}" for c, t in vectors.dtypes)
    return vectors.mapInArrow(run, f"{types}, `{out}` array<struct<representative: {'int' if kind == pa.int32() else 'bigint'}, similarity: double, part: int>>")


def cluster_index(vectors: DataFrame, k: int = 32, sample: int = 2000) -> DataFrame:
    """id, representative, similarity: each vector's nearest representative; every vector is indexed.

    Scored by representatives alone, members take over their score, so what is rare is answered badly; cluster_search looks at the members.
    """
    ids, reps = representatives(vectors, k, sample)
    if not ids:
        return vectors.select("id", F.lit(None).cast("bigint").alias("representative"), F.lit(None).cast("double").alias("similarity"))
    return near_reps(vectors.select("id", "emb"), "emb", ids, reps, 1).select("id", F.col("near")[0].alias("r")).select("id", "r.representative", "r.similarity")


def cluster_search(vectors: DataFrame, queries: DataFrame, top: int = 5, k: int = 32, probe: int = 28, sample: int = 2000) -> DataFrame:
    """query_id, clip_id, score, rank: the `top` best among the members behind each query's `probe` nearest representatives.

    Members are dealt to tasks whatever their cluster, and a task keeps `top` of a query's candidates before they meet, so neither a large cluster nor a
    frequent query lands in one task.
    """
    ids, reps = representatives(vectors, k, sample)
    if not ids:
        return queries.sparkSession.createDataFrame([], f"query_id {dict(queries.dtypes)['query_id']}, clip_id {dict(vectors.dtypes)['id']}, score double, rank int")
    members = near_reps(vectors.select("id", "emb"), "emb", ids, reps, 1).select(F.col("id").alias("clip_id"), "emb", F.col("near")[0]["part"].alias("part"))
    asked = near_reps(queries.select("query_id", "vec"), "vec", ids, reps, probe).select("query_id", "vec", F.transform("near", lambda r: r["part"]).alias("parts"))
    return search.nearest(asked, members, top)


def fit_rates(frames, spec: EncoderSpec, flops_x: float) -> tuple[tuple[int, ...], tuple[int, ...]]:
    """(prune, merge) of each layer for the in-frame baseline: one more token at a time goes where it costs the least likeness for the work it saves, until the encoder is flops_x cheaper."""
    import numpy as np

    from . import kernel

    exact = kernel.exact(frames, spec)
    rates = np.zeros((2, spec.layers), int)
    tried: dict = {}

    def run(r):
        key = tuple(map(tuple, r))
        if key not in tried:
            z, flops = kernel.reduced(frames, spec, *key)
            tried[key] = float(kernel.cosine(z, exact).mean()), flops
        return tried[key]

    while run(rates)[1] * flops_x > kernel.flops_exact(spec):
        now, steps = run(rates), []
        for way in range(2):
            for layer in range(spec.layers):
                more = rates.copy()
                more[way, layer] += 1
                got = run(more)
                if got[1] < now[1]:
                    steps.append(((now[0] - got[0]) / (now[1] - got[1]), way, layer))
        if not steps:
            break
        _, way, layer = min(steps)
        rates[way, layer] += 1
    return tuple(map(int, rates[0])), tuple(map(int, rates[1]))


def proxy_cascade(rows: DataFrame, exact: DataFrame, low: float = 0.2, high: float = 0.8, train: str = "is_train") -> DataFrame:
    """id, p, label, asked: a cheap logistic proxy on (id, emb, label, is_train) answers where it is sure, (id, answer) of the exact way elsewhere."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector, vector_to_array

    x = rows.withColumn("features", array_to_vector("emb")).withColumn("label", F.col("label").cast("double"))
    model = LogisticRegression(maxIter=20, regParam=0.01).fit(x.where(train))
    p = model.transform(x.where(f"not {train}")).select("id", F.get(vector_to_array("probability"), F.lit(1)).alias("p"))
    asked = F.col("p").between(low, high)
    return p.join(exact, "id", "left").select("id", "p", F.when(asked, F.col("answer")).otherwise((F.col("p") > 0.5).cast("int")).alias("label"), asked.alias("asked"))
