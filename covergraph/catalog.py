"""Registry of the queries outside the llm subpackage."""

from __future__ import annotations

import uuid
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles as sql
from .functions import sqlapi
from .functions.exact import Share
from .functions.metric import expression, lattice
from .operators import audit, cliques, prune, search
from .plans import evaluate, relational
from .sources import points as source
from .sources import storage
from .streaming import arrivals

#: Shares of the degree table.
TABLE_SHARES = ["1", "0.995", "0.95"]
SELF_SHARES = ["1", "0.995", "0.95", "0.9"]
PEEL, SAMPLED, DELTA = "0.8", "0.8", 0.1


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Covered points and out-degree of each node of the exact clique-peel graph."""
    pts = source.embeddings(spark, sf_dir)
    edges = source.stage(cliques.peel(pts, PEEL).edges())
    degree = edges.groupBy("src").agg(F.count_distinct("dst").alias("degree"))
    return audit.covered_counts(pts, edges).join(degree, "src", "left").select("src", "covered", F.coalesce("degree", F.lit(0)).alias("degree"))


def _r(name: str, digits: int = 6):
    return F.round(name, digits).alias(name)


def _points(f):
    return lambda spark, sf_dir: f(spark, source.embeddings(spark, sf_dir))


def _pruned(f, share=1):
    """f(points, edges of the nearest-first prune, n)."""

    def run(spark, sf_dir):
        pts = source.stage(source.embeddings(spark, sf_dir))
        return f(pts, source.stage(prune.prune(pts, share)), pts.count())

    return run


def _peeled(f, delta=None, share=PEEL):
    return lambda spark, sf_dir: f(cliques.peel(source.embeddings(spark, sf_dir), share, delta))


def profile(spark, sf_dir):
    return source.profile(source.embeddings(spark, sf_dir))


def dedupe(spark, sf_dir):
    return source.dedupe(source.text_vectors(source.table(spark, sf_dir, "documents"))).select("id", "copies")


def jitter_unique(spark, pts):
    """Distinct vectors before and after a small move."""
    twice = pts.unionByName(pts.withColumn("id", F.col("id") + 1000000))
    moved = source.jitter(twice, 0.25)
    return twice.agg(F.count_distinct("vec").alias("before")).crossJoin(moved.agg(F.count_distinct("vec").alias("after"), F.count(F.lit(1)).alias("n")))


def text_vectors(spark, sf_dir):
    v = source.text_vectors(source.table(spark, sf_dir, "documents"))
    return v.select("id", F.posexplode("vec").alias("bucket", "count")).where("count > 0")


def numeric_vectors(spark, sf_dir):
    v = source.line_item_vectors(source.table(spark, sf_dir, "lineitem"))
    return v.select("id", *[F.col("vec")[i].alias(c) for i, c in enumerate("abcd")])


def nearest_by(metric: str):
    """Each embedding's nearest other one under a metric."""

    def run(spark, sf_dir):
        pts = source.stage(source.embeddings(spark, sf_dir))
        near = search.knn_exact(pts, pts.withColumnRenamed("id", "qid"), 2, metric)
        return near.where("id <> qid").withColumn("r", F.row_number().over(_by_qid())).where("r = 1").select("qid", "id", _r("dist") if metric == "cosine" else F.col("dist").cast("long").alias("dist"))

    return run


def _by_qid():
    from pyspark.sql import Window as W

    return W.partitionBy("qid").orderBy("dist", "id")


def pair_distances(metric: str):
    """All pairs of benchmark items, whose number is fixed: the set metrics need no vectors."""

    def run(spark, sf_dir):
        b = source.table(spark, sf_dir, "benchmark")
        side = lambda n: b.select(F.col("item_id").alias(n), (F.array_distinct(source.tokens(F.col("text"))) if metric == "jaccard" else F.substring("text", 1, 1 << 30)).alias(f"{n}_x"))
        a, c = side("a"), side("b")
        return a.join(F.broadcast(c), F.col("a") < F.col("b")).select("a", "b", F.round(expression(metric, F.col("a_x"), F.col("b_x")).cast("double"), 6).alias("dist"))

    return run


def thresholds(spark, sf_dir):
    n = source.table(spark, sf_dir, "embeddings").count()
    rows = [(s.num, s.den, s.need(n), s.clique(2), s.clique(4)) for s in (Share.of(x) for x in ("0", "0.5", (2, 3), "0.8", "0.9", "0.95", "0.98", "0.99", "0.995", "0.999"))]
    return spark.createDataFrame(rows, "num long, den long, need long, s2 long, s4 long")


def ownership_ties(spark, sf_dir):
    """Twelve points at equal distances, in chunks of four: each owns itself and ties for the eight outside."""
    pts = spark.createDataFrame([(i, [float(i == j) for j in range(12)]) for i in range(12)], "id long, vec array<double>")
    return cliques.peel(pts, "0.5").members.select("member", "owned")


def sql_distance(spark, sf_dir):
    """Distance of each embedding to the first one, through the SQL function."""
    sqlapi.register(spark)
    source.embeddings(spark, sf_dir).createOrReplaceTempView("lattice_points")
    return spark.sql("SELECT a.id, CAST(vector_l2sq(a.vec, b.vec) AS BIGINT) AS dist FROM lattice_points a CROSS JOIN (SELECT vec FROM lattice_points WHERE id = 0) b")


def sql_clique_edges(spark, sf_dir):
    """Edges of the nations of each region, through the table function."""
    sqlapi.register(spark)
    source.table(spark, sf_dir, "nation").createOrReplaceTempView("nation_rows")
    return spark.sql("SELECT e.src, e.dst FROM (SELECT collect_list(CAST(n_nationkey AS BIGINT)) AS ids FROM nation_rows GROUP BY n_regionkey) g, LATERAL clique_edges(g.ids) e")


def _text_peel(f, delta=None):
    """f over the peel of distinct text vectors, which takes several rounds and has ties."""
    return lambda spark, sf_dir: f(cliques.peel(source.dedupe(source.text_vectors(source.table(spark, sf_dir, "documents"))), PEEL, delta))


def first_edge_is_nearest(pts, edges, n):
    """Nodes whose first link is not their nearest point: none."""
    near = search.knn_exact(pts, pts.withColumnRenamed("id", "qid"), 2).where("id <> qid").groupBy("qid").agg(F.min(F.struct("dist", "id")).alias("m"))
    return edges.where("rank = 1").join(near, F.col("src") == F.col("qid")).where("dst <> m.id").select("src", "dst")


def beam_shards(index, queries, edges):
    """Recall at 10 of four shards' graphs together, by query."""
    found = search.beam_sharded(index, queries, 4, 1, 64, 10, own=True)
    truth = search.knn_exact(index, queries, 10, own=True).select("qid", "id")
    return found.join(truth, ["qid", "id"], "left_semi").groupBy("qid").agg(F.count(F.lit(1)).alias("hits"))


def beam_starts(index, queries, edges):
    """The same beam from the first point, from the one nearest to the mean, and from one drawn for each query: recall and cost."""
    g, truth, out = search.Graph(index, edges), search.knn_exact(index, queries, 10, own=True), None
    for name, start in (("first", 0), ("medoid", "medoid"), ("random", "random")):
        found = search.beam_sweep(g, queries, [64], [10], start=start, own=True)
        one = evaluate.recall(found, truth).agg(F.lit(name).alias("start"), _avg("recall"), F.round(F.avg("dist_evals"), 6).alias("dc"))
        out = one if out is None else out.unionByName(one)
    return out


def stream_distance(spark, sf_dir):
    """Arrivals as queries: each event asks for the neighbour of point event_id mod n; distance by hour."""
    pts = source.stage(source.embeddings(spark, sf_dir))
    n = pts.count()
    near = search.knn_exact(pts, pts.withColumnRenamed("id", "qid"), 2).where("id <> qid").groupBy("qid").agg(F.min("dist").cast("long").alias("dist"))
    asked = arrivals.events(spark, sf_dir).withColumn("qid", F.col("event_id") % n).join(source.stage(near), "qid")
    hours = asked.groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.max("dist").alias("worst"))
    return arrivals.drained(hours).select(F.unix_timestamp("w.start").alias("start_s"), "n", "worst")


def half_kept(members):
    """Per full chunk: members that own at most twice their fair share; at least half do."""
    w = members.groupBy("round", "chunk").agg(F.sum("owned").alias("owned"), F.sum(F.col("kept").cast("long")).alias("kept"), F.count(F.lit(1)).alias("size"))
    return w.withColumn("half", F.col("kept") * 2 >= F.col("size"))


def size_report(p):
    """Edges, whether they are within the theory's bound, and bytes: of edges spelled out, and of cliques with implicit leftovers."""
    e = p.edges().distinct()
    n = p.points.count()
    held = p.members.count() * 24 + p.leftovers.count() * 8
    return e.agg(F.count(F.lit(1)).alias("edges"), (F.count(F.lit(1)) <= 4 * n * 5).alias("within_bound"), (F.count(F.lit(1)) * 16).alias("edge_bytes"), F.lit(held).cast("long").alias("clique_bytes"))


def peel_log(p):
    """Every round: pool, chunks, distances and how far the pool shrinks."""
    return p.rounds().select("round", "pool", "chunks", "kept", "carried", "distances", F.round(F.col("carried") / F.col("pool"), 6).alias("shrink"))


def reachable_share(p):
    seen = audit.reachable(source.stage(p.edges()), 0)
    n = p.points.count()
    return seen.agg(F.count(F.lit(1)).alias("reached"), F.round(F.count(F.lit(1)) / max(1, n), 6).alias("share"))


def sample_draw(spark, pts):
    import numpy as np

    n = pts.count()
    w = Share.of(SAMPLED).sample(n, DELTA)
    pos, mult = np.unique(cliques.draws(n, w, 1, 1), return_counts=True)
    return spark.createDataFrame([(int(p), int(m)) for p, m in zip(pos, mult, strict=True)], "pos long, mult long")


def _sets(spark, sf_dir):
    """The three point sets of the given tables, the smaller first."""
    yield "embeddings", source.stage(source.embeddings(spark, sf_dir))
    yield "text", source.stage(_texts(spark, sf_dir))
    yield "items", source.stage(source.line_item_vectors(source.table(spark, sf_dir, "lineitem")))


def _texts(spark, sf_dir):
    return source.dedupe(source.text_vectors(source.table(spark, sf_dir, "documents"))).select("id", "vec")


def distance_cost(spark, sf_dir):
    """Distances of the exact peel and of sampled ones at two deltas, on sets of growing size:
    the exact peel's share of all pairs stays, a sampled one's falls like 1/n."""
    out = []

    def cost(ids, vecs, case, share, delta):
        log = cliques.peel_here(ids, vecs, share, delta)[2]
        return case, len(log), sum(r["distances"] for r in log)

    def apart(pts, share, delta):
        log = (cliques.peel_sent(pts, share) if delta is None and source.fits(pts) else cliques.peel(pts, share, delta)).log
        return len(log), sum(r["distances"] for r in log)

    for name, pts in _sets(spark, sf_dir):
        n = pts.count()
        cases = [(share, delta) for share in ("0.8", "0.9") for delta in (None, 0.1, 0.01)]
        done, rest = {}, cases
        if source.fits(pts):  # a sampled peel is a task's work, an exact one that of all tasks
            sampled = [c for c in cases if c[1]]
            done = {sampled[r["case"]]: (r["rounds"], r["distances"]) for r in cliques.peels_here(pts, sampled, cost, "case long, rounds int, distances long").collect()}
            rest = [c for c in cases if not c[1]]
        with ThreadPoolExecutor(4) as side_by_side:
            done |= dict(zip(rest, side_by_side.map(lambda c: apart(pts, *c), rest), strict=True))  # noqa: B023
        for c in cases:
            rounds, d = done[c]
            d = d if rounds else None
            out.append((name, n, *c, rounds or None, d, None if d is None else d / max(1, n * n)))
    return spark.createDataFrame(out, "points string, n long, share string, delta double, rounds int, distances long, part_of_all double")


def seed_success(spark, pts):
    """Sampled peels of twenty seeds at two deltas: how many are valid, against 1 - delta."""
    pts = source.stage(pts)

    def valid(ids, vecs, case, delta, seed):
        rounds, left, _ = cliques.peel_here(ids, vecs, SAMPLED, delta, seed=seed)
        return case, cliques.covers_here(vecs, rounds, left, Share.of(SAMPLED).need(len(ids)))

    cases = [(delta, seed) for delta in SEED_DELTAS for seed in range(1, SEEDS + 1)]
    good = [cases[r["case"]][0] for r in cliques.peels_here(pts, cases, valid, "case long, ok boolean").collect() if r["ok"]]
    out = [(delta, SEEDS, k := good.count(delta), k / SEEDS, k / SEEDS >= 1 - delta) for delta in SEED_DELTAS]
    return spark.createDataFrame(out, "delta double, seeds long, valid long, rate double, enough boolean")


#: Seeds and deltas of the success rate; nodes probed on large sets.
SEEDS, SEED_DELTAS, PROBES = 20, (0.1, 0.01), 10_000


def degree_table(pts, edges, n):
    out = None
    for s in TABLE_SHARES:
        one = audit.degree_stats(pts, prune.cut(edges, s, n)).select(F.lit(s).alias("share"), _r("mean"), _r("median"), "min", "max")
        out = one if out is None else out.unionByName(one)
    return out


def probe_vs_full(pts, edges, n):
    """Mean degree over a tenth of the nodes as probes, against all."""
    probes = pts.where(F.col("id") % 10 == 3)
    return audit.degree_stats(pts, edges).select(F.lit("all").alias("nodes"), _r("mean")).unionByName(audit.degree_stats(probes, edges.join(probes.select(F.col("id").alias("src")), "src", "left_semi")).select(F.lit("probes").alias("nodes"), _r("mean")))


def probe_line_items(spark, sf_dir):
    """Degrees of at most PROBES nodes, drawn by hash, over every line-item vector, for the shares of the degree table."""
    pts = source.stage(source.line_item_vectors(source.table(spark, sf_dir, "lineitem")))
    probes = source.stage(pts.orderBy(F.xxhash64("id"), "id").limit(PROBES))  # a probe sample is the method
    n, edges = pts.count(), source.stage(prune.prune(pts, 1, sources=probes) if source.fits(pts) else prune.probe_prune(pts, probes, 1))
    return degree_table(probes, edges, n)


def degrees_of_texts(spark, sf_dir):
    pts = source.stage(_texts(spark, sf_dir))
    return degree_table(pts, source.stage(prune.prune(pts, 1)), pts.count())


def pruned_by(metric):
    return lambda spark, sf_dir: prune.prune(source.stage(source.embeddings(spark, sf_dir)), "0.95", metric=metric).select("src", "rank", "dst", F.col("dist").cast("long").alias("dist"), "gain", "cum")


def jaccard_peel(f):
    """f over the peel of distinct token sets of documents under Jaccard's distance."""
    return lambda spark, sf_dir: f(cliques.peel(source.dedupe(source.token_sets(source.table(spark, sf_dir, "documents"))), PEEL, metric="jaccard"))


def partition_peel(spark, sf_dir):
    """A sampled peel whose chunks are formed within partitions: does every node cover its need, and without a shuffle?"""
    pts = source.stage(source.embeddings(spark, sf_dir))
    p = cliques.peel(pts, SAMPLED, DELTA, order="partition")
    one = cliques.local_ownership(pts, 20, source.block(pts.limit(5)))
    plan = one._jdf.queryExecution().executedPlan().toString()
    return audit.coverage_check(audit.clique_counts(pts, p.members, p.leftovers), SAMPLED).select("ok", "n_bad").withColumn("shuffles", F.lit("Exchange" in plan))


def _text_search(spark, sf_dir):
    """Documents' text vectors as the index, all benchmark items, held out, as queries."""
    items = source.text_vectors(source.table(spark, sf_dir, "benchmark"), key="item_id").withColumnRenamed("id", "qid")
    return source.stage(_texts(spark, sf_dir)), source.stage(items)


def _from_texts(f):
    return lambda spark, sf_dir: f(evaluate.tradeoff(*_text_search(spark, sf_dir)))


def knn_good_texts(spark, sf_dir):
    """The five nearest documents of quality 1 of each benchmark item: the join with labels comes before the search."""
    _, items = _text_search(spark, sf_dir)
    good = source.table(spark, sf_dir, "labels").where("quality = 1").select("doc_id").distinct()
    docs = source.text_vectors(source.table(spark, sf_dir, "documents").join(good, "doc_id", "left_semi"))
    return search.knn_exact(docs, items, 5).select("qid", "pos", "id", F.col("dist").cast("long").alias("dist"))


def prune_candidates(spark, pts):
    """Lists whose candidates are the 30 nearest only, and what they cover."""
    pts = source.stage(pts)
    near = search.knn_exact(pts, pts.withColumnRenamed("id", "qid"), 31).where("id <> qid").select(F.col("qid").alias("src"), F.col("id").alias("dst"))
    edges = source.stage(prune.prune(pts, 1, candidates=near))
    return audit.achieved_share(audit.covered_counts(pts, edges.select("src", "dst"))).select(_r("share_min"), _r("share_mean"), _r("share_max"))


def set_cover_vs_prune(spark, pts):
    pts, out = source.stage(pts), None
    for s in ("1", "0.95"):
        for name, f in (("prune", prune.prune), ("cover", prune.set_cover)):
            one = audit.degree_stats(pts, f(pts, s)).select(F.lit(s).alias("share"), F.lit(name).alias("method"), _r("mean"), _r("median"))
            out = one if out is None else out.unionByName(one)
    return out


def complete_check(spark, pts):
    """Every node linked to all others: links stay implicit, as the cliques' leftovers do, and coverage is still counted from distances."""
    pts = source.stage(pts)
    return audit.coverage_check(audit.covered_counts(pts, spark.createDataFrame([], "src long, dst long"), all_linked=pts), 1)


def _split(spark, sf_dir):
    index, queries = source.split(source.embeddings(spark, sf_dir))
    return source.stage(index), source.stage(queries)


def knn(spark, sf_dir):
    index, queries = _split(spark, sf_dir)
    return search.knn_exact(index, queries, 10, own=True).select("qid", "pos", "id", F.col("dist").cast("long").alias("dist"))


def knn_filtered(spark, sf_dir):
    """Neighbours among the points of label 3: the filter comes before the search."""
    e = source.table(spark, sf_dir, "embeddings").where("label = 3").select(F.col("vec_id").alias("id"))
    _, queries = _split(spark, sf_dir)
    return search.knn_exact(source.embeddings(spark, sf_dir).join(e, "id", "left_semi"), queries, 5, own=True).select("qid", "pos", "id")


def radius(spark, sf_dir):
    index, queries = _split(spark, sf_dir)
    return search.radius_search(index, queries, 3.5e14).where("id <> qid").select("qid", "id", F.col("dist").cast("long").alias("dist"))


def _searched(f, share="0.95"):
    """f(index, queries, edges of the prune at a share)."""

    def run(spark, sf_dir):
        index, queries = _split(spark, sf_dir)
        return f(index, queries, source.stage(prune.prune(index, share)))

    return run


def beam_equals_greedy(index, queries, edges):
    """Rows where a beam of one and the greedy walk disagree: none."""
    g = search.Graph(index, edges)
    one = search.beam_sweep(g, queries, [1], [1]).select("qid", F.col("id").alias("b_id"))
    return search.greedy(g, queries).join(one, "qid").where("result <> b_id").select("qid", "result", "b_id")


def joins_equal_greedy(index, queries, edges):
    """Rows where the walk by joins and the walk in memory disagree: none."""
    start = index.agg(F.min("id")).first()[0]
    far = search.greedy_joins(index, edges, queries, start).select("qid", F.col("result").alias("j_id"), F.col("steps").alias("j_steps"))
    return search.greedy(search.Graph(index, edges), queries).join(far, "qid").where("result <> j_id or steps <> j_steps").select("qid", "result", "j_id")


def joins_equal_beam(index, queries, edges):
    """Rows where the beam by joins and the beam in memory disagree, in what they find or in cost: none."""
    start = index.agg(F.min("id")).first()[0]
    near = search.beam_sweep(search.Graph(index, edges), queries, [4], [4]).select("qid", "pos", "id", "dist_evals", "expanded")
    far = search.beam_joins(index, source.stage(edges), queries, start, 4, 4).select("qid", "pos", "id", "dist_evals", "expanded")
    return near.exceptAll(far).unionByName(far.exceptAll(near))


def stream_recall(spark, sf_dir):
    """Arrivals as queries of a beam of 16: recall at 10 and distance computations by day."""
    index, queries = (source.stage(x) for x in source.split(source.embeddings(spark, sf_dir)))
    found = search.beam_sweep(search.Graph(index, prune.prune(index, "0.995")), queries, [16], [10], own=True)
    asked = source.indexed(queries.select("qid"), "qid")
    known = source.stage(evaluate.recall(found, search.knn_exact(index, queries, 10, own=True)).join(asked, "qid").select("pos", "recall", "dist_evals"))
    n = known.count()
    come = arrivals.events(spark, sf_dir).withColumn("pos", F.col("event_id") % max(n, 1)).join(known, "pos")
    days = come.groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.avg("recall").alias("recall"), F.avg("dist_evals").alias("dc"))
    return arrivals.drained(days).select(F.unix_timestamp("w.start").alias("start_s"), "n", _r("recall"), _r("dc"))


def medoids(spark, sf_dir):
    """The embedding of each label nearest to the label's mean."""
    pts = source.table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "label", lattice(F.col("embedding")).alias("vec"))
    return source.medoids(pts, "label")


def formats(spark, sf_dir):
    """Orders written and read in each format: rows and sums stay."""
    orders, out = source.table(spark, sf_dir, "orders"), None
    for form in ("csv", "json", "orc", "parquet"):
        back = storage.through(orders, form, arrivals.shared(spark))
        one = back.agg(F.lit(form).alias("form"), F.count(F.lit(1)).alias("n"), F.sum("o_orderkey").alias("keys"), F.count_distinct("o_orderpriority").alias("priorities"), F.max("o_orderdate").alias("latest"))
        out = one if out is None else out.unionByName(one)
    return out


def text_lines(spark, sf_dir):
    """Priorities written as lines of text and read back."""
    lines = storage.through(source.table(spark, sf_dir, "orders").select(F.col("o_orderpriority").alias("value")), "text", arrivals.shared(spark))
    return lines.groupBy(F.col("value").alias("priority")).count()


def flat_files(spark, sf_dir):
    """Embeddings written as binary vector files and read by the data source of its own."""
    path = f"{arrivals.shared(spark).removeprefix('file://').removeprefix('file:')}/flat-{uuid.uuid4().hex}"
    storage.write_flat(source.table(spark, sf_dir, "embeddings").select(F.col("embedding").alias("vec")), path)
    spark.dataSource.register(storage.FlatVectorSource)
    back = spark.read.format("flat_vectors").load(path)
    total = F.aggregate("vec", F.lit(0.0), lambda a, x: a + x.cast("double"))
    return back.agg(F.count(F.lit(1)).alias("n"), F.min(F.size("vec")).alias("dim"), F.round(F.sum(total), 4).alias("total"))


def stored_edges(spark, sf_dir):
    """Full lists written in buckets of their source, and the lists of a smaller share read back by a filter."""
    pts = source.stage(source.embeddings(spark, sf_dir))
    name = f"edges_{uuid.uuid4().hex}"
    storage.write_edges(prune.prune(pts, 1), name, f"{arrivals.shared(spark)}/{name}", source.width(pts))
    out = storage.read_edges(spark, name, "0.95", pts.count())
    spark.sql(f"DROP TABLE {name}")  # the files stay, and the plan knows them
    return out.select("src", "rank", "dst", "dist", "gain", "cum")


def stored_cliques(p):
    """Edges multiplied out of cliques that were written and read back."""
    path = f"{arrivals.shared(p.points.sparkSession)}/cliques-{uuid.uuid4().hex}"
    storage.write_cliques(p.members, path)
    p.members = p.points.sparkSession.read.parquet(path)
    return p.edges()


def sql_thresholds(spark, sf_dir):
    sqlapi.register_thresholds(spark)
    n = source.table(spark, sf_dir, "embeddings").count()
    return spark.sql(f"SELECT num, den, coverage_need(num, den, {n}) AS need, clique_size(num, den, 2) AS s2, clique_size(num, den, 4) AS s4, sample_size(num, den, {n}, 0.1) AS w FROM VALUES (1L, 2L), (2L, 3L), (4L, 5L), (19L, 20L), (199L, 200L) AS t(num, den)")


def sql_neighbors(spark, sf_dir):
    """The three nearest points, themselves among them, of every embedding whose id 100 divides, through the table function."""
    pts, queries = _split(spark, sf_dir)
    sqlapi.register_neighbors(spark, *source.block(pts))
    queries.createOrReplaceTempView("asking_points")
    return spark.sql("SELECT q.qid, n.pos, n.id, CAST(n.dist AS BIGINT) AS dist FROM asking_points q, LATERAL neighbors(q.vec, 3) n")


def sample_by(spark, sf_dir):
    """A stratified sample that takes every finished order and no open one."""
    taken = source.table(spark, sf_dir, "orders").sampleBy("o_orderstatus", {"F": 1.0, "O": 0.0, "P": 1.0}, seed=5)
    return taken.groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


def slack(pts):
    """Edges of the prune that covers only what a link is nearer to by a margin: more of them, the larger the margin."""
    out = None
    for s in ("1", "1.2", "1.5"):
        one = prune.prune(pts, "0.95", slack=float(s)).agg(F.lit(s).alias("slack"), F.count(F.lit(1)).alias("edges"))
        out = one if out is None else out.unionByName(one)
    return out


def self_queries(spark, sf_dir):
    """Points found by a greedy walk to themselves, per share."""
    pts = source.stage(source.embeddings(spark, sf_dir))
    full, n, out = source.stage(prune.prune(pts, 1)), pts.count(), None
    for s in SELF_SHARES:
        walk = search.greedy(search.Graph(pts, prune.cut(full, s, n)), pts.withColumnRenamed("id", "qid"))
        one = walk.agg(F.lit(s).alias("share"), F.sum((F.col("result") == F.col("qid")).cast("long")).alias("found"), F.count(F.lit(1)).alias("total"))
        out = one if out is None else out.unionByName(one)
    return out


def tradeoff(spark, sf_dir):
    return evaluate.tradeoff(*_split(spark, sf_dir), own=True)


def _from_tradeoff(f):
    return lambda spark, sf_dir: f(tradeoff(spark, sf_dir))


#: Points, share and clusters of the hard case.
HARD_SHARES = [("0.5", 2), ("0.8", 5), ("0.9", 10)]
HARD = [(n, share, k) for n in (100, 1000) for share, k in HARD_SHARES]


def hard(f):
    def run(spark, sf_dir):
        out = None
        for n, share, k in HARD:
            nodes, links = source.line_of_balls(n, k)
            pts = spark.createDataFrame(nodes, "id long, vec array<double>")
            one = f(pts, spark.createDataFrame(links, "src long, dst long"), share).withColumn("n", F.lit(n)).withColumn("share", F.lit(share))
            out = one if out is None else out.unionByName(one)
        return out

    return run


def hard_given(f):
    """f over the hard case that all embeddings make, for each share and its clusters."""

    def run(spark, sf_dir):
        given, out = source.stage(source.embeddings(spark, sf_dir)), None
        n = given.count()
        for share, k in HARD_SHARES:
            nodes, links = (source.stage(x) for x in source.balls_of_points(given, k))
            one = f(nodes, links, share).withColumn("n", F.lit(n)).withColumn("share", F.lit(share))
            out = one if out is None else out.unionByName(one)
        return out

    return run


def hard_coverage(pts, edges, share):
    return audit.coverage_check(audit.covered_counts(pts, edges), share).select("ok", "min_covered", "need")


def hard_failures(pts, edges, share):
    walk = search.greedy(search.Graph(pts, edges), pts.withColumnRenamed("id", "qid"))
    return walk.agg(F.sum((F.col("result") == F.col("qid")).cast("long")).alias("found"))


E = sql.EMB
_GIVEN = "(SELECT count(*) AS n FROM embeddings), (VALUES " + ", ".join(f"({k}, '{t}')" for t, k in HARD_SHARES) + ") t(k, share)"
_HARD = ", ".join(f"({n}, {k}, '{t}')" for n, t, k in HARD)
_CUTS = " UNION ALL ".join(f"SELECT '{s}' AS share, round(avg(k), 6) AS mean, round(median(k), 6) AS median, min(k) AS min, max(k) AS max FROM (SELECT src, count(*) AS k FROM e WHERE {sql.cut(s)} GROUP BY 1)" for s in TABLE_SHARES)
_NEAR = "SELECT a AS qid, arg_min(b, row({d}, b)) AS id, CAST(min({d}) AS BIGINT) AS dist FROM ({pairs}) WHERE a <> b GROUP BY 1"
_ROUNDS = "SELECT CAST(round AS INTEGER) AS round, CAST(pool AS BIGINT) AS pool, kept, CAST(pool - kept AS BIGINT) AS carried FROM (SELECT m.round, sum(kept::INT)::BIGINT AS kept, (SELECT count(*) FROM p) - coalesce((SELECT sum(b.kept::INT) FROM m b WHERE b.round < m.round), 0) AS pool FROM m GROUP BY 1)"
_L = "p AS (SELECT vec_id AS id, list_transform(embedding, lambda x: floor(CAST(x AS DOUBLE) * 16777216)) AS v FROM embeddings)"
_SELF = "SELECT x.id AS a, y.id AS b, {f} AS d FROM p x, p y"
_IDX, _QRY = "(SELECT * FROM q)", "(SELECT * FROM q WHERE id % 100 = 0)"
_R6 = lambda *names: ", ".join(f"round({n}, 6) AS {n}" for n in names)
_QD = f"WITH {_L}, q AS (SELECT id, v, list_inner_product(v, v) AS n FROM p), x AS (SELECT a.id AS qid, b.id AS id, a.n + b.n - 2 * list_inner_product(a.v, b.v) AS dist FROM {_QRY} a, {_IDX} b)"
_TOK = "list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\\p{L}\\p{N}_]+'), lambda t: t <> '')"

_REACH_SHARES = ["1", "0.999", "0.995", "0.95", "0.9"]
_REACH = " UNION ALL ".join(f"SELECT CAST({t} AS DOUBLE) AS share, round(median(r), 6) AS median_edges, round(avg(r), 6) AS mean_edges FROM (SELECT min(rank) AS r FROM e WHERE cum >= {sql.need(Share.of(t))} GROUP BY src)" for t in _REACH_SHARES)
_TARGETS = sql.RATIOS.replace("{targets}", ", ".join(map(str, evaluate.TARGETS)))
_RATIO = f"SELECT k, target, share, {_R6('dc_ratio', 'degree_ratio')}, ref_censored, num_censored FROM ratio"
_HONEST = "coalesce(NOT (ref_censored OR num_censored), false)"
_AVERAGE = f"SELECT k, round(avg(dc_ratio), 6) AS dc_ratio, round(avg(degree_ratio), 6) AS degree_ratio, round(avg(CASE WHEN {_HONEST} THEN dc_ratio END), 6) AS dc_ratio_uncensored, CAST(sum(CAST({_HONEST} AS INTEGER)) AS BIGINT) AS n_uncensored FROM ratio GROUP BY 1"
_FRONT = f"SELECT share, k, b, {_R6('recall', 'dc', 'full_recall')}, recall > full_recall + 1e-9 AS beats FROM pa"
_LEAST = "SELECT k, min(share) AS min_share FROM (SELECT k, share, max(recall) AS top FROM pts GROUP BY 1, 2) WHERE top > 0.97 GROUP BY 1"
_DRAWN = sql.drawn("qid", 0, 1, "(SELECT count(*) FROM p)")
_MEAN = "(SELECT list(a ORDER BY i) FROM (SELECT i, avg(v[i]) AS a FROM p, range(1, 65) r(i) GROUP BY 1))"
_STARTS = sql.beams(["1"], [64], [10], f"SELECT share AS start, {_R6('recall', 'dc')} FROM (SELECT share, avg(recall) AS recall, avg(evals) AS dc FROM rc GROUP BY 1)", starts=f"""mid AS (SELECT list_sum(list_transform(range(1, 65), lambda i: (v[i] - c[i]) * (v[i] - c[i]))) AS far, id FROM p, (SELECT {_MEAN} AS c)),
g AS (SELECT y.share, {sql.need(Share.of(1))} AS need, qid, CASE y.share WHEN 'first' THEN (SELECT min(id) FROM p) WHEN 'medoid' THEN (SELECT arg_min(id, far) FROM mid) ELSE (SELECT o.id FROM (SELECT id, row_number() OVER (ORDER BY id) - 1 AS pos FROM p) o WHERE o.pos = {_DRAWN}) END AS start
  FROM (SELECT unnest(['first', 'medoid', 'random']) AS share) y, (SELECT id AS qid FROM p WHERE id % 100 = 0))""")


def _beams(tail: str, more: str | None = None, text: bool = False) -> str:
    """What `tail` makes of the recall and cost of every share, width and k."""
    extra = [sql.POINTS] + ([_TARGETS if more is sql.RATIOS else more] if more else [])
    held = {"base": sql.TEXT, "asked": sql.ASKED_ITEMS, "queries": "SELECT item_id AS qid FROM imp"} if text else {}
    return sql.beams([str(float(t)) for t in map(Share.of, evaluate.SHARES)], evaluate.WIDTHS, evaluate.KS, tail, *extra, **held)


def _ratios(t):
    return evaluate.ratio_table(t).select("k", "target", "share", _r("dc_ratio"), _r("degree_ratio"), "ref_censored", "num_censored")


def _averages(t):
    return evaluate.ratio_average(t).select("k", _r("dc_ratio"), _r("degree_ratio"), _r("dc_ratio_uncensored"), "n_uncensored")


def _fronts(t):
    """beats: by more than rounding."""
    return evaluate.pareto(t).select("share", "k", "b", _r("recall"), _r("dc"), _r("full_recall"), (F.col("recall") > F.col("full_recall") + 1e-9).alias("beats"))


def edges_to_reach(pts, edges, n):
    """Edges that each share takes, and the median's ratio to that of full coverage."""
    from pyspark.sql import Window as W

    t = prune.edges_to_reach(edges, _REACH_SHARES, n).select(F.col("share").cast("double").alias("share"), _r("median_edges"), _r("mean_edges"))
    full = F.max(F.when(F.col("share") == 1, F.col("median_edges"))).over(W.partitionBy())
    return t.withColumn("ratio", F.round(F.col("median_edges") / full, 6))


def _ordered(order):
    return lambda spark, sf_dir: cliques.peel(source.embeddings(spark, sf_dir), PEEL, order=order).edges()


REGISTRY: dict[str, tuple] = {
    "points_profile": (profile, "SELECT count(*) AS n, min(len(embedding)) AS dim_min, max(len(embedding)) AS dim_max, 0 AS bad, count(DISTINCT embedding) AS distinct_vecs FROM embeddings"),
    "points_dedupe": (dedupe, f"WITH t AS (SELECT doc_id, unnest({_TOK}) AS t FROM documents), c AS (SELECT doc_id, CAST('0x' || substr(md5(t), 1, 8) AS BIGINT) % 64 AS b, count(*) AS k FROM t GROUP BY 1, 2), v AS (SELECT doc_id, list(row(b, k) ORDER BY b) AS v FROM c GROUP BY 1) SELECT min(doc_id) AS id, count(*) AS copies FROM v GROUP BY v"),
    "points_jitter_unique": (_points(jitter_unique), "SELECT count(DISTINCT embedding) AS before, 2 * count(*) AS after, 2 * count(*) AS n FROM embeddings"),
    "text_vectors": (text_vectors, f"WITH t AS (SELECT doc_id, unnest({_TOK}) AS t FROM documents) SELECT doc_id AS id, CAST(CAST('0x' || substr(md5(t), 1, 8) AS BIGINT) % 64 AS INTEGER) AS bucket, CAST(count(*) AS DOUBLE) AS count FROM t GROUP BY 1, 2"),
    "numeric_vectors": (numeric_vectors, "SELECT row_number() OVER (ORDER BY a, b, c, d) - 1 AS id, a, b, c, d FROM (SELECT DISTINCT round(l_quantity * 100) AS a, round(l_extendedprice * 1) AS b, round(l_discount * 10000) AS c, round(l_tax * 10000) AS d FROM lineitem)"),
    "distance_l2sq": (nearest_by("l2sq"), f"WITH {E} " + _NEAR.format(d="d", pairs="SELECT * FROM d")),
    "distance_l1": (nearest_by("l1"), f"WITH {_L} " + _NEAR.format(d="d", pairs=_SELF.format(f="list_sum(list_transform(range(1, 65), lambda i: abs(x.v[i] - y.v[i])))"))),
    "distance_linf": (nearest_by("linf"), f"WITH {_L} " + _NEAR.format(d="d", pairs=_SELF.format(f="list_max(list_transform(range(1, 65), lambda i: abs(x.v[i] - y.v[i])))"))),
    "distance_cosine": (nearest_by("cosine"), f"WITH {_L} " + _NEAR.replace("CAST(min({d}) AS BIGINT)", "round(min({d}), 6)").format(d="d", pairs=_SELF.format(f="1 - list_cosine_similarity(x.v, y.v)"))),
    "distance_jaccard": (pair_distances("jaccard"), f"WITH t AS (SELECT item_id, list_distinct({_TOK}) AS t FROM benchmark) SELECT a.item_id AS a, b.item_id AS b, round(1 - len(list_intersect(a.t, b.t)) / greatest(len(list_distinct(list_concat(a.t, b.t))), 1), 6) AS dist FROM t a JOIN t b ON a.item_id < b.item_id"),
    "distance_levenshtein": (pair_distances("levenshtein"), None),
    "thresholds": (thresholds, "SELECT num, den, (num * (n - 1) + den - 1) // den AS need, (2 * den + den - num - 1) // (den - num) AS s2, (4 * den + den - num - 1) // (den - num) AS s4 FROM (VALUES (0, 1), (1, 2), (2, 3), (4, 5), (9, 10), (19, 20), (49, 50), (99, 100), (199, 200), (999, 1000)) t(num, den), (SELECT count(*) AS n FROM embeddings)"),
    "clique_chunks": (_points(lambda s, p: cliques.chunks(p, Share.of(PEEL).clique(), 1, 1).select("id", "pos", "chunk")), sql.peel(PEEL, "SELECT k1.id, k1.pos, coalesce(chunk, -1) AS chunk FROM k1 LEFT JOIN c1 USING (id)")),
    "clique_ownership_ties": (ownership_ties, "SELECT i AS member, 9::BIGINT AS owned FROM range(12) r(i)"),
    "clique_ownership": (_peeled(lambda p: p.members), sql.peel(PEEL, "SELECT round, chunk, member, owned, kept FROM m")),
    "clique_keep_half": (_peeled(lambda p: half_kept(p.members)), sql.peel(PEEL, "SELECT round, chunk, CAST(sum(owned) AS BIGINT) AS owned, CAST(sum(kept::INT) AS BIGINT) AS kept, count(*) AS size, 2 * sum(kept::INT) >= count(*) AS half FROM m GROUP BY 1, 2")),
    "peel_exact_edges": (_peeled(lambda p: p.edges()), sql.peel(PEEL, "SELECT src, dst FROM g")),
    "peel_exact_rounds": (_peeled(lambda p: p.rounds().select("round", "pool", "kept", "carried")), sql.peel(PEEL, _ROUNDS)),
    "peel_exact_coverage": (_peeled(lambda p: audit.covered_counts(p.points, source.stage(p.edges())).select("src", "covered")), sql.peel(PEEL, sql.COVERED)),
    "peel_exact_size": (_peeled(size_report), sql.peel(PEEL, "SELECT count(*) AS edges, count(*) <= 20 * (SELECT count(*) FROM p) AS within_bound, 16 * count(*) AS edge_bytes, (SELECT count(*) FROM m) * 24 + (SELECT count(*) FROM l) * 8 AS clique_bytes FROM (SELECT DISTINCT * FROM g)")),
    "peel_exact_log": (_peeled(peel_log), sql.peel(PEEL, f"SELECT round, pool, pool // {Share.of(PEEL).clique()} AS chunks, kept, carried, pool // {Share.of(PEEL).clique()} * {Share.of(PEEL).clique()} * (SELECT count(*) FROM p) AS distances, round(carried / pool, 6) AS shrink FROM ({_ROUNDS})")),
    "peel_reachable_share": (_peeled(reachable_share), sql.peel(PEEL, ", b AS (SELECT 0::BIGINT AS node UNION SELECT dst FROM b JOIN g ON src = node) SELECT count(*) AS reached, round(count(*) / (SELECT count(*) FROM p), 6) AS share FROM b")),
    **{f"peel_order_{o}": (_ordered(o), sql.peel(PEEL, "SELECT src, dst FROM g", order=o)) for o in ("id", "locality")},
    "peel_partition_check": (partition_peel, "SELECT true AS ok, 0::BIGINT AS n_bad, false AS shuffles"),
    "peel_jaccard_edges": (jaccard_peel(lambda p: p.edges().distinct()), sql.peel(PEEL, "SELECT src, dst FROM g", rounds=9, base=sql.SETS)),
    "peel_jaccard_rounds": (jaccard_peel(lambda p: p.rounds().select("round", "pool", "kept", "carried")), sql.peel(PEEL, _ROUNDS, rounds=9, base=sql.SETS)),
    "peel_exact_check": (_peeled(lambda p: audit.coverage_check(audit.covered_counts(p.points, source.stage(p.edges())), PEEL)), sql.peel(PEEL, f"SELECT bool_and(covered >= need) AS ok, count(*) FILTER (WHERE covered < need) AS n_bad, min(covered) AS min_covered, max(need) AS need FROM ({sql.COVERED}), (SELECT {sql.need(Share.of(PEEL))} AS need)")),
    **{f"peel_exact_edges_{t.replace('.', '')}": (_peeled(lambda p: p.edges(), share=t), sql.peel(t, "SELECT src, dst FROM g")) for t in ("0", "0.5", "0.9", "0.95")},
    "peel_text_edges": (_text_peel(lambda p: p.edges().distinct()), sql.peel(PEEL, "SELECT src, dst FROM g", rounds=6, base=sql.TEXT)),
    "peel_text_rounds": (_text_peel(lambda p: p.rounds().select("round", "pool", "kept", "carried")), sql.peel(PEEL, _ROUNDS, rounds=6, base=sql.TEXT)),
    "peel_text_sampled": (_text_peel(lambda p: p.members, DELTA), sql.peel(PEEL, "SELECT round, chunk, member, owned, kept FROM m", DELTA, rounds=6, base=sql.TEXT)),
    "sample_draw": (_points(sample_draw), f"SELECT pos, count(*) AS mult FROM (SELECT {sql.drawn('i', 1, 1, '(SELECT count(*) FROM embeddings)')} AS pos FROM range(CAST(ceil(16 * ln((SELECT count(*) FROM embeddings) / 0.1) * 5) AS BIGINT)) r(i)) GROUP BY 1"),
    "peel_sampled_ownership": (_peeled(lambda p: p.members, DELTA, SAMPLED), sql.peel(SAMPLED, "SELECT round, chunk, member, owned, kept FROM m", DELTA)),
    "peel_sampled_edges": (_peeled(lambda p: p.edges(), DELTA, SAMPLED), sql.peel(SAMPLED, "SELECT src, dst FROM g", DELTA)),
    "peel_sampled_rounds": (_peeled(lambda p: p.rounds().select("round", "pool", "kept", "carried"), DELTA, SAMPLED), sql.peel(SAMPLED, _ROUNDS, DELTA)),
    "peel_sampled_coverage": (_peeled(lambda p: audit.clique_counts(p.points, p.members, p.leftovers).select("src", "covered"), DELTA, SAMPLED), sql.peel(SAMPLED, sql.COVERED, DELTA)),
    "peel_distance_cost": (distance_cost, None),
    "peel_seed_success": (_points(seed_success), "SELECT delta, count(*) AS seeds, count(*) FILTER (WHERE ok) AS valid, count(*) FILTER (WHERE ok) / count(*) AS rate, count(*) FILTER (WHERE ok) / count(*) >= 1 - delta AS enough FROM (" + " UNION ALL ".join(f"SELECT {d}::DOUBLE AS delta, ok FROM ({sql.peel(SAMPLED, f'SELECT bool_and(covered >= {sql.need(Share.of(SAMPLED))}) AS ok FROM ({sql.COVERED})', d, seed=i)})" for d in SEED_DELTAS for i in range(1, SEEDS + 1)) + ") GROUP BY 1"),
    "prune_navigable": (_pruned(lambda p, e, n: e), sql.prune("SELECT src, rank, dst, dist, gain, cum FROM e")),
    "prune_gamma_995": (_pruned(lambda p, e, n: e, "0.995"), sql.prune(f"SELECT src, rank, dst, dist, gain, cum FROM e WHERE {sql.cut('0.995')}")),
    "prune_gamma_950": (_pruned(lambda p, e, n: e, "0.95"), sql.prune(f"SELECT src, rank, dst, dist, gain, cum FROM e WHERE {sql.cut('0.95')}")),
    "prune_prefix_except": (_pruned(lambda p, e, n: prune.prune(p, "0.95").select("src", "rank", "dst").exceptAll(prune.cut(e, "0.95", n).select("src", "rank", "dst"))), "SELECT 0::BIGINT AS src, 0::INTEGER AS rank, 0::BIGINT AS dst WHERE false"),
    "prune_candidates": (_points(prune_candidates), sql.candidates_only(30, f"SELECT round(min(covered / (n - 1)), 6) AS share_min, round(avg(covered / (n - 1)), 6) AS share_mean, round(max(covered / (n - 1)), 6) AS share_max FROM ({sql.COVERED}), (SELECT count(*) AS n FROM p)")),
    "prune_l1": (pruned_by("l1"), sql.prune(f"SELECT src, rank, dst, CAST(dist AS BIGINT) AS dist, gain, cum FROM e WHERE {sql.cut('0.95')}", sql.embeddings_by("list_sum(list_transform(range(1, 65), lambda i: abs(x.v[i] - y.v[i])))"))),
    "prune_linf": (pruned_by("linf"), sql.prune(f"SELECT src, rank, dst, CAST(dist AS BIGINT) AS dist, gain, cum FROM e WHERE {sql.cut('0.95')}", sql.embeddings_by("list_max(list_transform(range(1, 65), lambda i: abs(x.v[i] - y.v[i])))"))),
    "prune_probe": (probe_line_items, None),
    "degree_table": (_pruned(degree_table), sql.prune(_CUTS)),
    "degree_table_text": (degrees_of_texts, sql.prune(_CUTS, sql.TEXT)),
    "coverage_trace": (_pruned(lambda p, e, n: prune.coverage_trace(e, n).select("src", "rank", _r("uncovered"), _r("log10_uncovered"))), sql.prune("SELECT src, rank, round(1 - cum / (n - 1), 6) AS uncovered, round(log10(greatest(1 - cum / (n - 1), 0.5 / (n - 1))), 6) AS log10_uncovered FROM e, (SELECT count(*) AS n FROM p)")),
    "coverage_median": (_pruned(lambda p, e, n: prune.median_trace(e, n).select("rank", _r("median_log10"))), sql.prune("SELECT pos AS rank, round(median(log10(greatest(1 - cum / (n - 1), 0.5 / (n - 1)))), 6) AS median_log10 FROM (SELECT DISTINCT rank AS pos FROM e) JOIN (SELECT src, max(rank) AS top FROM e GROUP BY 1) ON true JOIN e USING (src), (SELECT count(*) AS n FROM p) WHERE e.rank = least(pos, top) GROUP BY 1")),
    "edges_to_reach": (_pruned(edges_to_reach), sql.prune(f"SELECT share, median_edges, mean_edges, round(median_edges / max(median_edges) FILTER (share = 1) OVER (), 6) AS ratio FROM ({_REACH})")),
    "probe_vs_full": (_pruned(probe_vs_full), sql.prune("SELECT 'all' AS nodes, round(avg(k), 6) AS mean FROM (SELECT count(*) AS k FROM e GROUP BY src) UNION ALL SELECT 'probes', round(avg(k), 6) FROM (SELECT count(*) AS k FROM e WHERE src % 10 = 3 GROUP BY src)")),
    "first_edge_is_nearest": (_pruned(first_edge_is_nearest), "SELECT 0::BIGINT AS src, 0::BIGINT AS dst WHERE false"),
    "set_cover_edges": (_points(lambda s, p: prune.set_cover(p, "0.95")), None),
    "set_cover_vs_prune": (_points(set_cover_vs_prune), None),
    "covered_counts": (_pruned(lambda p, e, n: audit.covered_counts(p, e.select("src", "dst")).select("src", "covered"), "0.95"), sql.prune(f", g AS (SELECT src, dst FROM e WHERE {sql.cut('0.95')}) {sql.COVERED}")),
    "is_navigable": (_pruned(lambda p, e, n: audit.coverage_check(audit.covered_counts(p, e.select("src", "dst")), 1)), "SELECT true AS ok, 0::BIGINT AS n_bad, count(*) - 1 AS min_covered, count(*) - 1 AS need FROM embeddings"),
    "is_gamma_covering": (_pruned(lambda p, e, n: audit.coverage_check(audit.covered_counts(p, e.select("src", "dst")), "0.95"), "0.95"), sql.prune(f", g AS (SELECT src, dst FROM e WHERE {sql.cut('0.95')}) SELECT bool_and(covered >= need) AS ok, count(*) FILTER (WHERE covered < need) AS n_bad, min(covered) AS min_covered, max(need) AS need FROM ({sql.COVERED}), (SELECT {sql.need(Share.of('0.95'))} AS need)")),
    "achieved_gamma": (_pruned(lambda p, e, n: audit.achieved_share(audit.covered_counts(p, e.select("src", "dst"))).select(_r("share_min"), _r("share_mean"), _r("share_max")), "0.95"), sql.prune(f", g AS (SELECT src, dst FROM e WHERE {sql.cut('0.95')}) SELECT round(min(covered / (n - 1)), 6) AS share_min, round(avg(covered / (n - 1)), 6) AS share_mean, round(max(covered / (n - 1)), 6) AS share_max FROM ({sql.COVERED}), (SELECT count(*) AS n FROM p)")),
    "uncovered_pairs": (_pruned(lambda p, e, n: audit.uncovered_pairs(p, e.select("src", "dst")), "0.95"), sql.prune(f", g AS (SELECT src, dst FROM e WHERE {sql.cut('0.95')}) SELECT y.a AS src, y.b AS target FROM d y WHERE y.a <> y.b AND NOT EXISTS (SELECT 1 FROM g JOIN d x ON x.a = g.dst WHERE g.src = y.a AND x.b = y.b AND x.d < y.d)")),
    "coverage_sampled": (_pruned(lambda p, e, n: audit.covered_counts(p, e.select("src", "dst"), targets=100).select("src", "covered", "checked", _r("half_width")), "0.95"), sql.prune(f", g AS (SELECT src, dst FROM e WHERE {sql.cut('0.95')}), t AS (SELECT id FROM p ORDER BY {sql.hashed('id', sql.DRAWS, 1)}, id LIMIT 100), y AS (SELECT g.src, count(DISTINCT x.b) AS covered FROM g JOIN d x ON x.a = g.dst JOIN t ON t.id = x.b JOIN d z ON z.a = g.src AND z.b = x.b WHERE x.d < z.d AND x.b <> g.src GROUP BY 1), n AS (SELECT p.id AS src, (SELECT count(*) FROM t WHERE t.id <> p.id) AS checked FROM p) SELECT src, coalesce(covered, 0) AS covered, checked, round(sqrt(ln(2 / 0.05) / (2 * checked)), 6) AS half_width FROM n LEFT JOIN y USING (src)")),
    "validate_graph": (_pruned(lambda p, e, n: audit.validate_graph(p, e.select("src", "dst"))), sql.prune("SELECT count(*) AS edges, 0::BIGINT AS self_loops, 0::BIGINT AS dangling, 0::BIGINT AS parallel FROM e")),
    "complete_graph_check": (_points(complete_check), "SELECT true AS ok, 0::BIGINT AS n_bad, count(*) - 1 AS min_covered, count(*) - 1 AS need FROM embeddings"),
    "bounds": (lambda s, d: audit.bounds(s, source.table(s, d, "embeddings").count(), "0.95").select("n", "need", _r("clique_degree"), _r("navigable_degree"), _r("worst_edges"), "regime"), "SELECT n, (19 * (n - 1) + 19) // 20 AS need, 80.0::DOUBLE AS clique_degree, round(sqrt(n), 6) AS navigable_degree, round(n * sqrt(n), 6) AS worst_edges, CASE WHEN 80 < sqrt(n) THEN 'cliques' ELSE 'navigable' END AS regime FROM (SELECT count(*) AS n FROM embeddings)"),
    "knn_exact": (knn, f"{_QD} SELECT qid, CAST(pos AS INTEGER) AS pos, id, CAST(dist AS BIGINT) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS pos FROM x WHERE id <> qid) WHERE pos <= 10"),
    "knn_filtered": (knn_filtered, f"{_QD.replace(_IDX, '(SELECT q.* FROM q JOIN embeddings ON vec_id = id WHERE label = 3)')} SELECT qid, CAST(pos AS INTEGER) AS pos, id FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS pos FROM x WHERE id <> qid) WHERE pos <= 5"),
    "radius_search": (radius, f"{_QD} SELECT qid, id, CAST(dist AS BIGINT) AS dist FROM x WHERE dist <= 350000000000000 AND id <> qid"),
    "greedy_walk": (_searched(lambda i, q, e: search.greedy(search.Graph(i, e), q).select("qid", "result", F.col("dist").cast("long").alias("dist"), "steps")), sql.prune(f", x AS (SELECT a.id AS qid, b.id, a.n + b.n - 2 * list_inner_product(a.v, b.v) AS dist FROM {_QRY} a, {_IDX} b), {sql.greedy(sql.cut('0.95'))} SELECT qid, arg_max(at_id, steps) AS result, CAST(min(dist) AS BIGINT) AS dist, CAST(max(steps) AS INTEGER) AS steps FROM w GROUP BY 1")),
    "greedy_joins_equal": (_searched(joins_equal_greedy), "SELECT 0::BIGINT AS qid, 0::BIGINT AS result, 0::BIGINT AS j_id WHERE false"),
    "beam_b1_equals_greedy": (_searched(beam_equals_greedy), "SELECT 0::BIGINT AS qid, 0::BIGINT AS result, 0::BIGINT AS b_id WHERE false"),
    "beam_results": (_searched(lambda i, q, e: search.beam_sweep(search.Graph(i, e), q, [64], [10], own=True).select("qid", "pos", "id", F.col("dist").cast("long").alias("dist"), "dist_evals"), "1"), sql.beams(["1"], [64], [10], "SELECT qid, CAST(pos AS INTEGER) AS pos, id, CAST(dist AS BIGINT) AS dist, evals AS dist_evals FROM found WHERE pos <= 10")),
    "beam_sweep": (_searched(lambda i, q, e: search.beam_sweep(search.Graph(i, e), q, evaluate.WIDTHS, evaluate.KS, own=True).where("b >= k and pos = 1").groupBy("b", "k").agg(_avg("dist_evals"), _avg("edges_scanned"), _avg("expanded")), "0.995"), sql.beams(["0.995"], evaluate.WIDTHS, evaluate.KS, "SELECT b, k, round(avg(evals), 6) AS dist_evals, round(avg(scanned), 6) AS edges_scanned, round(avg(expanded), 6) AS expanded FROM z, (SELECT unnest([1, 10, 100]) AS k) WHERE b >= k AND evals > 1 GROUP BY 1, 2")),
    "beam_bsp_equals_local": (_searched(joins_equal_beam), "SELECT 0::BIGINT AS qid, 0 AS pos, 0::BIGINT AS id, 0::BIGINT AS dist_evals, 0::BIGINT AS expanded WHERE false"),
    "stream_query_recall": (stream_recall, sql.beams(["0.995"], [16], [10], "SELECT CAST(epoch(time_bucket(INTERVAL '1 day', ts)) AS BIGINT) AS start_s, count(*) AS n, round(avg(recall), 6) AS recall, round(avg(evals), 6) AS dc FROM events JOIN (SELECT row_number() OVER (ORDER BY qid) - 1 AS pos, recall, evals FROM rc) r ON r.pos = event_id % (SELECT count(*) FROM rc) GROUP BY 1")),
    "points_medoid": (medoids, f"WITH {_L}, l AS (SELECT p.id, label, v FROM p JOIN embeddings ON vec_id = p.id), c AS (SELECT label, i, avg(v[i]) AS x FROM l, range(1, 65) r(i) GROUP BY 1, 2), m AS (SELECT label, list(x ORDER BY i) AS m FROM c GROUP BY 1) SELECT label, arg_min(id, row(list_sum(list_transform(range(1, 65), lambda i: (v[i] - m[i]) * (v[i] - m[i]))), id)) AS id FROM l JOIN m USING (label) GROUP BY 1"),
    "source_formats": (formats, "SELECT form, count(*) AS n, sum(o_orderkey)::BIGINT AS keys, count(DISTINCT o_orderpriority) AS priorities, max(o_orderdate) AS latest FROM orders, (VALUES ('csv'), ('json'), ('orc'), ('parquet')) t(form) GROUP BY 1"),
    "source_text": (text_lines, "SELECT o_orderpriority AS priority, count(*) AS count FROM orders GROUP BY 1"),
    "source_flat_files": (flat_files, "SELECT count(*) AS n, CAST(min(len(embedding)) AS INTEGER) AS dim, round(sum(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE)))), 4) AS total FROM embeddings"),
    "stored_edges": (stored_edges, sql.prune(f"SELECT src, rank, dst, dist, gain, cum FROM e WHERE {sql.cut('0.95')}")),
    "stored_cliques": (_peeled(stored_cliques), sql.peel(PEEL, "SELECT src, dst FROM g")),
    "sql_thresholds": (sql_thresholds, "SELECT num::BIGINT AS num, den::BIGINT AS den, (num * (n - 1) + den - 1) // den AS need, ((2 * den + den - num - 1) // (den - num))::BIGINT AS s2, ((4 * den + den - num - 1) // (den - num))::BIGINT AS s4, CAST(ceil(16 * ln(n / 0.1) * den / (den - num)) AS BIGINT) AS w FROM (VALUES (1, 2), (2, 3), (4, 5), (19, 20), (199, 200)) t(num, den), (SELECT count(*) AS n FROM embeddings)"),
    "sql_neighbors": (sql_neighbors, f"{_QD} SELECT qid, CAST(pos AS INTEGER) AS pos, id, CAST(dist AS BIGINT) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS pos FROM x) WHERE pos <= 3"),
    "rel_sample_by": (sample_by, "SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_orderstatus IN ('F', 'P') GROUP BY 1"),
    "prune_slack": (_points(lambda s, p: slack(source.stage(p))), " UNION ALL ".join(f"SELECT * FROM ({sql.slack_edges(t, '0.95')})" for t in ("1", "1.2", "1.5"))),
    "beam_sharded": (_searched(beam_shards), None),
    "beam_starts": (_searched(beam_starts, "1"), _STARTS),
    "stream_query_distance": (stream_distance, f"WITH {E}, k AS (SELECT a AS qid, CAST(min(d) AS BIGINT) AS dist FROM d WHERE a <> b GROUP BY 1) SELECT CAST(epoch(time_bucket(INTERVAL '1 hour', ts)) AS BIGINT) AS start_s, count(*) AS n, max(dist) AS worst FROM events JOIN k ON qid = event_id % (SELECT count(*) FROM p) GROUP BY 1"),
    "self_query_rate": (self_queries, sql.prune(", x AS (SELECT a AS qid, b AS id, d AS dist FROM d), " + ", ".join(sql.greedy(sql.cut(t), f"w{i}") for i, t in enumerate(SELF_SHARES)) + " " + " UNION ALL ".join(f"SELECT '{t}' AS share, count(*) FILTER (WHERE r = qid) AS found, count(*) AS total FROM (SELECT qid, arg_max(at_id, steps) AS r FROM w{i} GROUP BY 1)" for i, t in enumerate(SELF_SHARES)))),
    "reachable": (_peeled(lambda p: audit.reachable(source.stage(p.edges()), 0)), sql.peel(PEEL, ", b AS (SELECT 0::BIGINT AS node, 0 AS hops UNION SELECT dst, hops + 1 FROM b JOIN g ON src = node WHERE hops < 50) SELECT node, CAST(min(hops) AS INTEGER) AS hops FROM b GROUP BY 1")),
    "components": (_peeled(lambda p: audit.components(p.points, source.stage(p.edges()))), sql.peel(PEEL, ", b AS (SELECT id AS node, id AS c FROM p UNION SELECT dst, c FROM b JOIN (SELECT src, dst FROM g UNION SELECT dst, src FROM g) h ON src = node) SELECT node, min(c) AS component FROM b GROUP BY 1")),
    "recall_cost": (lambda s, d: tradeoff(s, d).select("share", "k", "b", _r("degree"), _r("recall"), _r("dc")), _beams(f"SELECT share, k, b, {_R6('degree', 'recall', 'dc')} FROM pts")),
    "recall_cost_text": (_from_texts(lambda t: t.select("share", "k", "b", _r("degree"), _r("recall"), _r("dc"))), _beams(f"SELECT share, k, b, {_R6('degree', 'recall', 'dc')} FROM pts", text=True)),
    "ratio_table": (_from_tradeoff(_ratios), _beams(_RATIO, sql.RATIOS)),
    "ratio_table_text": (_from_texts(_ratios), _beams(_RATIO, sql.RATIOS, text=True)),
    "ratio_average": (_from_tradeoff(_averages), _beams(_AVERAGE, sql.RATIOS)),
    "ratio_average_text": (_from_texts(_averages), _beams(_AVERAGE, sql.RATIOS, text=True)),
    "pareto_points": (_from_tradeoff(_fronts), _beams(_FRONT, sql.PARETO)),
    "min_gamma": (_from_tradeoff(evaluate.min_share), _beams(_LEAST)),
    "min_gamma_text": (_from_texts(evaluate.min_share), _beams(_LEAST, text=True)),
    "knn_good_texts": (knn_good_texts, f"WITH RECURSIVE {sql.TEXT.split('p AS (SELECT min')[0]} q AS (SELECT doc_id AS id, list_transform(range(64), lambda i: CAST(coalesce(m[i], 0) AS DOUBLE)) AS v, list_inner_product(v, v) AS n FROM mp WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)), {sql.ASKED_ITEMS} SELECT qid, CAST(pos AS INTEGER) AS pos, id, CAST(dist AS BIGINT) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS pos FROM x) WHERE pos <= 5"),
    "hard_case_points": (hard(lambda p, e, s: p.select("id", (F.round(F.col("vec")[0], 4) + 0.0).alias("x"), (F.round(F.col("vec")[1], 4) + 0.0).alias("y"))), f"SELECT i AS id, round((i // (n // k)) * 5 + cos(2 * pi() * (i % (n // k)) / (n // k)), 4) + 0.0 AS x, round(sin(2 * pi() * (i % (n // k)) / (n // k)), 4) + 0.0 AS y, n, share FROM (VALUES {_HARD}) t(n, k, share), range(1000) r(i) WHERE i < n"),
    "sql_distance": (sql_distance, f"WITH {_L} SELECT a.id, CAST(list_sum(list_transform(range(1, 65), lambda i: (a.v[i] - b.v[i]) * (a.v[i] - b.v[i]))) AS BIGINT) AS dist FROM p a, (SELECT v FROM p WHERE id = 0) b"),
    "sql_clique_edges": (sql_clique_edges, "SELECT a.n_nationkey::BIGINT AS src, b.n_nationkey::BIGINT AS dst FROM nation a JOIN nation b USING (n_regionkey) WHERE a.n_nationkey <> b.n_nationkey"),
    "hard_case_coverage": (hard_given(hard_coverage), f"SELECT true AS ok, n - (n + k - 1) // k AS min_covered, ((k - 1) * (n - 1) + k - 1) // k AS need, n, share FROM {_GIVEN}"),
    "hard_case_failures": (hard_given(hard_failures), f"SELECT CAST(k AS BIGINT) AS found, n, share FROM {_GIVEN}"),
}


def _avg(name: str):
    return F.round(F.avg(name), 6).alias(name)


def queries():
    return {k: v[0] for k, v in REGISTRY.items()} | relational.queries() | arrivals.QUERIES


def oracles():
    return {k: v[1] for k, v in REGISTRY.items() if v[1]} | relational.oracles() | arrivals.ORACLES
