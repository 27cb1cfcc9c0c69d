"""Queries of whole detectors, measures and experiment tables, with their SQL, on the constructed stream (and the natural one)."""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import detect, lsh, metrics, model, similarity
from ..operators.detect import Config
from ..sources.scratch import Scratch
from ..sources.tables import table
from . import streams
from .novelty import signature_sql

QUERIES: dict = {}
SQL: dict[str, str] = {}
THRESHOLD = 0.8
#: The search of the hashed detectors: as many tables as find a neighbour at the threshold's cosine with chance 0.9.
HASHED = Config(k=4, tables=lsh.tables_needed(4, 1 - THRESHOLD, 0.1))


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return keep


# ---- SQL of a detector -------------------------------------------------------------------------------------------------------


def scores_sql(cfg: Config, source: str = "docs", out: str = "scored") -> str:
    """CTEs from ``source(doc_id, batch_id, truth_id, terms)`` to ``out(doc_id, distance, match_id)``."""
    p = out  # names of one detector's tables begin with its own
    damp = {"log": "(log10(tf) + 1)", "raw": "tf", "collection": "cf"}[cfg.tf_mode]
    model_sql = {
        "static": f"""{p}_m AS (SELECT b.batch_id, term, idf, cf FROM (SELECT term, log10((SELECT CAST(count(*) AS DOUBLE) FROM {source} WHERE batch_id = 0) / count(*)) AS idf, sum(tf) AS cf FROM {p}_tf WHERE batch_id = 0 GROUP BY term), (SELECT DISTINCT batch_id FROM {source}) b)""",
        "merged": f"""{p}_m AS (SELECT batch_id, term, log10(n / sum(coalesce(d, 0)) OVER w) AS idf, sum(coalesce(c, 0)) OVER w AS cf FROM {p}_g LEFT JOIN {p}_o USING (batch_id, term) WINDOW w AS (PARTITION BY term ORDER BY batch_id))""",
        "additive": f"""{p}_m AS (SELECT batch_id, term, sum(coalesce(i, 0)) OVER w AS idf, sum(coalesce(c, 0)) OVER w AS cf FROM {p}_g LEFT JOIN {p}_o USING (batch_id, term) WINDOW w AS (PARTITION BY term ORDER BY batch_id))""",
    }[cfg.scheme]
    past = f"WHERE t.batch_id <= m.batch_id AND m.batch_id > 0" if cfg.history == "all_seen" else "WHERE t.batch_id = 0 AND m.batch_id > 0"
    ctes = f"""{p}_tk AS (SELECT doc_id, batch_id, unnest(terms) AS term FROM {source}), {p}_tf AS (SELECT doc_id, batch_id, term, count(*) AS tf FROM {p}_tk GROUP BY ALL),
{p}_z AS (SELECT batch_id, nb, CAST(sum(nb) OVER (ORDER BY batch_id) AS DOUBLE) AS n FROM (SELECT batch_id, count(*) AS nb FROM {source} GROUP BY 1)),
{p}_o AS (SELECT batch_id, term, count(*) AS d, sum(tf) AS c, log10(any_value(nb) / CAST(count(*) AS DOUBLE)) AS i FROM {p}_tf JOIN {p}_z USING (batch_id) GROUP BY batch_id, term),
{p}_g AS (SELECT f.term, z.batch_id, n FROM (SELECT term, min(batch_id) AS b FROM {p}_tf GROUP BY term) f JOIN {p}_z z ON z.batch_id >= f.b), {model_sql},
{p}_q AS (SELECT batch_id, doc_id, term, {damp} * idf AS x FROM {p}_tf JOIN {p}_m USING (batch_id, term) WHERE batch_id > 0),
{p}_h AS (SELECT m.batch_id, doc_id, term, {damp} * idf AS x FROM {p}_tf t JOIN {p}_m m USING (term) {past}),
{p}_ql AS (SELECT batch_id, doc_id, sum(x * x) AS s FROM {p}_q GROUP BY ALL), {p}_hl AS (SELECT batch_id, doc_id, sum(x * x) AS s FROM {p}_h GROUP BY ALL)"""
    query_length = f"{p}_ql"
    if cfg.oov == "norm" and cfg.scheme == "static":
        ctes += f""", {p}_u AS (SELECT batch_id, doc_id, sum(({damp.replace('cf', 'tf')} * log10((SELECT CAST(count(*) AS DOUBLE) FROM {source} WHERE batch_id = 0))) ** 2) AS more FROM {p}_tf WHERE batch_id > 0 AND term NOT IN (SELECT term FROM {p}_tf WHERE batch_id = 0) GROUP BY ALL),
{p}_qn AS (SELECT batch_id, doc_id, s + coalesce(more, 0) AS s FROM {p}_ql LEFT JOIN {p}_u USING (batch_id, doc_id))"""
        query_length = f"{p}_qn"
    if cfg.search == "lsh":
        bands = ""
        for side in "qh":
            bands += f""", {signature_sql(f'{p}_{side}', f'{p}_{side}s', cfg.k, cfg.tables, 'batch_id, doc_id')}, {p}_{side}b AS (SELECT batch_id, doc_id, unnest(bands) AS bucket, generate_subscripts(bands, 1) AS t FROM {p}_{side}s)"""
        held = f"(SELECT * FROM {p}_hb QUALIFY row_number() OVER (PARTITION BY batch_id, t, bucket ORDER BY doc_id DESC) <= {cfg.bucket_cap})" if cfg.bucket_cap else f"{p}_hb"
        ctes += bands + f""", {p}_t AS (SELECT a.batch_id, a.doc_id AS q, b.doc_id AS h, a.t FROM {p}_qb a JOIN {held} b ON a.batch_id = b.batch_id AND a.t = b.t AND a.bucket = b.bucket AND b.doc_id < a.doc_id), {p}_p AS (SELECT DISTINCT batch_id, q, h FROM {p}_t)"""
        if cfg.distance == "hamming":
            bits = cfg.k * cfg.tables
            ctes += f""", {p}_d AS (SELECT q, h, round(list_sum([bit_count(xor(x.bands[i], y.bands[i])) FOR i IN range(1, {cfg.tables + 1})]) / CAST({bits} AS DOUBLE), 6) AS distance FROM {p}_p p JOIN {p}_qs x ON x.batch_id = p.batch_id AND x.doc_id = q JOIN {p}_hs y ON y.batch_id = p.batch_id AND y.doc_id = h)"""
    limit = f"JOIN {p}_p p ON p.batch_id = a.batch_id AND p.q = a.doc_id AND p.h = b.doc_id" if cfg.search == "lsh" else ""
    if cfg.distance != "hamming":
        ctes += f""", {p}_dot AS (SELECT a.batch_id, a.doc_id AS q, b.doc_id AS h, sum(a.x * b.x) AS dot FROM {p}_q a JOIN {p}_h b ON a.batch_id = b.batch_id AND a.term = b.term AND b.doc_id < a.doc_id {limit} WHERE a.x <> 0 AND b.x <> 0 GROUP BY ALL),
{p}_d AS (SELECT q, h, round(1 - greatest(-1, least(1, coalesce(dot / nullif(sqrt(u.s * v.s), 0), 0))), 6) AS distance FROM {p}_dot d JOIN {query_length} u ON u.batch_id = d.batch_id AND u.doc_id = q JOIN {p}_hl v ON v.batch_id = d.batch_id AND v.doc_id = h)"""
    if cfg.combine == "mean":
        ctes += f""", {p}_b AS (SELECT t.q, t.t, min({{'d': coalesce(round(distance, 6), 1), 'h': t.h}}) AS s FROM {p}_t t LEFT JOIN {p}_d d ON d.q = t.q AND d.h = t.h GROUP BY ALL),
{p}_n AS (SELECT q, round((sum(s.d) + {cfg.tables} - count(*)) / {cfg.tables}, 9) AS distance, min(s).h AS h FROM {p}_b GROUP BY q)"""
    else:
        ctes += f", {p}_n AS (SELECT q, distance, h FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY distance, h) AS r FROM {p}_d) WHERE r = 1)"
    return ctes + f", {out} AS (SELECT doc_id, coalesce(distance, 1) AS distance, h AS match_id FROM (SELECT doc_id FROM {source} WHERE batch_id > 0) LEFT JOIN (SELECT * FROM {p}_n WHERE distance < 1) ON q = doc_id)"


DECIDED = f"SELECT doc_id, distance, CASE WHEN distance < {THRESHOLD} THEN match_id END AS match_id, match_id IS NULL OR distance >= {THRESHOLD} AS is_novel, CASE WHEN distance < {THRESHOLD} THEN coalesce(match_id + 1, 0) ELSE 0 END AS predicted FROM"
BASE_SQL = "WITH" + streams.constructed_sql()

VARIANTS = {
    "detect_static_lsh": HASHED.but(scheme="static"),
    "detect_incremental_lsh": HASHED,
    "detect_additive_lsh": HASHED.but(scheme="additive"),
    "detect_static_exact": Config(scheme="static", search="exact"),
    "detect_incremental_exact": Config(search="exact"),
    "detect_additive_exact": Config(scheme="additive", search="exact"),
    "detect_static_norm": Config(scheme="static", search="exact", oov="norm"),
    "detect_single_table": HASHED.but(tables=1),
    "detect_capped": HASHED.but(bucket_cap=3),
    "detect_reference": Config(search="exact", history="reference"),
    "detect_all_seen": Config(search="exact", history="all_seen"),
    "detect_hamming": HASHED.but(distance="hamming"),
    "detect_incremental_raw": Config(search="exact", tf_mode="raw"),
    "detect_incremental_collection": Config(search="exact", tf_mode="collection"),
    "combine_union": HASHED.but(combine="union"),
    "combine_mean": HASHED.but(combine="mean"),
}


def _detector(cfg: Config):
    def run(spark, d) -> DataFrame:
        return detect.decide(detect.scores(streams.constructed(spark, d), cfg), THRESHOLD)

    return run


for _name, _cfg in VARIANTS.items():
    QUERIES[_name] = _detector(_cfg)
    SQL[_name] = f"{BASE_SQL}, {scores_sql(_cfg)} {DECIDED} scored"


@query("detect_random", f"{BASE_SQL}, scored AS (SELECT doc_id, round(CAST('0x' || substr(md5(doc_id || '|1'), 1, 8) AS BIGINT) / 4294967296.0::DOUBLE, 6) AS distance, CAST(NULL AS BIGINT) AS match_id FROM docs WHERE batch_id > 0) SELECT doc_id, distance FROM scored")
def detect_random(spark, d):
    return detect.random(streams.constructed(spark, d)).select("doc_id", "distance")


@query("detect_constant", f"{BASE_SQL} SELECT doc_id, 1.0::DOUBLE AS all_novel, 0.0::DOUBLE AS all_old FROM docs WHERE batch_id > 0")
def detect_constant(spark, d):
    docs = streams.constructed(spark, d)
    return detect.constant(docs, True).select("doc_id", F.col("distance").alias("all_novel")).join(detect.constant(docs, False).select("doc_id", F.col("distance").alias("all_old")), "doc_id")


NEAR_SQL = f"{BASE_SQL}, {scores_sql(Config(search='exact', history='all_seen'))}, near AS (SELECT q, h FROM scored_d WHERE distance < {THRESHOLD})"


def near_pairs(spark, d) -> tuple[DataFrame, DataFrame]:
    """Pairs nearer than the threshold among all documents, and the documents."""
    docs = streams.constructed(spark, d)
    tf = model.term_counts(docs)
    w = model.weights(tf, model.corpus_size(docs)).withColumn("seq", F.col("doc_id"))
    return similarity.within(similarity.products(w, w, prior=True), THRESHOLD).select("q", "h"), docs.select("doc_id")


@query("detect_novel_only")
def detect_novel_only(spark, d):
    pairs, docs = near_pairs(spark, d)
    scratch = Scratch(spark, "settle")
    return detect.settle(scratch.write(pairs, "pairs"), docs, scratch.write)


CHAIN_SQL = f"""{BASE_SQL.replace('WITH', 'WITH RECURSIVE', 1)}, {scores_sql(Config(search='exact', history='all_seen'))}, dec AS ({DECIDED} scored),
chain AS (SELECT doc_id, doc_id AS node FROM docs UNION ALL SELECT chain.doc_id, match_id FROM chain JOIN dec ON dec.doc_id = chain.node WHERE match_id IS NOT NULL) SELECT doc_id, min(node) AS story FROM chain GROUP BY doc_id HAVING doc_id IN (SELECT doc_id FROM dec)"""


@query("event_chains", CHAIN_SQL)
def event_chains(spark, d):
    decided = detect.decide(detect.scores(streams.constructed(spark, d), Config(search="exact", history="all_seen")), THRESHOLD)
    return detect.chains(decided, Scratch(spark, "chains").write)


@query("decide", f"{BASE_SQL}, {scores_sql(Config(scheme='static', search='exact'))} {DECIDED} scored")
def decide(spark, d):
    return detect.decide(detect.scores(streams.constructed(spark, d), Config(scheme="static", search="exact")), THRESHOLD)


# ---- measures ----------------------------------------------------------------------------------------------------------------

EXACT = Config(search="exact")
SCORED = f"{BASE_SQL}, {scores_sql(EXACT, out='sc')}, s AS (SELECT doc_id, distance, match_id, truth_id FROM sc JOIN docs USING (doc_id)), dec AS (SELECT s.*, match_id IS NULL OR distance >= {THRESHOLD} AS is_novel FROM s)"


def with_truth(docs: DataFrame, cfg: Config) -> DataFrame:
    """Scored rows of a stream with its truth, as a written table: measures read them more than once."""
    by = [*detect.streams_of(docs), "doc_id"]
    extra = [c for c in ("source_id",) if c in docs.columns]
    return Scratch(docs.sparkSession, "scored").write(detect.scores(docs, cfg).join(docs.select(*by, "truth_id", *extra), by), "rows")


def scored(spark, d, cfg: Config = EXACT, **stream) -> DataFrame:
    return with_truth(streams.constructed(spark, d, **stream), cfg)


def decided(spark, d) -> DataFrame:
    return detect.decide(scored(spark, d), THRESHOLD)


COUNTS = "c AS (SELECT count(*) FILTER (truth_id IS NULL AND is_novel) AS tp, count(*) FILTER (truth_id IS NULL AND NOT is_novel) AS fn, count(*) FILTER (truth_id IS NOT NULL AND is_novel) AS fp, count(*) FILTER (truth_id IS NOT NULL AND NOT is_novel) AS tn FROM dec)"
COST = "(0.02::DOUBLE * {m} + 0.098::DOUBLE * {f}) / 0.02"


@query("met_confusion", f"{SCORED}, {COUNTS} SELECT * FROM c")
def met_confusion(spark, d):
    return metrics.confusion(decided(spark, d))


@query("met_rates", f"{SCORED}, {COUNTS} SELECT round(fn / (tp + fn), 6) AS p_miss, round(fp / (fp + tn), 6) AS p_fa, round(fp / nullif(tp + fp, 0), 6) AS p_fa_flagged FROM c")
def met_rates(spark, d):
    return metrics.rates(metrics.confusion(decided(spark, d))).select(*[F.round(c, 6).alias(c) for c in ("p_miss", "p_fa", "p_fa_flagged")])


#: A call that large lines come back, against the lines that did; by the line's number.
LINE_RATES = "SELECT l_linenumber, count(*) FILTER (l_returnflag = 'R' AND l_quantity <= 25) / count(*) FILTER (l_returnflag = 'R') AS m, count(*) FILTER (l_returnflag <> 'R' AND l_quantity > 25) / count(*) FILTER (l_returnflag <> 'R') AS f FROM lineitem GROUP BY 1"


@query("met_cost", f"SELECT l_linenumber, m AS p_miss, f AS p_fa, round({COST.format(m='m', f='f')}, 6) AS cost FROM ({LINE_RATES})")
def met_cost(spark, d):
    back, large = F.col("l_returnflag") == "R", F.col("l_quantity") > 25
    share = lambda part, whole: F.try_divide(F.count_if(whole & part), F.count_if(whole))
    rows = table(spark, d, "lineitem").groupBy("l_linenumber").agg(share(~large, back).alias("p_miss"), share(large, ~back).alias("p_fa"))
    return rows.withColumn("cost", F.round(metrics.cost(F.col("p_miss"), F.col("p_fa")), 6))


CURVE = f"""dist AS (SELECT distance AS threshold, count(*) FILTER (truth_id IS NULL) AS a, count(*) FILTER (truth_id IS NOT NULL) AS b FROM s GROUP BY 1),
pts AS (SELECT threshold, coalesce(sum(a) OVER w, 0) AS missed, coalesce(sum(b) OVER w, 0) AS caught FROM dist WINDOW w AS (ORDER BY threshold ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) UNION ALL SELECT 2, sum(a), sum(b) FROM dist),
tot AS (SELECT sum(a) AS na, sum(b) AS nb FROM dist), curve AS (SELECT threshold, missed / na AS p_miss, 1 - caught / nb AS p_fa FROM pts, tot)"""


@query("met_det", f"{SCORED}, {CURVE} SELECT threshold, round(p_miss, 6) AS p_miss, round(p_fa, 6) AS p_fa, round({COST.format(m='p_miss', f='p_fa')}, 6) AS cost FROM curve")
def met_det(spark, d):
    return metrics.det_curve(scored(spark, d)).select("threshold", *[F.round(c, 6).alias(c) for c in ("p_miss", "p_fa", "cost")])


@query("met_det_grid", f"""{SCORED}, g AS (SELECT unnest(range(21)) / 20 AS threshold) SELECT threshold, round(count(*) FILTER (truth_id IS NULL AND distance < threshold) / count(*) FILTER (truth_id IS NULL), 6) AS p_miss,
round(1 - count(*) FILTER (truth_id IS NOT NULL AND distance < threshold) / count(*) FILTER (truth_id IS NOT NULL), 6) AS p_fa FROM g, s GROUP BY threshold""")
def met_det_grid(spark, d):
    return metrics.det_grid(scored(spark, d)).select("threshold", F.round("p_miss", 6).alias("p_miss"), F.round("p_fa", 6).alias("p_fa"))


@query("met_probit", """WITH p AS (SELECT DISTINCT CAST(l_quantity AS DOUBLE) / 51 AS p FROM lineitem), q AS (SELECT p, sqrt(-2 * ln(least(p, 1 - p))) AS t FROM p)
SELECT p, round((t - (2.515517::DOUBLE + t * (0.802853::DOUBLE + t * 0.010328::DOUBLE)) / (1 + t * (1.432788::DOUBLE + t * (0.189269::DOUBLE + t * 0.001308::DOUBLE)))) * CASE WHEN p < 0.5 THEN -1 ELSE 1 END, 6) + 0.0::DOUBLE AS z FROM q""")
def met_probit(spark, d):
    """At shares of the quantities' range."""
    shares = table(spark, d, "lineitem").select((F.col("l_quantity").cast("double") / 51).alias("p")).distinct()
    return shares.withColumn("z", F.round(metrics.probit(F.col("p")), 6) + F.lit(0.0))


BEST = f"cc AS (SELECT *, round({COST.format(m='p_miss', f='p_fa')}, 9) AS cost FROM curve), best AS (SELECT * FROM cc ORDER BY cost, threshold LIMIT 1)"


@query("met_min_cost", f"{SCORED}, {CURVE}, {BEST} SELECT round(cost, 6) AS cost, threshold, round(p_miss, 6) AS p_miss, round(p_fa, 6) AS p_fa FROM best")
def met_min_cost(spark, d):
    best = metrics.best_point(metrics.det_curve(scored(spark, d)))
    return best.select(F.round("cost", 6).alias("cost"), "threshold", F.round("p_miss", 6).alias("p_miss"), F.round("p_fa", 6).alias("p_fa"))


@query("met_auc", f"{SCORED}, {CURVE}, st AS (SELECT p_miss, p_fa, (p_miss - lag(p_miss) OVER w) * (p_fa + lag(p_fa) OVER w) / 2 AS a FROM curve WINDOW w AS (ORDER BY p_miss, p_fa DESC)) SELECT round(sum(a), 6) AS auc, (SELECT round((p_miss + p_fa) / 2, 6) FROM curve ORDER BY round(abs(p_miss - p_fa), 9), p_miss + p_fa LIMIT 1) AS equal_error FROM st")
def met_auc(spark, d):
    return metrics.area(metrics.det_curve(scored(spark, d))).select(F.round("auc", 6).alias("auc"), F.round("equal_error", 6).alias("equal_error"))


def two_best(a: str, b: str) -> str:
    """Best points of two scored tables, as CTEs best_a and best_b."""
    parts = []
    for n, source in (("a", a), ("b", b)):
        text = f"s_{n} AS (SELECT distance, truth_id FROM {source} JOIN docs USING (doc_id)), " + CURVE.replace("FROM s ", f"FROM s_{n} ") + ", " + BEST
        for word in ("dist", "pts", "tot", "curve", "cc", "best"):
            text = text.replace(f"{word} AS (", f"{word}_{n} AS (").replace(f"FROM {word} ", f"FROM {word}_{n} ").replace(f"FROM {word})", f"FROM {word}_{n})").replace(f"FROM {word},", f"FROM {word}_{n},").replace(", tot)", f", tot_{n})").replace(f", {word} WINDOW", f", {word}_{n} WINDOW")
        parts.append(text)
    return ", ".join(parts)


@query("met_gain", f"""{BASE_SQL}, {scores_sql(Config(scheme='static', search='exact'), out='st')}, {scores_sql(EXACT, out='me')}, {two_best('st', 'me')}
SELECT round(a.p_miss, 6) AS miss_a, round(b.p_miss, 6) AS miss_b, round(a.p_fa, 6) AS fa_a, round(b.p_fa, 6) AS fa_b, round(a.cost, 6) AS cost_a, round(b.cost, 6) AS cost_b, round(a.p_miss - b.p_miss, 6) AS miss_gain, round(a.cost - b.cost, 6) AS cost_gain FROM best_a a, best_b b""")
def met_gain(spark, d):
    best = [metrics.best_point(metrics.det_curve(scored(spark, d, Config(scheme=s, search="exact")))) for s in ("static", "merged")]
    both = metrics.compare(*best)
    return both.select(*[F.round(c, 6).alias(c) for c in ("miss_a", "miss_b", "fa_a", "fa_b", "cost_a", "cost_b", "miss_gain", "cost_gain")])


@query("met_match", f"{SCORED} SELECT count(*) FILTER (truth_id IS NOT NULL) AS n_old, count(*) FILTER (truth_id IS NOT NULL AND NOT is_novel) AS called_old, count(*) FILTER (NOT is_novel AND match_id = truth_id) AS right_id FROM dec")
def met_match(spark, d):
    return metrics.match_accuracy(decided(spark, d))


PAIRS = f"{BASE_SQL}, {scores_sql(HASHED, out='ha')}, {scores_sql(EXACT, out='ex')}"


@query("met_work", f"{PAIRS} SELECT (SELECT count(*) FROM ha_p) AS hashed, (SELECT count(*) FROM ex_dot) AS joined, (SELECT count(*) FROM docs WHERE batch_id > 0) * (SELECT count(*) FROM docs WHERE batch_id = 0) AS all_pairs")
def met_work(spark, d):
    docs = streams.constructed(spark, d)
    sizes = docs.agg((F.count_if(F.col("batch_id") > 0) * F.count_if(F.col("batch_id") == 0)).alias("all_pairs"))
    return detect.work(docs, HASHED, Scratch(spark, "work")).join(sizes)


@query("met_recall", f"{PAIRS} SELECT count(*) AS n, count(*) FILTER (ha.distance <= ex.distance) AS hit, round(count(*) FILTER (ha.distance <= ex.distance) / count(*), 6) AS recall FROM ex LEFT JOIN ha USING (doc_id)")
def met_recall(spark, d):
    docs = streams.constructed(spark, d)
    near = lambda cfg: detect.scores(docs, cfg).select(F.col("doc_id").alias("q"), "distance", F.col("match_id").alias("h"))
    return metrics.recall(near(HASHED), near(EXACT)).withColumn("recall", F.round("recall", 6))


RANDOM = f"{BASE_SQL}, s AS (SELECT doc_id, round(CAST('0x' || substr(md5(doc_id || '|1'), 1, 8) AS BIGINT) / 4294967296.0::DOUBLE, 6) AS distance, truth_id FROM docs WHERE batch_id > 0)"


@query("met_random_line", f"{RANDOM}, {CURVE} SELECT count(*) AS points, round(avg(p_miss + p_fa), 4) AS mean_sum FROM curve")
def met_random_line(spark, d):
    docs = streams.constructed(spark, d)
    rows = detect.random(docs).join(docs.select("doc_id", "truth_id"), "doc_id")
    return metrics.det_curve(rows).agg(F.count("*").alias("points"), F.round(F.avg(F.col("p_miss") + F.col("p_fa")), 4).alias("mean_sum"))


@query("met_annotated", f"{SCORED}, k AS (SELECT DISTINCT doc_id FROM labels), {COUNTS.replace('FROM dec', 'FROM dec JOIN docs USING (doc_id) WHERE source_id IN (SELECT doc_id FROM k)').replace('truth_id', 'dec.truth_id')}, every AS (SELECT count(*) AS n_all FROM dec) SELECT c.*, n_all FROM c, every")
def met_annotated(spark, d):
    """Counts over the snippets cut from annotated documents, with the number of all snippets."""
    rows = decided(spark, d)
    known = table(spark, d, "labels").select(F.col("doc_id").alias("source_id")).distinct()
    return metrics.confusion(rows.join(known, "source_id", "left_semi")).join(rows.agg(F.count("*").alias("n_all")))


@query("met_bootstrap")
def met_bootstrap(spark, d):
    return metrics.bootstrap(decided(spark, d))


@query("met_holdout", f"""{SCORED.replace('dec AS (SELECT s.*', 'half AS (SELECT s.*, row_number() OVER (ORDER BY doc_id) * 2 <= count(*) OVER () AS early FROM s), dec AS (SELECT s.*')}, {CURVE.replace('FROM s ', 'FROM half WHERE early ')}, {BEST},
dd AS (SELECT truth_id, distance >= threshold AS is_novel FROM half, best WHERE NOT early), {COUNTS.replace('FROM dec', 'FROM dd')} SELECT c.*, threshold FROM c, best""")
def met_holdout(spark, d):
    rows = scored(spark, d)
    half = streams.numbered(rows, F.floor(F.col("doc_id") / 4096), ["doc_id"], "k").join(F.broadcast(rows.agg(F.count("*").alias("n"))))
    half = half.withColumn("early", (F.col("k") + 1) * 2 <= F.col("n"))
    best = metrics.best_point(metrics.det_curve(half.filter("early").select("doc_id", "distance", "match_id", "truth_id"))).select("threshold")
    late = half.filter("NOT early").join(F.broadcast(best)).withColumn("is_novel", F.col("distance") >= F.col("threshold"))
    return metrics.confusion(late).join(best)


@query("met_coverage", f"{SCORED}, h AS (SELECT 1) SELECT count(*) AS n, count(*) FILTER (match_id IS NULL) AS no_candidate, round(avg(distance), 6) AS mean_distance FROM s")
def met_coverage(spark, d):
    return scored(spark, d).agg(F.count("*").alias("n"), F.count_if(F.col("match_id").isNull()).alias("no_candidate"), F.round(F.avg("distance"), 6).alias("mean_distance"))


# ---- experiment tables ---------------------------------------------------------------------------------------------------------


def best_of(rows: DataFrame) -> DataFrame:
    best = metrics.best_point(metrics.det_curve(rows))
    return best.select("threshold", *[F.round(c, 6).alias(c) for c in ("p_miss", "p_fa", "cost")])


def union_all(parts: list[DataFrame]) -> DataFrame:
    return functools.reduce(DataFrame.unionByName, parts)


SCHEMES = {"static": Config(scheme="static", search="exact"), "static_norm": Config(scheme="static", search="exact", oov="norm"), "merged": EXACT, "additive": Config(scheme="additive", search="exact")}


def best_sql(name: str, cfg: Config, base: str, extra: str) -> str:
    return f"(WITH {base}, {scores_sql(cfg, out='sc')}, s AS (SELECT doc_id, distance, truth_id FROM sc JOIN docs USING (doc_id)), {CURVE}, {BEST} SELECT {extra} threshold, round(p_miss, 6) AS p_miss, round(p_fa, 6) AS p_fa, round(cost, 6) AS cost FROM best)"


CELLS = [(keep, burst) for keep in (0.2, 0.3, 0.5) for burst in (1, 4, 14)]


def best_of_streams(docs: DataFrame, cfgs: dict[str, Config], label: str = "scheme") -> DataFrame:
    """Each scheme's best point on each stream: (label, stream, threshold, p_miss, p_fa, cost)."""
    parts = []
    for name, cfg in cfgs.items():
        best = metrics.best_point(metrics.det_curve(with_truth(docs, cfg), ("stream",)), ("stream",))
        parts.append(best.select(F.lit(name).alias(label), "stream", "threshold", *[F.round(c, 6).alias(c) for c in ("p_miss", "p_fa", "cost")]))
    return union_all(parts)


def cells(spark, d) -> DataFrame:
    """The nine streams of kept share and repeats an event, cut from the same parents."""
    held = streams.parents(spark, d)
    return streams.together({f"{keep}/{burst}": streams.constructed(spark, d, keep, burst, held=held) for keep, burst in CELLS})


@query("exp_schemes", " UNION ALL ".join(best_sql(n, c, streams.constructed_sql(k, b), f"'{n}' AS scheme, {k}::DOUBLE AS keep, {b} AS burst,") for n, c in SCHEMES.items() for k, b in CELLS))
def exp_schemes(spark, d):
    """Each scheme at its own best threshold, over kept share and repeats an event (the comparison of the paper's two tables)."""
    out = best_of_streams(cells(spark, d), SCHEMES)
    part = F.split("stream", "/")
    return out.select("scheme", F.get(part, F.lit(0)).cast("double").alias("keep"), F.get(part, F.lit(1)).cast("int").alias("burst"), "threshold", "p_miss", "p_fa", "cost")


def curves_sql(k: float, b: int) -> str:
    parts = []
    for name in ("static", "merged"):
        parts.append(f"(WITH {streams.constructed_sql(k, b)}, {scores_sql(SCHEMES[name], out='sc')}, s AS (SELECT doc_id, distance, truth_id FROM sc JOIN docs USING (doc_id)), {CURVE}, {BEST} SELECT '{name}' AS scheme, cc.threshold, round(cc.p_miss, 6) AS p_miss, round(cc.p_fa, 6) AS p_fa, cc.threshold = best.threshold AS is_best FROM cc, best)")
    return " UNION ALL ".join(parts)


@query("exp_curves", curves_sql(0.3, 4))
def exp_curves(spark, d):
    """The trade-off curves of the static and the incremental scheme on one stream, each with its lowest-cost point marked."""
    docs = streams.constructed(spark, d, 0.3, 4).withColumn("stream", F.lit("0.3/4"))
    parts = []
    for name in ("static", "merged"):
        curve = metrics.det_curve(with_truth(docs, SCHEMES[name]))
        best = metrics.best_point(curve).select(F.col("threshold").alias("at"))
        parts.append(curve.join(F.broadcast(best)).select(F.lit(name).alias("scheme"), "threshold", F.round("p_miss", 6).alias("p_miss"), F.round("p_fa", 6).alias("p_fa"), (F.col("threshold") == F.col("at")).alias("is_best")))
    return union_all(parts)


@query("exp_natural", f"WITH {streams.natural_sql()}, {scores_sql(EXACT, 'ndocs', 'sc')}, s AS (SELECT doc_id, distance, truth_id FROM sc JOIN ndocs USING (doc_id)), {CURVE}, {BEST} SELECT threshold, round(p_miss, 6) AS p_miss, round(p_fa, 6) AS p_fa, round(cost, 6) AS cost FROM best")
def exp_natural(spark, d):
    """The given documents in order, truth from 5-grams: merged weights, exhaustive search."""
    return best_of(with_truth(streams.natural(spark, d), EXACT))


SWEEP_K, SWEEP_L = (4, 8, 13), (1, 2, 5, 14, 22)


@query("exp_tables", " UNION ALL ".join(f"(WITH {streams.constructed_sql()}, {scores_sql(Config(k=k, tables=max(SWEEP_L)), out='ha')}, {scores_sql(EXACT, out='ex')}, p AS (SELECT q, h, min(t) AS t FROM ha_t GROUP BY ALL), g AS (SELECT unnest({list(SWEEP_L)}) AS l), f AS (SELECT l, p.q, min(coalesce(distance, 1)) AS d FROM p JOIN g ON p.t <= l LEFT JOIN ha_d x ON x.q = p.q AND x.h = p.h GROUP BY ALL), c AS (SELECT l, count(*) AS pairs FROM p JOIN g ON p.t <= l GROUP BY l) SELECT {k} AS k, CAST(g.l AS INTEGER) AS tables, coalesce(any_value(c.pairs), 0) AS pairs, count(*) AS n, count(*) FILTER (coalesce(f.d, 1) <= ex.distance) AS hit FROM ex CROSS JOIN g LEFT JOIN f ON f.l = g.l AND f.q = ex.doc_id LEFT JOIN c ON c.l = g.l GROUP BY g.l)" for k in SWEEP_K))
def exp_tables(spark, d):
    """Recall and work of hashed search over bits and tables. The first tables of the widest index are the smaller indexes."""
    docs, scratch = streams.constructed(spark, d), Scratch(spark, "sweep")
    tf, held = detect.statistics(docs, EXACT, scratch)
    exact = scratch.write(detect.scores(docs, EXACT).select(F.col("doc_id").alias("q"), F.col("distance").alias("d")), "exact")
    every = scratch.write(detect.all_distances(docs, tf, held, EXACT), "distances")
    limits = F.explode(F.array(*[F.lit(x) for x in SWEEP_L])).alias("tables")
    parts = []
    for k in SWEEP_K:
        cfg = Config(k=k, tables=max(SWEEP_L))
        met = detect.met_in_tables(*detect.hashed(tf, held, cfg), cfg).groupBy("q", "h").agg((F.min("table_no") + 1).alias("first"))
        known = scratch.write(met.join(every, ["q", "h"], "left").withColumn("distance", F.coalesce("distance", F.lit(1.0))), f"met-{k}")
        cells = known.select("q", "distance", "first", limits).filter(F.col("first") <= F.col("tables"))
        pairs = cells.groupBy("tables").agg(F.count("*").alias("pairs"))
        best = cells.groupBy("tables", "q").agg(F.min("distance").alias("f"))
        both = exact.select("q", "d", limits).join(best, ["tables", "q"], "left")
        counts = both.groupBy("tables").agg(F.count("*").alias("n"), F.count_if(F.coalesce("f", F.lit(1.0)) <= F.col("d")).alias("hit"))
        parts.append(counts.join(pairs, "tables", "left").select(F.lit(k).alias("k"), "tables", F.coalesce("pairs", F.lit(0)).alias("pairs"), "n", "hit"))
    return union_all(parts)


BATCHES = (1, 10, 100, 1_000_000)


@query("exp_batch_size", " UNION ALL ".join(best_sql(s, Config(scheme=s, search="exact"), streams.constructed_sql(batch=b), f"'{s}' AS scheme, {b} AS batch,") for b in BATCHES for s in ("static", "merged", "additive")))
def exp_batch_size(spark, d):
    """Schemes over the size of batches; with one document a batch the additive scheme is the static one."""
    held = streams.parents(spark, d)
    docs = streams.together({str(b): streams.constructed(spark, d, batch=b, held=held) for b in BATCHES})
    out = best_of_streams(docs, {s: Config(scheme=s, search="exact") for s in ("static", "merged", "additive")})
    return out.select("scheme", F.col("stream").cast("int").alias("batch"), "threshold", "p_miss", "p_fa", "cost")
