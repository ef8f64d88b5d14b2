"""What users of a linkage do around it: other joins, aggregates, windows, set operations, sources, streams, SQL functions."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..config import LinkConfig
from ..functions import tokens as tok
from ..functions.udfs import register
from ..operators import baselines, batch, evaluate, select
from ..operators.index import Index, build_index
from ..sources import lists
from ..sources.fixtures import address_list
from ..streaming import arrivals as live
from . import oracles as o
from .workloads import _BLEND as BLEND_SQL
from .workloads import _PM as PAIR_SQL
from .workloads import ORACLES, QUERIES, query, ref_link, truth_of, two  # noqa: F401  its queries stand with the workloads'


def shared_folder(spark: SparkSession) -> str:
    """A new folder that driver and executors share: under the session's checkpoint folder, else a temporary one of this machine."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        base = tempfile.mkdtemp(prefix="tokenweave-")
        atexit.register(shutil.rmtree, base, ignore_errors=True)
        base = f"file://{base}"
    return f"{base.rstrip('/')}/{uuid.uuid4().hex}"


# ---- joins

query("join_semi", f"WITH {o.pair_parts('raw_mentions', 'gazetteer', 20)} SELECT id, address FROM raw_mentions WHERE id IN (SELECT id_1 FROM cand)")(lambda s, d: (lambda x: x[0].select("id", "address").join(x[2].select(F.col("id_1").alias("id")), "id", "left_semi"))(ref_link(s, d, k=20)))
query("join_anti", f"WITH {o.pair_parts('raw_mentions', 'gazetteer', 20)} SELECT id, address FROM raw_mentions WHERE id NOT IN (SELECT id_1 FROM cand)")(lambda s, d: (lambda x: x[0].select("id", "address").join(x[2].select(F.col("id_1").alias("id")), "id", "left_anti"))(ref_link(s, d, k=20)))


@query("join_full", "SELECT coalesce(a.truth, b.truth) AS site, count(a.id) AS n_a, count(b.id) AS n_b FROM (SELECT truth, min(id) AS id FROM raw_a GROUP BY truth) a FULL JOIN (SELECT truth, min(id) AS id FROM raw_b GROUP BY truth) b ON a.truth = b.truth GROUP BY 1")
def _(s, d):
    a, b = two(s, d, ("raw_a", "raw_b"))
    x, y = a.select("truth", F.lit(1).alias("a")).distinct(), b.select("truth", F.lit(1).alias("b")).distinct()
    return x.join(y, "truth", "full").select(F.col("truth").alias("site"), F.coalesce("a", F.lit(0)).cast("long").alias("n_a"), F.coalesce("b", F.lit(0)).cast("long").alias("n_b"))


@query("join_range", rf"WITH r AS (SELECT id, length({o.PLAIN}) AS n FROM url_lines), g AS (SELECT id, length({o.PLAIN}) AS n FROM passages) SELECT r.id AS id_1, g.id AS id_2 FROM r JOIN g ON g.n BETWEEN r.n - 40 AND r.n + 40")
def _(s, d):
    """Sizes within a window of each other: sizes fall into bins as wide as the window, so that an equal bin is the join key."""
    a, b = two(s, d, ("url_lines", "passages"))
    n, width = F.length(F.regexp_replace(F.lower("address"), r"[^\p{L}\p{N}]", "")), 40
    x = a.select(F.col("id").alias("id_1"), n.alias("n1")).withColumn("bin", F.floor(F.col("n1") / width)).withColumn("bin", F.explode(F.array(F.col("bin") - 1, F.col("bin"), F.col("bin") + 1)))
    y = b.select(F.col("id").alias("id_2"), n.alias("n2")).withColumn("bin", F.floor(F.col("n2") / width))
    return x.join(y, "bin").where(f"n2 BETWEEN n1 - {width} AND n1 + {width}").select("id_1", "id_2")


@query("join_asof", "SELECT event_id, max(o_orderdate) AS since FROM (SELECT event_id, user_id, ts FROM events) e LEFT JOIN orders ON o_custkey = user_id AND o_orderdate <= ts GROUP BY event_id")
def _(s, d):
    """The latest order date of the site at the time of an event: one sorted pass over both, no pair of rows."""
    address_list(s, d, "site")
    e = s.table("events").select(F.col("user_id").cast("long").alias("site"), "ts", "event_id", F.lit(None).cast("timestamp").alias("since"))
    r = s.table("orders").select(F.col("o_custkey").cast("long").alias("site"), F.col("o_orderdate").cast("timestamp").alias("ts"), F.lit(None).cast("long").alias("event_id"), F.col("o_orderdate").cast("timestamp").alias("since"))
    w = Window.partitionBy("site").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)
    both = e.select("site", "ts", F.col("event_id").cast("long").alias("event_id"), "since").union(r).withColumn("since", F.max("since").over(w))
    return both.where("event_id IS NOT NULL").select("event_id", "since")


# ---- aggregates

_G = "SELECT truth, kind, status, n_nationkey, r_name FROM raw_mentions JOIN customer ON c_custkey = truth JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey"


def _grouped(s, d):
    address_list(s, d, "raw_mentions")
    return s.sql(_G)


query("agg_rollup", f"SELECT r_name, n_nationkey, count(*) AS n FROM ({_G}) GROUP BY ROLLUP (r_name, n_nationkey)")(lambda s, d: _grouped(s, d).rollup("r_name", "n_nationkey").agg(F.count("*").alias("n")))
query("agg_cube", f"SELECT kind, status, count(*) AS n FROM ({_G}) GROUP BY CUBE (kind, status)")(lambda s, d: _grouped(s, d).cube("kind", "status").agg(F.count("*").alias("n")))
query("agg_grouping_sets", f"SELECT kind, status, grouping_id(kind, status)::BIGINT AS g, count(*) AS n FROM ({_G}) GROUP BY GROUPING SETS ((kind), (status), ())")(
    lambda s, d: (_grouped(s, d).createOrReplaceTempView("tw_grouped"), s.sql("SELECT kind, status, grouping_id(kind, status) AS g, count(*) AS n FROM tw_grouped GROUP BY GROUPING SETS ((kind), (status), ())"))[1])
query("agg_pivot", "SELECT kind, count(*) FILTER (status = 'F') AS f, count(*) FILTER (status = 'O') AS o, count(*) FILTER (status = 'P') AS p FROM raw_mentions GROUP BY kind")(
    lambda s, d: address_list(s, d, "raw_mentions").groupBy("kind").pivot("status", ["F", "O", "P"]).agg(F.count(F.lit(1))).select("kind", *[F.coalesce(c, F.lit(0)).alias(c.lower()) for c in "FOP"]))
query("agg_percentile", f"SELECT percentile_disc(0.5) WITHIN GROUP (ORDER BY df) AS middle, percentile_disc(0.99) WITHIN GROUP (ORDER BY df) AS high, max(df) AS most FROM (SELECT token, count(*) AS df FROM ({o.tokens('raw_mentions', 'phrases', True)}) GROUP BY token)")(
    lambda s, d: build_index(address_list(s, d, "raw_mentions")).frequencies().agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY df)").cast("long").alias("middle"), F.expr("percentile_disc(0.99) WITHIN GROUP (ORDER BY df)").cast("long").alias("high"), F.max("df").alias("most")))
query("agg_approx")(lambda s, d: build_index(address_list(s, d, "raw_mentions")).postings.agg(F.approx_count_distinct("token").alias("about_tokens"), F.approx_count_distinct("id").alias("about_ids")))

# ---- windows

query("win_rank", "SELECT id, kind, rank() OVER w AS r, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY kind ORDER BY length(address), id) AS q, round(percent_rank() OVER w, 9) AS pr FROM raw_mentions WINDOW w AS (PARTITION BY kind ORDER BY length(address))")(lambda s, d: _ranks(address_list(s, d, "raw_mentions")))


def _ranks(raw):
    w, v = Window.partitionBy("kind").orderBy(F.length("address")), Window.partitionBy("kind").orderBy(F.length("address"), "id")
    return raw.select("id", "kind", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(4).over(v).cast("long").alias("q"), F.round(F.percent_rank().over(w), 9).alias("pr"))


@query("win_frame", "SELECT day, status, n, sum(n) OVER (PARTITION BY status ORDER BY day ROWS BETWEEN 6 PRECEDING AND CURRENT ROW)::BIGINT AS week, first_value(n) OVER (PARTITION BY status ORDER BY day) AS first_n, lag(n) OVER (PARTITION BY status ORDER BY day) AS before FROM (SELECT strftime(o_orderdate, '%Y-%m-%d') AS day, o_orderstatus AS status, count(*) AS n FROM orders GROUP BY 1, 2)")
def _(s, d):
    address_list(s, d, "site")
    days = s.table("orders").groupBy(F.date_format("o_orderdate", "yyyy-MM-dd").alias("day"), F.col("o_orderstatus").alias("status")).agg(F.count("*").alias("n"))
    w = Window.partitionBy("status").orderBy("day")
    return days.select("day", "status", "n", F.sum("n").over(w.rowsBetween(-6, 0)).alias("week"), F.first_value("n").over(w).alias("first_n"), F.lag("n").over(w).alias("before"))


# ---- set operations, sorting, subqueries

_TWO = f"WITH p AS (WITH {o.pair_parts('raw_b', 'raw_a', 5)} SELECT * FROM cand), q AS (WITH {o.pair_parts('raw_b', 'raw_a', 20, 'words')} SELECT * FROM cand)"


def _passes(s, d):
    b, a = two(s, d, ("raw_b", "raw_a"))
    return tuple(batch.link(b, a, c).select("id_1", "id_2") for c in (LinkConfig(k=5), LinkConfig(k=20, blocker="words")))


query("setop_union", f"{_TWO} SELECT * FROM p UNION SELECT * FROM q")(lambda s, d: (lambda x: x[0].union(x[1]).distinct())(_passes(s, d)))
query("setop_intersect", f"{_TWO} SELECT * FROM p INTERSECT SELECT * FROM q")(lambda s, d: (lambda x: x[0].intersect(x[1]))(_passes(s, d)))
query("setop_except", f"{_TWO} SELECT * FROM q EXCEPT SELECT * FROM p")(lambda s, d: (lambda x: x[1].exceptAll(x[0]))(_passes(s, d)))
query("topk_links", f"{o.linked()} SELECT * FROM scored ORDER BY score DESC, id_1, id_2 LIMIT 10")(lambda s, d: ref_link(s, d)[2].orderBy(F.desc("score"), "id_1", "id_2").limit(10))
query("subquery_best", f"{o.linked(k=20)} SELECT id_1, max(score) AS best FROM scored GROUP BY id_1")(
    lambda s, d: (ref_link(s, d, k=20)[2].createOrReplaceTempView("tw_scored"), s.sql("SELECT DISTINCT id_1, score AS best FROM tw_scored x WHERE score = (SELECT max(score) FROM tw_scored y WHERE y.id_1 = x.id_1)"))[1])
query("sample_hash", "SELECT id, address FROM raw_mentions ORDER BY md5(id::VARCHAR), id LIMIT 100")(lambda s, d: address_list(s, d, "raw_mentions").select("id", "address").orderBy(F.md5(F.col("id").cast("string").cast("binary")), "id").limit(100))

# ---- values of the given tables

query("json_arrivals", "SELECT event_id, (props::JSON ->> 'k')::INT AS k FROM events")(lambda s, d: (address_list(s, d, "site"), s.table("events").select("event_id", F.from_json("props", "k int")["k"].alias("k")))[1])
query("url_parts", r"SELECT page_id AS id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host FROM pages")(lambda s, d: (address_list(s, d, "site"), s.table("pages").select(F.col("page_id").alias("id"), F.parse_url("url", F.lit("HOST")).alias("host")))[1])
query("list_report", r"SELECT count(*) AS n_rows, count(*) FILTER (id IS NULL) AS null_ids, (SELECT count(*) FROM (SELECT id FROM turns GROUP BY id HAVING count(*) > 1)) AS repeated_ids, count(*) FILTER (address IS NULL) AS null_texts, count(*) FILTER (address IS NOT NULL AND NOT regexp_matches(address, '[\p{L}\p{N}]')) AS wordless_texts FROM turns")(lambda s, d: lists.list_report(address_list(s, d, "turns")))
query("udf_sql", f"WITH cand AS (SELECT id AS id_1, truth AS id_2 FROM raw_mentions), {o.score_parts('raw_mentions', 'gazetteer', 'pooled', 'words')} SELECT * FROM scored")(lambda s, d: _by_sql(s, d))


def _by_sql(s, d):
    raw, gaz = two(s, d)
    register(s)
    both = raw.select(F.col("id").alias("id_1"), F.col("truth").alias("id_2"), tok.words(F.col("address")).alias("x")).join(gaz.select(F.col("id").alias("id_2"), tok.words(F.col("address")).alias("y")), "id_2")
    return both.select("id_1", "id_2", F.expr("tw_pooled(x, y)").alias("score"))


@query("udtf_tokens", rf"SELECT id, w[i] AS token, (i - 1)::INT AS place FROM (SELECT id, w, unnest(range(1, len(w) + 1)) AS i FROM (SELECT id, {o.WORDS} AS w FROM gazetteer))")
def _(s, d):
    address_list(s, d, "gazetteer")
    register(s)
    return s.sql("SELECT id, token, place FROM gazetteer, LATERAL tw_tokens(address)")


def _round_trip(fmt, **options):
    def run(s, d):
        path = shared_folder(s)
        gaz = address_list(s, d, "gazetteer")
        gaz.write.format(fmt).options(**options).save(path)
        return lists.read_addresses(s, path, fmt, schema=lists.SCHEMA if fmt in ("csv", "json") else None, **options)

    return run


for _fmt, _options in (("parquet", {}), ("orc", {}), ("csv", {"header": True}), ("json", {})):
    query(f"source_{_fmt}", "SELECT id, address FROM gazetteer")(_round_trip(_fmt, **_options))


@query("index_saved", f"SELECT id, token FROM ({o.tokens('gazetteer', 'phrases', True)})")
def _(s, d):
    path = shared_folder(s)
    build_index(address_list(s, d, "gazetteer")).save(path, buckets=8)
    return Index.load(s, path).postings.select("id", "token")


# ---- streams; each query drains a stream of the arrivals and gives what a batch run gives


def _stream(s: SparkSession, d: str, days: int = 3) -> DataFrame:
    """Arrivals as a stream of files, a few ranges of time each, oldest first."""
    path = shared_folder(s)
    rows = address_list(s, d, "arrivals").select("event_id", "site_id", F.col("ts").cast("timestamp").alias("ts"), "address")
    rows.repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(path)
    return live.read_stream(s, path, "event_id long, site_id long, ts timestamp, address string", files_per_trigger=100)


def _drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    return live.drain_to_files(stream, shared_folder(stream.sparkSession), mode)


query("stream_lookup", f"SELECT DISTINCT a.id AS event_id, g.id AS id FROM (SELECT id, token FROM ({o.tokens('(SELECT event_id AS id, address FROM arrivals)', 'phrases', True)})) a JOIN ({o.tokens('gazetteer', 'phrases', True)}) g USING (token) JOIN (SELECT token FROM ({o.tokens('gazetteer', 'phrases', True)}) GROUP BY token HAVING count(*) <= 20) USING (token)")(
    lambda s, d: _drained(live.candidates(_stream(s, d), build_index(s.table("gazetteer")).prune(20))).select("event_id", "id").distinct())
query("stream_tumbling", "SELECT date_trunc('hour', ts) AS start, count(*) AS n FROM arrivals GROUP BY 1")(lambda s, d: _drained(live.tumbling(_stream(s, d), late="40 days").select("start", "n"), "complete"))
query("stream_sliding", "SELECT time_bucket(INTERVAL 15 MINUTE, ts) - INTERVAL 15 MINUTE * k AS start, count(*) AS n FROM arrivals, range(4) r(k) GROUP BY 1")(lambda s, d: _drained(live.sliding(_stream(s, d), late="40 days").select("start", "n"), "complete"))
query("stream_session", """WITH x AS (SELECT site_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS b FROM arrivals WINDOW w AS (PARTITION BY site_id ORDER BY ts)), y AS (SELECT *, sum(b) OVER (PARTITION BY site_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM x)
    SELECT site_id, min(ts) AS start, count(*) AS n FROM y GROUP BY site_id, g""")(lambda s, d: _drained(live.sessions(_stream(s, d), late="40 days").select("site_id", "start", "n"), "complete"))
query("stream_dedup", "SELECT DISTINCT address FROM arrivals")(lambda s, d: _drained(live.without_repeats(_stream(s, d), "40 days").select("address")))
query("stream_interval_join", "SELECT a.event_id AS event_1, b.event_id AS event_2 FROM arrivals a JOIN arrivals b ON a.site_id = b.site_id AND a.event_id < b.event_id AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 1 HOUR")(lambda s, d: _drained(live.interval_join(_stream(s, d), _stream(s, d), late="40 days").select("event_1", "event_2")))
query("stream_rare_tokens", f"SELECT token, count(*) AS df FROM ({o.tokens('(SELECT event_id AS id, address FROM arrivals)', 'phrases', True)}) GROUP BY token")(
    lambda s, d: _drained(live.rare_while(_stream(s, d), 100)).groupBy("token").agg(F.max("df").alias("df")))


@query("stream_link", f"WITH asked AS (SELECT event_id AS id, address FROM arrivals), {o.index_parts('asked', 'gazetteer')}, cand AS MATERIALIZED (SELECT DISTINCT lt.id AS id_1, rt.id AS id_2 FROM rd JOIN rt USING (token) JOIN lt USING (token) WHERE rd.df <= 20), {o.score_parts('asked', 'gazetteer')} SELECT * FROM scored WHERE score > 0.7")
def _(s, d):
    out = shared_folder(s)
    stream = _stream(s, d)
    gaz = s.table("gazetteer")

    def sink(links, number):
        links.select(F.col("query_id").alias("id_1"), F.col("id").alias("id_2"), "score").write.mode("overwrite").parquet(f"{out}/batch={number}")

    live.link_stream(stream, build_index(gaz).prune(20), gaz, sink, shared_folder(s)).awaitTermination()
    return s.read.option("basePath", out).parquet(f"{out}/batch=*").select("id_1", "id_2", "score")


# ---- costs, and links beside known answers

query("cost_report", f"{o.linked()} SELECT (SELECT count(*) FROM raw_mentions) * (SELECT count(*) FROM gazetteer) AS all_pairs, (SELECT count(*) FROM hits) AS proposed, (SELECT count(*) FROM cand) AS evaluations, (SELECT count(*) FROM scored WHERE score > 0.7) AS links")(
    lambda s, d: evaluate.cost_report(*two(s, d)))
#: An outside answer for each mention: the reference address of its order's customer. Open orders (status P) stand for those
#: that the outside system didn't find. ``printed`` is the answer's score, null where the linkage doesn't propose it.
_ANSWERED = f"""{o.linked()}, {o.BEST}, answers AS (SELECT r.id AS id, t.score AS printed, CASE WHEN r.status <> 'P' THEN g.address END AS external FROM raw_mentions r LEFT JOIN gazetteer g ON g.id = r.truth LEFT JOIN scored t ON t.id_1 = r.id AND t.id_2 = r.truth)"""


@query("sample_links", f"{_ANSWERED} SELECT a.id AS id, b.id_2 AS id_2, round(b.score, 9) AS score, round(a.printed, 9) AS printed, (SELECT count(*) FROM scored s WHERE s.id_1 = a.id AND s.score = b.score) AS ties FROM answers a JOIN best b ON b.id_1 = a.id")
def _(s, d):
    """The best match of each mention beside the score of its known answer, and how many tie for the best."""
    raw, _, scored = ref_link(s, d)
    by_score = scored.join(truth_of(raw).withColumnRenamed("id_2", "t"), "id_1").groupBy("id_1", "score").agg(F.min("id_2").alias("id_2"), F.count("*").alias("ties"), F.max(F.col("id_2") == F.col("t")).alias("known"))
    one = by_score.groupBy("id_1").agg(F.max(F.struct("score", "id_2", "ties")).alias("b"), F.max(F.when(F.col("known"), F.col("score"))).alias("printed"))
    return one.select(F.col("id_1").alias("id"), "b.id_2", F.round("b.score", 9).alias("score"), F.round("printed", 9).alias("printed"), "b.ties")


@query("external_agreement", f"{_ANSWERED} SELECT b.score IS NOT NULL AS linked, a.external IS NOT NULL AS elsewhere, count(*) AS n, round(avg(b.score), 9) AS score FROM answers a LEFT JOIN (SELECT * FROM best WHERE score > 0.7) b ON b.id_1 = a.id GROUP BY 1, 2")
def _(s, d):
    raw, gaz, scored = ref_link(s, d)
    known = gaz.select(F.col("id").alias("truth"), F.col("address").alias("found"))
    answers = raw.select("id", "truth", "status").join(known, "truth", "left").select("id", F.when(F.col("status") != "P", F.col("found")).alias("external"))
    return evaluate.agree_with_external(raw, select.best_match(scored), answers, 0.7)


# ---- rules and neighbours

_SYSTEMS = {
    "phrases": "SELECT id_1, id_2 FROM (SELECT *, row_number() OVER (PARTITION BY id_1 ORDER BY score DESC, id_2) AS r FROM scored) WHERE r = 1 AND score > 0.7",
    "rules": "SELECT id_1, min(id_2) AS id_2 FROM rules GROUP BY id_1",
    "both": "SELECT id_1, id_2 FROM (SELECT *, row_number() OVER (PARTITION BY id_1 ORDER BY score DESC, id_2) AS r FROM blended) WHERE r = 1 AND score > 0.49",
}
query("blend_metrics", f"{BLEND_SQL}, " + ", ".join(f"l_{k} AS ({v})" for k, v in _SYSTEMS.items()) + " " + " UNION ALL ".join(f"SELECT '{k}' AS system, * FROM ({PAIR_SQL.replace('FROM l)', f'FROM l_{k})').replace('FROM l JOIN', f'FROM l_{k} JOIN')})" for k in _SYSTEMS))(lambda s, d: _blend_metrics(s, d))
query("vector_neighbours", """SELECT query_id, vec_id, cosine, rank FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY cosine DESC, vec_id)::INT AS rank FROM (SELECT a.vec_id AS query_id, b.vec_id AS vec_id, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cosine FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0)) WHERE rank <= 3""")(
    lambda s, d: (lambda v: baselines.vector_neighbours(v, v.where("vec_id % 50 = 0")))(s.read.parquet(f"{d}/embeddings.parquet")))


def _blend_metrics(s, d):
    """F of the linkage, of the rules and of both, each with one link an address."""
    raw, gaz, scored = ref_link(s, d)
    rules = baselines.standardised_link(raw, gaz).withColumn("score", F.lit(1.0))
    parts = [("phrases", select.accept(select.best_match(scored), 0.7)), ("rules", select.best_match(rules)), ("both", select.accept(select.best_match(batch.blend(scored, rules, 0.7)), 0.49))]
    out = None
    for name, links in parts:
        row = evaluate.pair_metrics(links, truth_of(raw)).select(F.lit(name).alias("system"), "*")
        out = row if out is None else out.union(row)
    return out
