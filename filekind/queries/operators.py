"""One query for each family of relational operators that users of these methods run."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.text import extension, ngrams, token_rows, tokens_of, trim
from ..operators import confusion, metrics, splits, vocab
from ..plans.heavy_hitters import frequent_terms
from ..sources import corpus
from ..sources.tables import load
from . import sql
from .workloads import CORPORA, TEST, _timed, predictions, raw, task

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(oracle: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle is not None:
            ORACLES[f.__name__] = oracle
        return f

    return add


_TOK = sql.tokens("text")
_ITEMS = f"(SELECT item_id, unnest(t) AS token, (generate_subscripts(t, 1) - 1)::INT AS pos FROM (SELECT item_id, {_TOK} AS t FROM benchmark))"


@query("""SELECT origin, count(*) AS files, sum(length(content))::BIGINT AS chars FROM (
SELECT 'documents' AS origin, text AS content FROM documents UNION ALL SELECT 'pages', regexp_replace(html, '<html lang="[a-z]+"', '<html', 'g') FROM pages
UNION ALL SELECT 'conversations', text FROM conversations UNION ALL SELECT 'benchmark', text FROM benchmark) GROUP BY origin""")
def scan_corpus(spark, sf):
    parts = (corpus.prose(spark, sf), corpus.pages(spark, sf), corpus.turns(spark, sf), corpus.items(spark, sf))
    return reduce(DataFrame.unionByName, parts).groupBy("origin").agg(F.count("*").alias("files"), F.sum(F.length("content")).alias("chars"))


@query(f"SELECT doc_id, len({_TOK})::INT AS tokens FROM documents WHERE len({_TOK}) <= 20")
def filter_short(spark, sf):
    """Documents that trimming ten tokens at both ends empties."""
    t = tokens_of(F.col("text"))
    return load(spark, sf, "documents").select("doc_id", F.size(t).alias("tokens"), trim(t).alias("rest")).where(F.size("rest") == 0).drop("rest")


@query("SELECT doc_id, sha1(text) AS sha, source || '.' || lang AS filename, lang AS suffix, octet_length(encode(text)) AS bytes FROM documents")
def hash_names(spark, sf):
    name = F.concat_ws(".", "source", "lang")
    return load(spark, sf, "documents").select("doc_id", F.sha1("text").alias("sha"), name.alias("filename"), extension(name).alias("suffix"), F.octet_length("text").cast("long").alias("bytes"))


@query(f"SELECT doc_id, len(t)::INT AS tokens, len(list_distinct(t))::INT AS terms FROM (SELECT doc_id, {_TOK} AS t FROM documents)")
def tokenize_docs(spark, sf):
    d = load(spark, sf, "documents").select("doc_id", tokens_of(F.col("text")).alias("t"))
    return d.select("doc_id", F.size("t").alias("tokens"), F.size(F.array_distinct("t")).alias("terms"))


@query(f"SELECT 'b' || item_id AS file_id, pos, token FROM {_ITEMS}")
def token_positions(spark, sf):
    return token_rows(corpus.items(spark, sf))


@query(f"SELECT gram, count(*) AS n FROM (SELECT token || ' ' || lead(token) OVER (PARTITION BY item_id ORDER BY pos) AS gram FROM {_ITEMS}) WHERE gram IS NOT NULL GROUP BY gram")
def ngram_counts(spark, sf):
    b = load(spark, sf, "benchmark").select(F.explode(ngrams(tokens_of(F.col("text")), 2)).alias("gram"))
    return b.groupBy("gram").agg(F.count("*").alias("n"))


@query("SELECT doc_id, lang, quality, toxic, n_chars FROM documents JOIN labels USING (doc_id)")
def join_labels(spark, sf):
    return load(spark, sf, "documents").select("doc_id", "lang", "n_chars").join(load(spark, sf, "labels"), "doc_id").select("doc_id", "lang", "quality", "toxic", "n_chars")


@query("SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def semi_labeled(spark, sf):
    return load(spark, sf, "documents").select("doc_id", "lang").join(load(spark, sf, "labels").select("doc_id"), "doc_id", "left_semi")


@query("SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def anti_labeled(spark, sf):
    return load(spark, sf, "documents").select("doc_id", "lang").join(load(spark, sf, "labels").select("doc_id"), "doc_id", "left_anti")


@query("SELECT a.item_id, count(*) AS near FROM benchmark a JOIN benchmark b ON length(a.text) * 10 BETWEEN length(b.text) * 9 AND length(b.text) * 11 GROUP BY a.item_id")
def theta_length_pairs(spark, sf):
    """How many benchmark items are nearly as long as each. Lengths are counted first, so the theta join is between different lengths, by bins of their logarithm; it never pairs items."""
    b = load(spark, sf, "benchmark").select("item_id", F.length("text").alias("n"))
    sizes = b.groupBy("n").agg(F.count("*").alias("items")).withColumn("bin", F.floor(F.log(F.greatest("n", F.lit(1))) * 5))
    near = sizes.select(F.col("n").alias("m"), "items", F.explode(F.array(F.col("bin") - 1, F.col("bin"), F.col("bin") + 1)).alias("bin"))
    met = sizes.select("n", "bin").join(near, "bin").where((F.col("n") * 10).between(F.col("m") * 9, F.col("m") * 11)).groupBy("n").agg(F.sum("items").alias("near"))
    return b.join(met, "n").select("item_id", "near")


_BINS = [(0, 100), (100, 1_000), (1_000, 5_000), (5_000, 10_000_000)]


@query("SELECT lo, hi, count(*) AS files FROM documents JOIN (VALUES " + ", ".join(map(str, _BINS)) + ") v(lo, hi) ON n_chars >= lo AND n_chars < hi GROUP BY ALL")
def range_bins(spark, sf):
    """Histogram of sizes by a range join with a table of bins."""
    bins = F.broadcast(spark.createDataFrame(_BINS, "lo int, hi int"))
    d = load(spark, sf, "documents").select("n_chars")
    return d.join(bins, (F.col("n_chars") >= F.col("lo")) & (F.col("n_chars") < F.col("hi"))).groupBy("lo", "hi").agg(F.count("*").alias("files"))


_ARRIVAL = "SELECT doc_id, ts AS arrival FROM documents JOIN events ON event_id = doc_id"


@query(f"SELECT doc_id, arrival, (SELECT max(e.ts) FROM events e WHERE e.event_type = 'error' AND e.ts < a.arrival) AS last_error FROM ({_ARRIVAL}) a")
def asof_arrival(spark, sf):
    """The last error before each arrival: both streams in one, and the running last value. Hours split the work; an hour starts with
    the last error of the hours before."""
    e = load(spark, sf, "events")
    arrivals = load(spark, sf, "documents").select("doc_id").join(e.select(F.col("event_id").alias("doc_id"), F.col("ts").alias("at")), "doc_id").select("at", "doc_id", F.lit(None).cast("timestamp_ntz").alias("err"))
    errors = e.where("event_type = 'error'").select(F.col("ts").alias("at"), F.lit(None).cast("long").alias("doc_id"), F.col("ts").alias("err"))
    both = arrivals.unionByName(errors).withColumn("hour", F.date_trunc("hour", "at"))
    before = both.groupBy("hour").agg(F.max("err").alias("m")).withColumn("carried", F.max("m").over(Window.orderBy("hour").rowsBetween(Window.unboundedPreceding, -1)))  # a row an hour
    inside = F.max("err").over(Window.partitionBy("hour").orderBy("at").rangeBetween(Window.unboundedPreceding, Window.currentRow))
    strict = F.max(F.when(F.col("doc_id").isNull(), F.col("err"))).over(Window.partitionBy("hour").orderBy(F.col("at"), F.col("doc_id").isNull()).rowsBetween(Window.unboundedPreceding, -1))
    got = both.withColumn("seen", strict).withColumn("upto", inside).join(F.broadcast(before.select("hour", "carried")), "hour")
    # Arrivals come before errors of the same instant, so an error at the very time does not count.
    return got.where("doc_id is not null").select("doc_id", F.col("at").alias("arrival"), F.coalesce("seen", "carried").alias("last_error"))


@query(f"SELECT doc_id, count(*) AS near FROM ({_ARRIVAL}) a JOIN events e ON e.ts BETWEEN a.arrival - INTERVAL 1 HOUR AND a.arrival + INTERVAL 1 HOUR GROUP BY doc_id")
def interval_events(spark, sf):
    """Events within an hour of each arrival, by an interval join on hours."""
    e = load(spark, sf, "events").select("event_id", "ts")
    a = load(spark, sf, "documents").select("doc_id").join(e.select(F.col("event_id").alias("doc_id"), F.col("ts").alias("arrival")), "doc_id")
    hours = F.explode(F.array(*(F.date_trunc("hour", F.expr(f"arrival + INTERVAL '{h}' HOUR")) for h in (-1, 0, 1))))
    met = a.withColumn("hour", hours).join(e.select("ts", F.date_trunc("hour", "ts").alias("hour")), "hour")
    return met.where(F.expr("ts BETWEEN arrival - INTERVAL '1' HOUR AND arrival + INTERVAL '1' HOUR")).groupBy("doc_id").agg(F.count("*").alias("near"))


@query("""SELECT label, o.n AS n_old, w.n AS n_new FROM (SELECT lang || (doc_id // 200 % 7) AS label, count(*) AS n FROM documents WHERE doc_id % 2 = 0 GROUP BY 1) o
FULL JOIN (SELECT lang || (doc_id // 200 % 5) AS label, count(*) AS n FROM documents WHERE doc_id % 2 = 1 GROUP BY 1) w USING (label)""")
def outer_metrics(spark, sf):
    """Two tables of class counts side by side, with classes that either lacks."""
    d = load(spark, sf, "documents").select("doc_id", "lang")

    def counts(half: int, parts: int, name: str) -> DataFrame:
        label = F.concat("lang", (F.floor(F.col("doc_id") / 200) % parts).cast("string"))
        return d.where(F.col("doc_id") % 2 == half).groupBy(label.alias("label")).agg(F.count("*").alias(name))

    return counts(0, 7, "n_old").join(counts(1, 5, "n_new"), "label", "full_outer")


@query("""SELECT i, j, coalesce(n, 0) AS n FROM (SELECT DISTINCT lang AS i FROM documents) CROSS JOIN (SELECT DISTINCT floor(log2(n_chars + 1))::INT AS j FROM documents)
LEFT JOIN (SELECT lang AS i, floor(log2(n_chars + 1))::INT AS j, count(*) AS n FROM documents GROUP BY ALL) USING (i, j)""")
def cross_zero_fill(spark, sf):
    """A dense table of counts by language and magnitude: the product of two small sets of names, filled with zeros."""
    d = load(spark, sf, "documents").select(F.col("lang").alias("i"), F.floor(F.log2(F.col("n_chars") + 1)).cast("int").alias("j"))
    grid = d.select("i").distinct().crossJoin(F.broadcast(d.select("j").distinct()))  # languages x at most 63 magnitudes
    n = d.groupBy("i", "j").agg(F.count("*").alias("n"))
    return grid.join(n, ["i", "j"], "left").select("i", "j", F.coalesce("n", F.lit(0)).alias("n"))


@query(f"SELECT lang AS label, count(DISTINCT u) AS terms FROM (SELECT lang, unnest({_TOK}) AS u FROM documents) GROUP BY lang")
def count_distinct_terms(spark, sf):
    toks = vocab.tokens(CORPORA["T1"](spark, sf))
    return vocab.terms(toks).groupBy("label").agg(F.count_distinct("term").alias("terms"))


@query()
def approx_distinct_terms(spark, sf):
    """The same by sketch, with its relative error."""
    t = vocab.terms(vocab.tokens(CORPORA["T1"](spark, sf)))
    both = t.groupBy("label").agg(F.count_distinct("term").alias("exact"), F.approx_count_distinct("term", 0.02).alias("sketch"))
    return both.withColumn("error", F.round(F.abs(F.col("sketch") - F.col("exact")) / F.col("exact"), 6))


_SETS = f"SELECT origin, label, count(*) AS files FROM (SELECT origin, label FROM ({sql.T2})) GROUP BY "


@query(_SETS + "CUBE (origin, label)")
def cube_origin_lang(spark, sf):
    return raw(spark, sf, "T2").cube("origin", "label").agg(F.count("*").alias("files"))


@query(_SETS + "ROLLUP (origin, label)")
def rollup_origin_lang(spark, sf):
    return raw(spark, sf, "T2").rollup("origin", "label").agg(F.count("*").alias("files"))


@query(sql.query([f"c AS ({sql.T2})", f"sp AS (SELECT *, {sql.split()} AS split FROM (SELECT *, {sql.bucket('sha', 42, 100)} AS b FROM c))"],
                 "SELECT split, origin, label, count(*) AS files FROM sp GROUP BY GROUPING SETS ((split, origin), (split, label), ())"))
def grouping_sets_split(spark, sf):
    s, o, l = F.col("split"), F.col("origin"), F.col("label")
    return splits.assign(raw(spark, sf, "T2")).groupingSets([[s, o], [s, l], []], s, o, l).agg(F.count("*").alias("files"))


@query(sql.query(TEST, "SELECT label, " + ", ".join(f"count(*) FILTER (pred = '{c}') AS {c}" for c in ("de", "en", "es", "fr")) + " FROM p GROUP BY label"))
def pivot_confusion(spark, sf):
    wide = predictions(spark, sf).groupBy("label").pivot("pred", ["de", "en", "es", "fr"]).count()
    return wide.select("label", *(F.coalesce(c, F.lit(0)).alias(c) for c in ("de", "en", "es", "fr")))


@query(f"""SELECT label, n, (rank() OVER o)::INT AS rank, (dense_rank() OVER o)::INT AS dense, (row_number() OVER (ORDER BY n DESC, label))::INT AS number,
(ntile(4) OVER (ORDER BY n DESC, label))::INT AS quarter, round(percent_rank() OVER o, 6) AS percent FROM (SELECT label, count(*) AS n FROM ({sql.T2}) GROUP BY label) WINDOW o AS (ORDER BY n DESC)""")
def rank_classes(spark, sf):
    n = raw(spark, sf, "T2").groupBy("label").agg(F.count("*").alias("n"))
    by, full = Window.orderBy(F.desc("n")), Window.orderBy(F.desc("n"), "label")
    return n.select("label", "n", F.rank().over(by).alias("rank"), F.dense_rank().over(by).alias("dense"), F.row_number().over(full).alias("number"), F.ntile(4).over(full).alias("quarter"), F.round(F.percent_rank().over(by), 6).alias("percent"))


@query(f"SELECT label, n, round(sum(n) OVER (ORDER BY n DESC, label ROWS UNBOUNDED PRECEDING) / sum(n) OVER (), 6) AS share FROM (SELECT label, count(*) AS n FROM ({sql.T2}) GROUP BY label)")
def running_share(spark, sf):
    n = raw(spark, sf, "T2").groupBy("label").agg(F.count("*").alias("n"))
    return n.select("label", "n", F.round(F.sum("n").over(Window.orderBy(F.desc("n"), "label").rowsBetween(Window.unboundedPreceding, 0)) / F.sum("n").over(Window.partitionBy()), 6).alias("share"))


_TIMED = sql.chain(sql.P6, scored="split IN ('val', 'test')")


@query(sql.query(_TIMED, "SELECT file_id, round(avg((p.label = pred)::INT) OVER (PARTITION BY date_trunc('day', arrival) ORDER BY arrival, file_id ROWS BETWEEN 19 PRECEDING AND CURRENT ROW), 6) AS accuracy FROM p JOIN c USING (file_id)"))
def moving_accuracy(spark, sf):
    """Accuracy over the last twenty arrivals of a day."""
    by = Window.partitionBy(F.date_trunc("day", "arrival")).orderBy("arrival", "file_id").rowsBetween(-19, 0)
    return _timed(spark, sf).select("file_id", F.round(F.avg((F.col("label") == F.col("pred")).cast("double")).over(by), 6).alias("accuracy"))


@query(sql.query(_TIMED, "SELECT day, n, n - lag(n) OVER (ORDER BY day) AS change FROM (SELECT date_trunc('day', arrival)::DATE AS day, count(*) AS n FROM p JOIN c USING (file_id) GROUP BY 1)"))
def lag_drift(spark, sf):
    w = _timed(spark, sf).groupBy(F.to_date("arrival").alias("day")).agg(F.count("*").alias("n"))
    return w.select("day", "n", (F.col("n") - F.lag("n").over(Window.orderBy("day"))).alias("change"))


@query(f"""SELECT label, term, n FROM (SELECT lang AS label, u AS term, count(*) AS n FROM (SELECT lang, unnest({_TOK}) AS u FROM documents) GROUP BY ALL)
QUALIFY row_number() OVER (PARTITION BY label ORDER BY n DESC, term) <= 10""")
def topk_terms_per_class(spark, sf):
    n = vocab.class_term_freq(vocab.tokens(CORPORA["T1"](spark, sf)))
    return n.withColumn("k", F.row_number().over(Window.partitionBy("label").orderBy(F.desc("n"), "term"))).where("k <= 10").select("label", "term", "n")


@query(f"SELECT u AS term, count(*) AS n FROM (SELECT unnest({_TOK}) AS u FROM documents) GROUP BY u ORDER BY n DESC, term LIMIT 25")
def global_topk(spark, sf):
    t = vocab.terms(vocab.tokens(CORPORA["T1"](spark, sf)))
    return t.groupBy("term").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "term").limit(25)


def _half_sql(k: int) -> str:
    return f"""SELECT DISTINCT term FROM (SELECT label, term, count(*) AS n FROM h WHERE half = {k} GROUP BY ALL) JOIN (SELECT label, count(*) AS total FROM h WHERE half = {k} GROUP BY ALL) USING (label) WHERE n * 100 > total"""


def _halves(spark, sf):
    t1 = CORPORA["T1"](spark, sf).withColumn("half", F.substring("file_id", 2, 20).cast("long") % 2)
    return [vocab.build(vocab.tokens(t1.where(F.col("half") == k))).select("term") for k in (0, 1)]


for _name, _word, _how in (("vocab_union", "UNION", lambda a, b: a.union(b).distinct()), ("vocab_intersect", "INTERSECT", DataFrame.intersect), ("vocab_except", "EXCEPT", DataFrame.subtract)):
    QUERIES[_name] = lambda spark, sf, how=_how: how(*_halves(spark, sf))
    ORACLES[_name] = f"WITH h AS (SELECT doc_id % 2 AS half, lang AS label, unnest({_TOK}) AS term FROM documents) {_half_sql(0)} {_word} {_half_sql(1)}"


def _render_query(name: str, table: str) -> None:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        return corpus.rendered(spark, sf, table).select("file_id", "label", "sha")

    QUERIES[name] = run
    ORACLES[name] = f"SELECT file_id, label, sha FROM ({sql.T2}) WHERE origin = '{table}'"


for _name, _table in (("render_json", "events"), ("render_csv", "orders"), ("render_tsv", "customer"), ("render_ini", "supplier"), ("render_tbl", "lineitem"), ("render_xml", "part"), ("render_vec", "embeddings")):
    _render_query(_name, _table)


@query("SELECT event_id, (props->>'k')::BIGINT AS k, array_to_string(json_keys(props), '|') AS names FROM events")
def parse_props(spark, sf):
    """A field of the JSON column, and the names it has."""
    e = load(spark, sf, "events")
    return e.select("event_id", F.from_json("props", "k long")["k"].alias("k"), F.array_join(F.json_object_keys("props"), "|").alias("names"))


@query("SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 6) AS norm, len(embedding)::INT AS size FROM embeddings")
def embedding_norms(spark, sf):
    square = F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    return load(spark, sf, "embeddings").select("vec_id", F.round(F.sqrt(square), 6).alias("norm"), F.size("embedding").alias("size"))


@query("""SELECT 'orders' AS origin, year(o_orderdate)::INT AS year, month(o_orderdate)::INT AS month, count(*) AS n FROM orders GROUP BY ALL
UNION ALL SELECT 'lineitem', year(l_shipdate)::INT, month(l_shipdate)::INT, count(*) FROM lineitem GROUP BY ALL""")
def date_buckets(spark, sf):
    parts = [load(spark, sf, t).groupBy(F.lit(t).alias("origin"), F.year(c).alias("year"), F.month(c).alias("month")).agg(F.count("*").alias("n")) for t, c in (("orders", "o_orderdate"), ("lineitem", "l_shipdate"))]
    return parts[0].unionByName(parts[1])


@query("SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def tumbling_events(spark, sf):
    return load(spark, sf, "events").groupBy(F.window("ts", "6 hours").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


@query("SELECT b - INTERVAL (3 * k) HOUR AS start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 3 HOUR, ts, TIMESTAMP '1970-01-01') AS b FROM events), range(2) r(k) GROUP BY 1")
def sliding_events(spark, sf):
    return load(spark, sf, "events").groupBy(F.window("ts", "6 hours", "3 hours").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS new FROM events),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def session_events(spark, sf):
    return load(spark, sf, "events").groupBy("user_id", F.session_window("ts", "12 hours").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


@query(f"""SELECT label, term, n, total FROM (SELECT label, term, count(*) AS n FROM (SELECT lang AS label, unnest({_TOK}) AS term FROM documents) GROUP BY ALL)
JOIN (SELECT lang AS label, sum(len({_TOK}))::BIGINT AS total FROM documents GROUP BY lang) USING (label) WHERE n * 100 > total""")
def heavy_hitters_exact(spark, sf):
    """Frequent tokens of each class by summaries and an exact recount."""
    return frequent_terms(vocab.terms(vocab.tokens(CORPORA["T1"](spark, sf))), vocab.TAU[1])


@query(sql.query(TEST, "SELECT least(floor(p * 10), 9)::INT AS bin, count(*) AS n, round(avg(p), 6) AS mean_p, round(avg((label = pred)::INT), 6) AS accuracy FROM p GROUP BY 1"))
def calibration_bins(spark, sf):
    return metrics.calibration(predictions(spark, sf)).select("bin", "n", F.round("mean_p", 6).alias("mean_p"), F.round("accuracy", 6).alias("accuracy"))


@query(sql.query(sql.chain(sql.T2C, scored="split = 'val'"), "SELECT file_id, label, pred, round(p, 6) AS p FROM p"))
def nb_predictions(spark, sf):
    """Naive Bayes on the T2 validation files."""
    return predictions(spark, sf, "T2c", "val").select("file_id", "label", "pred", F.round("p", 6).alias("p"))


@query(sql.query([*sql.chain(sql.T2C, scored="split = 'val'"), *sql.t_s()], "SELECT file_id, class, round(share, 6) AS share FROM tp"))
def top_five(spark, sf):
    """The five likeliest classes of each validation file, renormalised."""
    return confusion.top_k(predictions(spark, sf, "T2c", "val")).select("file_id", F.explode("top").alias("x")).select("file_id", "x.class", F.round("x.q", 6).alias("share"))


@query(f"SELECT item_id, (pos)::INT AS pos, token || ' ' || nxt AS ngram FROM (SELECT *, lead(token) OVER (PARTITION BY item_id ORDER BY pos) AS nxt FROM {_ITEMS}) WHERE nxt IS NOT NULL")
def udtf_ngrams(spark, sf):
    """Bigrams by the SQL table function."""
    from .. import sqlapi

    sqlapi.register(spark)
    load(spark, sf, "benchmark").createOrReplaceTempView("fk_items")
    return spark.sql("SELECT item_id, g.pos, g.ngram FROM (SELECT item_id, fk_tokens(text) AS t FROM fk_items), LATERAL fk_ngram_rows(t, 2) g")


@query(f"SELECT item_id, len(t)::INT AS tokens, t[1] AS head, round(length(regexp_replace(text, '[\\x20-\\x7e\\t\\n\\r]', '', 'g')) / length(text), 6) AS odd FROM (SELECT item_id, text, {_TOK} AS t FROM benchmark)")
def sql_tokens(spark, sf):
    """The SQL functions, inlined by the analyzer."""
    from .. import sqlapi

    sqlapi.register(spark)
    load(spark, sf, "benchmark").createOrReplaceTempView("fk_items")
    return spark.sql("SELECT item_id, size(fk_tokens(text)) AS tokens, try_element_at(fk_tokens(text), 1) AS head, round(fk_nonprintable(text), 6) AS odd FROM fk_items")


@query(f"""SELECT file_id || '#' || k AS file_id, label, content FROM (SELECT file_id, label, unnest(xs) AS content, generate_subscripts(xs, 1) - 1 AS k FROM (
SELECT file_id, label, regexp_extract_all(content, '(?s)<script[^>]*>(.*?)</script>', 1) AS xs FROM ({sql.T2}) WHERE origin = 'pages'))""")
def embedded_scripts(spark, sf):
    """Script fragments inside pages as files of their own."""
    from ..operators.score import embedded

    return embedded(corpus.pages(spark, sf))
