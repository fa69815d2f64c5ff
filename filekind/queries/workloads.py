"""The experiment workloads over the given tables, as queries with the SQL that checks them."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import balance, baselines, confusion, drift, metrics, nb, prep, score, splits, vocab
from ..functions.text import bucket, tokens_of
from ..operators.features import Config, Space, learn_space, vectorize_sql
from ..sources import corpus
from ..store import keep, once
from . import sql

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(oracle: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle is not None:
            ORACLES[f.__name__] = oracle
        return f

    return add


def rounded(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in columns})


# --- corpora and models that several queries share -----------------------------------------------------------------

CORPORA = {"T1": corpus.prose, "T2": corpus.mixed, "T2c": corpus.mixed, "T3": lambda s, sf: corpus.prose(s, sf, "source"), "T4": lambda s, sf: corpus.judged(s, sf, "quality"), "T5": lambda s, sf: corpus.judged(s, sf, "toxic"), "T6": corpus.dated}
_MODELS: dict = {}


#: Preparation of each corpus; T2c is T2 without kinds that have less than one file in a hundred.
PREPARED = {"T2c": prep.Config(min_freq=(1, 100))}


def raw(spark: SparkSession, sf: str, name: str) -> DataFrame:
    """A corpus as it comes, written once."""
    return once(spark, ("raw", sf, "T2" if name == "T2c" else name), lambda: CORPORA[name](spark, sf))


def task(spark: SparkSession, sf: str, name: str) -> DataFrame:
    """A prepared corpus with its splits, written once."""
    return once(spark, ("task", sf, name), lambda: splits.assign(prep.prepare(raw(spark, sf, name), PREPARED.get(name, prep.Config()))))


def training(df: DataFrame, balanced: bool = True) -> DataFrame:
    """The vocab and train splits, each cut to its smallest class."""
    rows = df.where(F.col("split").isin("vocab", "train"))
    return balance.undersample(rows, within=("split",)) if balanced else rows


def tokenized(train: DataFrame, unit: str = "codepoint") -> DataFrame:
    """A training set as tokens, written once: vocabularies of all orders and the classifier read these."""
    return keep(train.select("file_id", "label", "split", tokens_of(F.col("content"), unit).alias("tokens")))


def learned(train: DataFrame, cfg: Config = Config(), holdout: str = "vocab") -> tuple[Space, score.Linear]:
    """The space from the holdout and naive Bayes from the train split."""
    train = train if "tokens" in train.columns else tokenized(train, cfg.unit)
    space = learn_space(train.where(F.col("split") == holdout), cfg)
    return space, nb.fit(train.where("split = 'train'"), space)


def model(spark: SparkSession, sf: str, name: str = "T1") -> tuple[Space, score.Linear]:
    key = (spark.sparkContext.applicationId, sf, name)
    if key not in _MODELS:
        _MODELS[key] = learned(training(task(spark, sf, name)))
    return _MODELS[key]


def predictions(spark: SparkSession, sf: str, name: str = "T1", split: str = "test") -> DataFrame:
    space, m = model(spark, sf, name)
    return once(spark, ("pred", sf, name, split), lambda: score.predict(task(spark, sf, name).where(F.col("split") == split), m, space, keep=("file_id", "label", "origin")))


VAL = sql.chain(sql.P1, scored="split = 'val'")
TEST = sql.chain(sql.P1)
VAL2 = sql.chain(sql.T2C, scored="split = 'val'")
TEST2 = sql.chain(sql.T2C)

# --- preparation -----------------------------------------------------------------------------------------------------

_FUNNEL = f"""WITH c AS ({{corpus}}), d AS (SELECT * FROM c QUALIFY row_number() OVER (PARTITION BY sha, label ORDER BY file_id) = 1),
fq AS (SELECT * FROM d WHERE label IN (SELECT label FROM d GROUP BY label HAVING count(*) * {{den}} >= (SELECT count(*) FROM d) * {{num}})),
tx AS (SELECT * FROM fq WHERE coalesce(length(regexp_replace(content, '[\\x20-\\x7e\\t\\n\\r]', '', 'g')) / nullif(length(content), 0), 0) <= 0.2),
un AS (SELECT * FROM tx WHERE sha NOT IN (SELECT sha FROM tx GROUP BY sha HAVING count(DISTINCT label) > 1))
SELECT 0 AS step, 'raw' AS name, count(*) AS files, count(DISTINCT label) AS classes, '{{t}}' AS task FROM c UNION ALL SELECT 1, 'distinct', count(*), count(DISTINCT label), '{{t}}' FROM d
UNION ALL SELECT 2, 'frequent', count(*), count(DISTINCT label), '{{t}}' FROM fq UNION ALL SELECT 3, 'textual', count(*), count(DISTINCT label), '{{t}}' FROM tx
UNION ALL SELECT 4, 'unambiguous', count(*), count(DISTINCT label), '{{t}}' FROM un"""


@query("SELECT * FROM (" + _FUNNEL.format(corpus=sql.T3, num=1, den=10_000, t="T3") + ") UNION ALL SELECT * FROM (" + _FUNNEL.format(corpus=sql.T2, num=1, den=100, t="T2") + ")")
def prep_funnel(spark, sf):
    """Files and classes left after each step of the preparation (T3, and T2 with a cut of one in a hundred)."""
    parts = [prep.funnel(raw(spark, sf, t), prep.Config(min_freq=cut)).withColumn("task", F.lit(t)) for t, cut in (("T3", (1, 10_000)), ("T2", (1, 100)))]
    return reduce(DataFrame.unionByName, parts)


def _distribution(corpus_sql: str, name: str) -> str:
    return f"""SELECT '{name}' AS task, label, n, round(n / sum(n) OVER (), 6) AS share, (row_number() OVER o)::INT AS rank, round(sum(n) OVER (ORDER BY n DESC, label ROWS UNBOUNDED PRECEDING) / sum(n) OVER (), 6) AS cum_share
FROM (SELECT label, count(*) AS n FROM ({corpus_sql}) GROUP BY label) WINDOW o AS (ORDER BY n DESC, label)"""


@query(" UNION ALL ".join(f"SELECT * FROM ({_distribution(c, t)})" for t, c in (("T1", sql.T1), ("T2", sql.T2), ("T3", sql.T3))))
def class_distribution(spark, sf):
    """Files per class with rank and running share."""
    parts = [rounded(prep.class_distribution(CORPORA[t](spark, sf)), "share", "cum_share").withColumn("task", F.lit(t)) for t in ("T1", "T2", "T3")]
    return reduce(DataFrame.unionByName, parts)


@query(f"WITH c AS ({sql.T2}) SELECT label, count(*) AS files FROM c GROUP BY label HAVING count(*) * 100 >= (SELECT count(*) FROM c)")
def rare_class_cut(spark, sf):
    """Classes of T2 with at least one file in a hundred."""
    return prep.drop_rare(CORPORA["T2"](spark, sf), (1, 100)).groupBy("label").agg(F.count("*").alias("files"))


_T8 = """SELECT 'd' || doc_id AS file_id, lang AS label, encode(text) AS b, octet_length(encode(regexp_replace(text, '[\\x20-\\x7e\\t\\n\\r]', '', 'g'))) AS odd FROM documents
UNION ALL SELECT 'x' || doc_id, 'blob', blob, len(list_filter(range(1, octet_length(blob) * 2, 2), lambda i: NOT (substr(hex(blob), i, 2) BETWEEN '20' AND '7E' OR substr(hex(blob), i, 2) IN ('09', '0A', '0D'))))
FROM (SELECT doc_id, unhex(string_agg(sha256(doc_id || ':' || k), '' ORDER BY k)) AS blob FROM documents, range(8) r(k) WHERE doc_id % 20 = 0 GROUP BY doc_id)"""


@query(f"SELECT file_id, label, round(odd / octet_length(b), 6) AS ratio FROM ({_T8}) WHERE odd / octet_length(b) <= 0.2")
def textual_filter(spark, sf):
    """Files of T8 whose bytes are at most one fifth non-printable."""
    ratio = prep.nonprintable_ratio(F.col("content_bytes"), binary=True)
    return rounded(prep.keep_textual(corpus.injected(spark, sf), content="content_bytes", binary=True).select("file_id", "label", ratio.alias("ratio")), "ratio")


@query(f"""WITH f AS (SELECT *, odd / octet_length(b) AS ratio FROM ({_T8})) SELECT label, count(*) AS files FROM f WHERE label NOT IN (
SELECT label FROM f WHERE {sql.bucket("file_id", "binary42", 100)} < 50 GROUP BY label HAVING avg(ratio) > 0.2) GROUP BY label""")
def textual_class_filter(spark, sf):
    """Classes of T8 that a half sample does not show to be binary."""
    return prep.keep_textual(corpus.injected(spark, sf), scope="class_sample", content="content_bytes", binary=True, sample=50).groupBy("label").agg(F.count("*").alias("files"))


@query(f"WITH c AS ({sql.T3}) SELECT sha, string_agg(DISTINCT label, '|' ORDER BY label) AS labels, count(*) AS files FROM c GROUP BY sha HAVING count(DISTINCT label) > 1")
def ambiguous_labels(spark, sf):
    """Contents of T3 that occur under several labels."""
    t3 = CORPORA["T3"](spark, sf)
    bad = t3.join(prep.ambiguous(t3), "sha", "left_semi")
    sets = prep.label_sets(bad).select("sha", F.array_join("labels", "|").alias("labels"))
    return sets.join(bad.groupBy("sha").agg(F.count("*").alias("files")), "sha")


@query(sql.query(sql.chain(sql.P1)[:4], "SELECT split, label, file_id FROM ba"))
def undersample(spark, sf):
    """The balanced vocab and train sets of T1."""
    return training(task(spark, sf, "T1")).select("split", "label", "file_id")


@query(sql.query([f"c AS ({sql.P1})", f"sp AS (SELECT *, {sql.split()} AS split FROM (SELECT *, {sql.bucket('sha', 42, 100)} AS b FROM c))"],
                 "SELECT split, label, count(*) AS files, round(count(*) / sum(count(*)) OVER (PARTITION BY split), 6) AS share FROM sp GROUP BY split, label"))
def split_shares(spark, sf):
    """Class shares in each split of T1."""
    from pyspark.sql import Window

    n = task(spark, sf, "T1").groupBy("split", "label").agg(F.count("*").alias("files"))
    return n.withColumn("share", F.round(F.col("files") / F.sum("files").over(Window.partitionBy("split")), 6))


# --- vocabularies and vectors ------------------------------------------------------------------------------------------

WHOLE = [f"c AS ({sql.T1})", f"hv AS (SELECT file_id, label, {sql.tokens('content')} AS t FROM c)", "u1 AS (SELECT label, unnest(t) AS term FROM hv)"]


def _vocabulary(grams: str, totals: str, tau: tuple[int, int], n: int) -> str:
    return f"""SELECT (row_number() OVER (ORDER BY term))::INT AS term_id, {n} AS n, term, round(max(n0 / total), 6) AS max_share, count(*) AS n_classes
FROM (SELECT label, term, count(*) AS n0 FROM {grams} GROUP BY ALL) JOIN ({totals}) USING (label) WHERE n0 * {tau[1]} > total * {tau[0]} GROUP BY term"""


_TOT = "SELECT label, sum(greatest(len(t) - {k}, 0)) AS total FROM hv GROUP BY label"
_V1 = f"v1 AS (SELECT DISTINCT term FROM ({_vocabulary('u1', _TOT.format(k=0), (1, 100), 1)}))"
_MAPPED = """g AS (SELECT file_id, label, tok, lead(tok, 1) OVER w AS t2, lead(tok, 2) OVER w AS t3 FROM (
  SELECT x.file_id, x.label, pos, coalesce(v.term, '<unk>') AS tok FROM (SELECT file_id, label, unnest(t) AS raw, generate_subscripts(t, 1) AS pos FROM hv) x LEFT JOIN v1 v ON x.raw = v.term)
  WINDOW w AS (PARTITION BY file_id ORDER BY pos))"""


@query(sql.query(WHOLE, _vocabulary("u1", _TOT.format(k=0), (1, 100), 1)))
def vocab_unigram(spark, sf):
    """V of T1: tokens over one in a hundred of any class."""
    return rounded(vocab.build(vocab.tokens(CORPORA["T1"](spark, sf))), "max_share")


def _higher(spark, sf, n: int) -> DataFrame:
    toks = vocab.tokens(CORPORA["T1"](spark, sf))
    return rounded(vocab.build(toks, n, vocab.as_list(vocab.build(toks))), "max_share")


@query(sql.query([*WHOLE, _V1, _MAPPED, "u2 AS (SELECT label, tok || ' ' || t2 AS term FROM g WHERE t2 IS NOT NULL)"], _vocabulary("u2", _TOT.format(k=1), (1, 1000), 2)))
def vocab_bigram(spark, sf):
    """V2 of T1: bigrams over V above one in a thousand of any class."""
    return _higher(spark, sf, 2)


@query(sql.query([*WHOLE, _V1, _MAPPED, "u3 AS (SELECT label, tok || ' ' || t2 || ' ' || t3 AS term FROM g WHERE t3 IS NOT NULL)"], _vocabulary("u3", _TOT.format(k=2), (1, 1000), 3)))
def vocab_trigram(spark, sf):
    """V3 of T1."""
    return _higher(spark, sf, 3)


@query(sql.query(WHOLE, f"""SELECT term FROM ({_vocabulary("u1", _TOT.format(k=0), (1, 100), 1)}) EXCEPT SELECT term FROM u1 GROUP BY term HAVING count(*) * 100 > (SELECT count(*) FROM u1)"""))
def vocab_global_gap(spark, sf):
    """Tokens that a threshold per class keeps and one over the whole corpus loses."""
    toks = vocab.tokens(CORPORA["T1"](spark, sf))
    return vocab.build(toks).select("term").exceptAll(vocab.build(toks, combine="global").select("term"))


@query(sql.query(TEST, "SELECT file_id, label, idx, round(freq, 6) AS freq FROM fr JOIN s USING (n, term)"))
def feature_rows(spark, sf):
    """Vectors of the T1 test files in long form."""
    space, _ = model(spark, sf)
    return rounded(vectorize_sql(task(spark, sf, "T1").where("split = 'test'"), space), "freq")


@query(sql.query(TEST, "SELECT file_id, round(sum(CASE WHEN n = 1 THEN freq END), 6) AS unigrams, round(coalesce(sum(CASE WHEN n = 2 THEN freq END), 0), 6) AS bigrams, round(sqrt(sum(freq * freq)), 6) AS norm, count(*) AS parts FROM fr GROUP BY file_id"))
def feature_norms(spark, sf):
    """Mass of each order, length and number of parts of each test vector."""
    space, _ = model(spark, sf)
    first = len(space.terms[1])
    v = vectorize_sql(task(spark, sf, "T1").where("split = 'test'"), space)
    mass = [F.coalesce(F.sum(F.when(t, F.col("freq"))), F.lit(0.0)) for t in (F.col("idx") <= first, F.col("idx") > first)]
    return rounded(v.groupBy("file_id").agg(mass[0].alias("unigrams"), mass[1].alias("bigrams"), F.sqrt(F.sum(F.col("freq") * F.col("freq"))).alias("norm"), F.count("*").alias("parts")), "unigrams", "bigrams", "norm")


@query(sql.query([*WHOLE, _V1], "SELECT term AS token, count(*) AS n, round(count(*) / (SELECT count(*) FROM u1), 6) AS share FROM u1 WHERE term IN (FROM v1) AND regexp_full_match(term, '\\w+') GROUP BY term ORDER BY n DESC, token LIMIT 50"))
def token_cloud(spark, sf):
    """The fifty most frequent vocabulary tokens without punctuation."""
    toks = vocab.tokens(CORPORA["T1"](spark, sf))
    return rounded(vocab.cloud(toks, vocab.as_list(vocab.build(toks)), 50), "share")


# --- confusion and accuracy of naive Bayes -----------------------------------------------------------------------------

@query(sql.query([*VAL, *sql.t_s()], "SELECT i, j, round(t, 6) AS t FROM tm"))
def confusion_t(spark, sf):
    return rounded(confusion.t_matrix(predictions(spark, sf, split="val")), "t")


@query(sql.query([*VAL, *sql.t_s()], "SELECT i, j, round(s, 6) AS s FROM sm"))
def confusion_s(spark, sf):
    return rounded(confusion.s_matrix(predictions(spark, sf, split="val")), "s")


_DIRECTED = """dr AS (SELECT i, j, coalesce(t, 0) AS t, coalesce(s, 0) AS s, coalesce(round(t, 12) > 0.05, false) AS by_t, coalesce(round(s, 12) > 0.02, false) AS by_s FROM tm FULL JOIN sm USING (i, j) WHERE i <> j),
dd AS (SELECT * FROM dr WHERE by_t OR by_s)"""
_RELATED = """SELECT least(i, j) AS a, greatest(i, j) AS b, round(max(t), 6) AS t_max, round(max(s), 6) AS s_max,
CASE WHEN bool_or(by_t) AND bool_or(by_s) THEN 'both' WHEN bool_or(by_t) THEN 't' ELSE 's' END AS via FROM dd GROUP BY ALL"""


def _named_groups(groups: DataFrame) -> DataFrame:
    return groups.withColumn("members", F.array_join("members", "|"))


def _matrices(spark, sf, name="T2c"):
    pred = predictions(spark, sf, name, "val")
    return confusion.t_matrix(pred), confusion.s_matrix(pred)


@query(sql.query([*VAL2, *sql.t_s(), _DIRECTED], _RELATED))
def related_pairs(spark, sf):
    """Pairs of file kinds (T2) that the classifier confuses."""
    return rounded(confusion.related(*_matrices(spark, sf)), "t_max", "s_max")


@query("WITH RECURSIVE " + ",\n".join([*VAL2, *sql.t_s(), _DIRECTED, "ed AS (SELECT i AS x, j AS y FROM dd UNION SELECT j, i FROM dd)", "re(x, y) AS (SELECT x, y FROM ed UNION SELECT re.x, ed.y FROM re JOIN ed ON re.y = ed.x)"])
       + "\nSELECT (row_number() OVER (ORDER BY members) - 1)::INT AS group_id, array_to_string(members, '|') AS members, 'components' AS builder FROM (SELECT DISTINCT list_sort(list_distinct(list(y))) AS members FROM re GROUP BY x)")
def confusion_groups(spark, sf):
    """Groups of kinds joined by related pairs."""
    return _named_groups(confusion.groups(*_matrices(spark, sf)))


@query(sql.query([*VAL2, *sql.t_s(), _DIRECTED], "SELECT (row_number() OVER (ORDER BY members) - 1)::INT AS group_id, array_to_string(members, '|') AS members, 'stars' AS builder FROM (SELECT DISTINCT list_sort(list_append(list(j), i)) AS members FROM dd GROUP BY i)"))
def confusion_stars(spark, sf):
    return _named_groups(confusion.groups(*_matrices(spark, sf), builder="stars"))


def _reach(tag: str, pairs: str) -> list[str]:
    """g{tag}: the members of each component of the pairs (i, j)."""
    return [f"e{tag}(x, y) AS (SELECT i, j FROM ({pairs}) UNION SELECT j, i FROM ({pairs}))", f"r{tag}(x, y) AS (SELECT x, y FROM e{tag} UNION SELECT r{tag}.x, e{tag}.y FROM r{tag} JOIN e{tag} ON r{tag}.y = e{tag}.x)",
            f"g{tag} AS (SELECT DISTINCT list_sort(list_distinct(list(y))) AS members FROM r{tag} GROUP BY x)"]


_BUILT = [
    *_reach("mu", "SELECT a.i, a.j FROM dd a JOIN dd b ON a.i = b.j AND a.j = b.i"), *_reach("pt", "SELECT i, j FROM dr WHERE by_t"), *_reach("ps", "SELECT i, j FROM dr WHERE by_s"),
    "nb AS (SELECT x, list(y) AS ys FROM (SELECT i AS x, j AS y FROM dd UNION SELECT j, i FROM dd) GROUP BY x)",
    "cq(m) AS (SELECT DISTINCT [least(i, j), greatest(i, j)] FROM dd UNION SELECT list_append(m, x) FROM cq JOIN nb ON x > m[len(m)] AND list_has_all(ys, m))",
]


@query("WITH RECURSIVE " + ",\n".join([*VAL2, *sql.t_s(), _DIRECTED, *_BUILT]) + """
SELECT (row_number() OVER (PARTITION BY builder ORDER BY members) - 1)::INT AS group_id, array_to_string(members, '|') AS members, builder FROM (
SELECT m AS members, 'cliques' AS builder FROM cq WHERE NOT EXISTS (SELECT 1 FROM nb WHERE list_has_all(ys, m)) UNION ALL SELECT members, 'mutual' FROM gmu
UNION ALL SELECT members, 'per_statistic' FROM (SELECT members FROM gpt UNION SELECT members FROM gps))""")
def confusion_cliques(spark, sf):
    """The other three ways to build groups."""
    t, s = _matrices(spark, sf)
    return _named_groups(reduce(DataFrame.unionByName, (confusion.groups(t, s, b) for b in ("cliques", "mutual", "per_statistic"))))


@query(sql.query([*VAL2, *sql.t_s(), _DIRECTED], f"SELECT DISTINCT label FROM c WHERE label NOT IN (SELECT i FROM dd UNION SELECT j FROM dd)"))
def clean_classes(spark, sf):
    """Kinds in no related pair."""
    return confusion.clean_classes(task(spark, sf, "T2c"), confusion.related(*_matrices(spark, sf)))


@query(sql.query(TEST, "SELECT i, j, coalesce(n, 0) AS n FROM (SELECT DISTINCT label AS i FROM c) CROSS JOIN (SELECT DISTINCT label AS j FROM c) LEFT JOIN (SELECT label AS i, pred AS j, count(*) AS n FROM p GROUP BY ALL) USING (i, j)"))
def confusion_matrix(spark, sf):
    return metrics.confusion(predictions(spark, sf), task(spark, sf, "T1"))


_PRF = ['"precision"', "recall", "f1"]


@query(sql.query(TEST2, sql.rounded(sql.per_class("p"), _PRF, ["label", "support", "tp", "fp", "fn"])))
def per_class_prf(spark, sf):
    """Precision, recall and F of each kind (T2 test files)."""
    return rounded(metrics.per_class(metrics.confusion(predictions(spark, sf, "T2c"))), "precision", "recall", "f1")


@query(sql.query([*TEST2, f"m AS ({sql.per_class('p')})"], sql.rounded(sql.averages("m"), _PRF, ["kind"])))
def avg_micro_macro(spark, sf):
    return rounded(metrics.averages(metrics.per_class(metrics.confusion(predictions(spark, sf, "T2c")))), "precision", "recall", "f1")


@query(sql.query(TEST2, """SELECT 'T2' AS task, sum(n)::BIGINT AS files, round(sum(hits) / sum(n), 6) AS accuracy, round(avg(hits / n), 6) AS class_accuracy FROM (SELECT label, count(*) AS n, sum((label = pred)::INT) AS hits FROM p GROUP BY label)"""))
def accuracy(spark, sf):
    return rounded(metrics.accuracy(predictions(spark, sf, "T2c")).select(F.lit("T2").alias("task"), "*"), "accuracy", "class_accuracy")


def _snapshots(spark, sf) -> tuple[DataFrame, DataFrame]:
    """T6 before and after the middle of its time, each prepared and split by itself."""
    t6 = raw(spark, sf, "T6")
    us = F.unix_micros(F.col("arrival").cast("timestamp"))
    lo, hi = t6.agg(F.min(us), F.max(us)).first()
    cut = (lo + hi) // 2 if lo is not None else 0
    return tuple(once(spark, ("snapshot", sf, name), lambda t=test: splits.assign(prep.prepare(t6.where(t)))) for name, test in (("old", us < cut), ("new", us >= cut)))


def _aged(spark, sf) -> tuple[DataFrame, DataFrame]:
    old, new = _snapshots(spark, sf)

    def make():
        space, m = learned(training(old))
        before = score.predict(old.where("split = 'test'"), m, space).withColumn("part", F.lit("old"))
        return before.unionByName(score.predict(splits.later_snapshot(old, new), m, space).withColumn("part", F.lit("new")))

    pred = once(spark, ("aged", sf), make)
    return pred.where("part = 'old'"), pred.where("part = 'new'")


_LATE = "NOT old AND sha NOT IN (SELECT sha FROM ca WHERE old) AND label IN (SELECT label FROM ca WHERE old)"
_AGED = [*sql.chain(sql.SNAPSHOTS, "a", learn="old", scored=f"(split = 'test' AND old) OR ({_LATE})"),
         "po AS (SELECT p.* FROM pa p JOIN spa USING (file_id) WHERE old)", "pn AS (SELECT p.* FROM pa p JOIN spa USING (file_id) WHERE NOT old)",
         f"mo AS ({sql.per_class('po')})", f"mn AS ({sql.per_class('pn')})"]


@query(sql.query(_AGED, """SELECT label, CASE WHEN coalesce(n.support, 0) = 0 THEN 'vanished' WHEN coalesce(o.support, 0) = 0 THEN 'new' ELSE 'both' END AS status,
o.support AS support_old, n.support AS support_new, round(n.recall - o.recall, 6) AS recall_delta, round(n."precision" - o."precision", 6) AS precision_delta, round(n.f1 - o.f1, 6) AS f1_delta FROM mo o FULL JOIN mn n USING (label)"""))
def ageing_delta(spark, sf):
    """T6: class measures on unseen later files against those on old test files."""
    old, new = (metrics.per_class(metrics.confusion(p)) for p in _aged(spark, sf))
    return rounded(drift.compare(old, new).select("label", "status", "support_old", "support_new", "recall_delta", "precision_delta", "f1_delta"), "recall_delta", "precision_delta", "f1_delta")


_MISS = "SELECT label FROM c WHERE o EXCEPT SELECT label FROM c WHERE NOT o AND sha NOT IN (SELECT sha FROM c WHERE o)"
_KIND = "o_orderpriority || strftime(o_orderdate, '%m%d')"


@query(f"WITH c AS (SELECT epoch_us(o_orderdate) < (SELECT (min(epoch_us(o_orderdate)) + max(epoch_us(o_orderdate))) // 2 FROM orders) AS o, {_KIND} AS label, sha1({_KIND} || o_custkey) AS sha FROM orders) {_MISS}")
def missing_classes(spark, sf):
    """Classes (order priority and day of the year) that the later half of all orders lacks once contents seen before are gone."""
    from ..sources.tables import load

    kind = F.concat("o_orderpriority", F.date_format("o_orderdate", "MMdd"))
    us = F.unix_micros(F.col("o_orderdate").cast("timestamp"))
    o = load(spark, sf, "orders").select(kind.alias("label"), F.sha1(F.concat(kind, F.col("o_custkey").cast("string"))).alias("sha"), us.alias("us"))
    lo, hi = o.agg(F.min("us"), F.max("us")).first()
    return splits.missing_classes(o.where(F.col("us") < (lo + hi) // 2), o.where(F.col("us") >= (lo + hi) // 2))


# --- ablations, baselines and extensions ----------------------------------------------------------------------------------

def _measured(pred: DataFrame, name: str) -> DataFrame:
    m = metrics.per_class(metrics.confusion(pred))
    return metrics.accuracy(pred).crossJoin(F.broadcast(metrics.macro(m).select(F.col("recall").alias("macro_recall"), F.col("f1").alias("macro_f1")))).select(F.lit(name).alias("variant"), "files", "accuracy", "macro_recall", "macro_f1")


def _measured_sql(pred: str, name: str) -> str:
    return f"""SELECT '{name}' AS variant, (SELECT count(*) FROM {pred}) AS files, round((SELECT avg((label = pred)::INT) FROM {pred}), 6) AS accuracy,
round(avg(coalesce(recall, 0)), 6) AS macro_recall, round(avg(coalesce(f1, 0)), 6) AS macro_f1 FROM ({sql.per_class(pred)}) WHERE support > 0"""


def _ablation(name: str, variants: dict[str, tuple[Config, bool, str]]):
    """A query over variants of the T1 pipeline: configuration, balance, holdout. Variants that are the plain pipeline share its model."""
    def run(spark, sf):
        out = []
        for v, (cfg, balanced, holdout) in variants.items():
            def make(cfg=cfg, balanced=balanced, holdout=holdout):
                tokens = once(spark, ("tokens", sf, balanced), lambda: tokenized(training(task(spark, sf, "T1"), balanced)))
                space, m = learned(tokens, cfg, holdout)
                return score.predict(task(spark, sf, "T1").where("split = 'test'"), m, space)

            plain = cfg == Config() and balanced and holdout == "vocab"
            out.append(rounded(_measured(predictions(spark, sf) if plain else once(spark, (name, sf, v), make), v), "accuracy", "macro_recall", "macro_f1"))
        return reduce(DataFrame.unionByName, out)

    steps, finals = [], []
    for i, (v, (cfg, balanced, holdout)) in enumerate(variants.items()):
        steps += sql.chain(sql.P1, f"_{i}", cfg.orders, cfg.head, cfg.tail, balanced, cfg.combine, holdout, taus=tuple(cfg.tau[k] for k in (1, 2, 3)))
        finals.append(f"SELECT * FROM ({_measured_sql(f'p_{i}', v)})")
    QUERIES[name], ORACLES[name] = run, sql.query(steps, " UNION ALL ".join(finals))


_ablation("ablate_ngrams", {"1": (Config(orders=(1,)), True, "vocab"), "1-2": (Config(), True, "vocab"), "1-2-3": (Config(orders=(1, 2, 3)), True, "vocab")})
_ablation("ablate_prep", {
    "base": (Config(), True, "vocab"), "unbalanced": (Config(), False, "vocab"), "untrimmed": (Config(head=0, tail=0), True, "vocab"),
    "no_holdout": (Config(), True, "train"), "global_vocab": (Config(combine="global"), True, "vocab"),
})

def _tau(first: int, second: int) -> Config:
    return Config(tau={1: (1, first), 2: (1, second), 3: (1, 1000)})


_ablation("search_thresholds", {f"1/{a} 1/{b}": (_tau(a, b), True, "vocab") for a, b in ((50, 1000), (100, 1000), (200, 1000), (100, 500), (100, 2000))})

# Training sets of natural proportions, balanced by leaving out, by copies and by made-up vectors. All are sums of the train vectors under weights of the files.
_MIX = f"""vt AS (SELECT label, file_id, n, term, count(*) / any_value(size) AS freq FROM f_n WHERE role = 1 AND split = 'train' GROUP BY label, file_id, n, term),
rk AS (SELECT *, row_number() OVER (PARTITION BY label ORDER BY md5(file_id || ':mix42'), file_id) - 1 AS k, count(*) OVER (PARTITION BY label) AS n FROM (SELECT DISTINCT label, file_id FROM vt)),
tm AS (SELECT *, most // n - 1 + (k < most % n)::INT AS times FROM rk, (SELECT max(n) AS most FROM rk)),
pr AS (SELECT a.label, a.file_id, b.file_id AS mate, {sql.bucket("(a.file_id || ':' || s)", "lambda42", 1000)} / 1000.0 AS lam FROM (SELECT tm.*, s FROM tm, range(1, 100000) r(s) WHERE s <= times) a JOIN rk b ON a.label = b.label AND b.k = (a.k + s) % a.n),
lt AS (SELECT * FROM lr_n WHERE split = 'train'),
oc AS (SELECT label, count(*) AS n, max(count(*)) OVER () AS most FROM lt GROUP BY label),
ov AS (SELECT file_id, most // n + (row_number() OVER (PARTITION BY label ORDER BY {sql.bucket("sha", "draw42", 1000000)}, md5(sha || ':balance42'), file_id) <= most % n)::INT AS w FROM lt JOIN oc USING (label)),
un AS ({sql.balanced("lt")}),
wt AS (SELECT 'natural' AS variant, file_id, 1.0::DOUBLE AS w FROM rk UNION ALL SELECT 'undersampled', file_id, 1 FROM un UNION ALL SELECT 'oversampled', file_id, w FROM ov
  UNION ALL SELECT 'synthetic', file_id, sum(w) FROM (SELECT file_id, 1.0 AS w FROM rk UNION ALL SELECT file_id, 1 - lam FROM pr UNION ALL SELECT mate, lam FROM pr) GROUP BY file_id),
sw AS (SELECT variant, label AS class, n, term, sum(freq * w) * {nb.SCALE} AS cnt FROM vt JOIN wt USING (file_id) GROUP BY ALL),
tw AS (SELECT variant, class, n, term, ln((coalesce(cnt, 0) + 1) / (sum(coalesce(cnt, 0)) OVER (PARTITION BY variant, class) + count(*) OVER (PARTITION BY variant, class))) AS lt
  FROM (SELECT DISTINCT variant, class FROM sw) CROSS JOIN s_n LEFT JOIN sw USING (variant, class, n, term)),
zw AS (SELECT variant, file_id, label, class, sum(freq * lt) AS score FROM fr_n JOIN tw USING (n, term) GROUP BY ALL),
qw AS (SELECT *, exp(score) / sum(exp(score)) OVER (PARTITION BY variant, file_id) AS p FROM zw),
pw AS (SELECT variant, file_id, label, class AS pred FROM qw QUALIFY row_number() OVER (PARTITION BY variant, file_id ORDER BY round(p, 12) DESC, class) = 1),
""" + ", ".join(f"pw_{v} AS (SELECT * FROM pw WHERE variant = '{v}')" for v in ("natural", "undersampled", "oversampled", "synthetic"))


@query(sql.query([*sql.chain(sql.P1, "_n", balance="vocab"), _MIX], " UNION ALL ".join(_measured_sql(f"pw_{v}", v) for v in ("natural", "undersampled", "oversampled", "synthetic"))))
def ablate_balance(spark, sf):
    """T1 under four training sets: as it comes, the large classes cut, the small ones copied, the small ones filled with made-up vectors."""
    space, _ = model(spark, sf)
    df = task(spark, sf, "T1")
    train, test = df.where("split = 'train'"), df.where("split = 'test'").where(F.size(tokens_of(F.col("content"))) > 0)
    natural = keep(vectorize_sql(train, space, trimmed=True))
    copies = balance.oversample(train).select(F.concat_ws("#", "file_id", "copy").alias("file_id"), "label", "content")
    sets = {
        "natural": natural, "undersampled": natural.join(balance.undersample(train).select("file_id"), "file_id", "left_semi"),
        "oversampled": vectorize_sql(copies, space, trimmed=True), "synthetic": natural.unionByName(balance.synthesize(natural).select(natural.columns)),
    }
    parts = [_measured(once(spark, ("balance", sf, v), lambda x=x: score.predict(test, nb.fit_vectors(x, space), space)), v) for v, x in sets.items()]
    return rounded(reduce(DataFrame.unionByName, parts), "accuracy", "macro_recall", "macro_f1")


# Half of the files in one encoding, half in another; read as bytes, or as text by a guessed encoding.
_LATIN = f"({sql.bucket('sha', 'encoding', 100)} < 50 AND NOT regexp_matches(content, '[^\\x00-\\xff]'))"
_TWICE = "regexp_replace(regexp_replace(regexp_replace(content, '[\\x{80}-\\x{7ff}]', repeat(chr(26), 2), 'g'), '[\\x{800}-\\x{ffff}]', repeat(chr(26), 3), 'g'), '[\\x{10000}-\\x{10ffff}]', repeat(chr(26), 4), 'g')"
_BYTES = f"SELECT * REPLACE (CASE WHEN {_LATIN} THEN regexp_replace(content, '[^\\x00-\\x7f]', chr(26), 'g') ELSE {_TWICE} END AS content) FROM ({sql.P1})"


@query(sql.query([*sql.chain(_BYTES, "_b"), *sql.chain(sql.P1, "_g", ascii_=False)], _measured_sql("p_b", "bytes") + " UNION ALL " + _measured_sql("p_g", "guessed encoding")))
def ablate_encoding(spark, sf):
    """T1 with half of its files in a one-byte encoding: every byte that is not ASCII as one sign, against letters by a guessed encoding."""
    df = task(spark, sf, "T1")
    one_byte = (bucket(F.col("sha"), "encoding", 100) < 50) & ~F.col("content").rlike(r"[^\x00-\xff]")
    coded = df.withColumn("content_bytes", F.when(one_byte, F.encode("content", "ISO-8859-1")).otherwise(F.encode("content", "UTF-8")))
    read = {"bytes": (F.decode("content_bytes", "ISO-8859-1"), Config()), "guessed encoding": (prep.guessed_text(F.col("content_bytes")), Config(unit="none"))}
    out = []
    for v, (content, cfg) in read.items():
        def make(content=content, cfg=cfg):
            rows = keep(coded.withColumn("content", content).drop("content_bytes"))
            space, m = learned(training(rows), cfg)
            return score.predict(rows.where("split = 'test'"), m, space)

        out.append(_measured(once(spark, ("encoding", sf, v), make), v))
    return rounded(reduce(DataFrame.unionByName, out), "accuracy", "macro_recall", "macro_f1")


_RATIOS, _SAMPLED = (10, 20, 40), (10, 50, 100)


@query(f"WITH f AS (SELECT *, odd / octet_length(b) AS ratio, {sql.bucket('file_id', 'binary42', 100)} AS bk FROM ({_T8})) " + " UNION ALL ".join(
    [f"SELECT 'file' AS scope, {r}::INT AS percent, 100::INT AS sampled, count(*) AS files, count(DISTINCT label) AS classes FROM f WHERE ratio <= {r} / 100" for r in _RATIOS]
    + [f"SELECT 'class_sample', {r}::INT, {k}::INT, count(*), count(DISTINCT label) FROM f WHERE label NOT IN (SELECT label FROM f WHERE bk < {k} GROUP BY label HAVING avg(ratio) > {r} / 100)" for r in _RATIOS for k in _SAMPLED]))
def ablate_binary(spark, sf):
    """T8 under thresholds and samples of the binary filter: files and classes that stay."""
    t8, out = keep(corpus.injected(spark, sf)), []
    for r in _RATIOS:
        for scope, k in (("file", 100), *(("class_sample", k) for k in _SAMPLED)):
            left = prep.keep_textual(t8, r / 100, scope=scope, content="content_bytes", binary=True, sample=k)
            out.append(left.agg(F.count("*").alias("files"), F.count_distinct("label").alias("classes")).select(F.lit(scope).alias("scope"), F.lit(r).alias("percent"), F.lit(k).alias("sampled"), "files", "classes"))
    return reduce(DataFrame.unionByName, out)


_NAMED = f"""nm AS (SELECT *, {sql.bucket("file_id", "name", 100)} AS nb FROM sp),
ot AS (SELECT label, coalesce(lead(label) OVER (ORDER BY label), min(label) OVER ()) AS other FROM (SELECT DISTINCT label FROM sp)),
fn AS (SELECT nm.*, CASE WHEN nb < 10 THEN file_id WHEN nb < 15 THEN file_id || '.' || other ELSE file_id || '.' || label END AS filename FROM nm JOIN ot USING (label)),
ft AS (SELECT * FROM fn WHERE split = 'test'), fl AS (SELECT * FROM fn WHERE split = 'train')"""
_CUES = "CASE " + " ".join(f"WHEN regexp_matches(content, '{p}') THEN '{c}'" for p, c in baselines.CUES) + " ELSE 'txt_en' END"
_BASE = {
    "suffix": "SELECT file_id, label, CASE WHEN regexp_extract(filename, '^.*[^/]\\.([^./]+)$', 1) IN (SELECT label FROM fl) THEN regexp_extract(filename, '^.*[^/]\\.([^./]+)$', 1) END AS pred FROM ft",
    "origin": "SELECT file_id, label, o.pred FROM ft LEFT JOIN (SELECT origin, label AS pred FROM (SELECT origin, label, row_number() OVER (PARTITION BY origin ORDER BY count(*) DESC, label) AS k FROM fl GROUP BY origin, label) WHERE k = 1) o USING (origin)",
    "cues": f"SELECT file_id, label, {_CUES} AS pred FROM ft",
    "prior": "SELECT file_id, label, (SELECT label FROM fl GROUP BY label ORDER BY count(*) DESC, label LIMIT 1) AS pred FROM ft",
    "naive_bayes": "SELECT file_id, label, pred FROM p",
}
_HITS = "SELECT '{n}' AS baseline, count(*) AS files, count(pred) AS answered, round(avg(coalesce(label = pred, false)::INT), 6) AS accuracy FROM ({q})"


def _base_predictions(spark, sf) -> dict[str, DataFrame]:
    t2 = corpus.named(spark, sf, task(spark, sf, "T2c"))
    train, test = t2.where("split = 'train'"), t2.where("split = 'test'")
    return {
        "suffix": baselines.by_extension(test, train), "origin": baselines.by_origin(train, test), "cues": baselines.by_cues(test),
        "prior": baselines.prior(train, test), "naive_bayes": predictions(spark, sf, "T2c"),
    }


@query(sql.query([*TEST2, _NAMED], " UNION ALL ".join(_HITS.format(n=n, q=q) for n, q in _BASE.items())))
def baseline_table(spark, sf):
    """Suffix, origin, cues, prior and naive Bayes on the T2 test files under damaged names."""
    hit = F.coalesce((F.col("label") == F.col("pred")).cast("int"), F.lit(0))
    parts = [p.agg(F.count("*").alias("files"), F.count("pred").alias("answered"), F.round(F.avg(hit), 6).alias("accuracy")).select(F.lit(n).alias("baseline"), "*") for n, p in _base_predictions(spark, sf).items()]
    return reduce(DataFrame.unionByName, parts)


def _base_query(name: str, kind: str) -> None:
    def run(spark, sf):
        return _base_predictions(spark, sf)[kind].select("file_id", "label", "pred")

    QUERIES[name], ORACLES[name] = run, sql.query([*TEST2, _NAMED], _BASE[kind])


for _n, _k in (("suffix_lookup", "suffix"), ("origin_lookup", "origin"), ("cue_rules", "cues"), ("prior", "prior")):
    _base_query(_n, _k)

_CENTROID = """vt AS (SELECT label, file_id, n, term, count(*) / any_value(size) AS freq FROM f WHERE role = 1 AND split = 'train' GROUP BY label, file_id, n, term),
ce AS (SELECT label AS class, n, term, sum(freq) / any_value(files) AS m FROM vt JOIN (SELECT label, count(*) AS files FROM ba WHERE split = 'train' GROUP BY label) USING (label) GROUP BY label, n, term),
cw AS (SELECT class, n, term, m / sqrt(sum(m * m) OVER (PARTITION BY class)) AS w FROM ce),
cd AS (SELECT file_id, label, class, sum(freq * w) AS dot FROM fr JOIN cw USING (n, term) GROUP BY ALL)"""


@query(sql.query([*TEST, _CENTROID], "SELECT file_id, label, class AS pred FROM cd QUALIFY row_number() OVER (PARTITION BY file_id ORDER BY round(dot, 12) DESC, class) = 1"))
def centroid_nearest(spark, sf):
    """The class of the nearest mean vector."""
    space, _ = model(spark, sf)
    df = task(spark, sf, "T1")
    return baselines.nearest_centroid(training(df).where("split = 'train'"), df.where("split = 'test'"), space)


#: Twins that one name covers.
ALIAS = {"jsonl": "json", "chat_user": "chat", "chat_assistant": "chat", "chat_system": "chat", "bench": "txt_en"}
_MERGE = "CASE {c} " + " ".join(f"WHEN '{a}' THEN '{b}'" for a, b in ALIAS.items()) + " ELSE {c} END"


@query(sql.query([*TEST2, f"pm AS (SELECT file_id, {_MERGE.format(c='label')} AS label, {_MERGE.format(c='pred')} AS pred FROM p)"], _measured_sql("p", "apart") + " UNION ALL " + _measured_sql("pm", "merged")))
def merged_labels(spark, sf):
    """T2 before and after twins get one name."""
    pred = predictions(spark, sf, "T2c")
    return rounded(_measured(pred, "apart").unionByName(_measured(confusion.merge_labels(pred, ALIAS), "merged")), "accuracy", "macro_recall", "macro_f1")


@query(sql.query([*sql.chain(sql.P6, scored="split IN ('val', 'test')"), "w AS (SELECT time_bucket(INTERVAL 6 HOUR, arrival, TIMESTAMP '1970-01-01') AS start, count(*) AS n, avg((p.label = pred)::INT) AS accuracy FROM p JOIN c USING (file_id) GROUP BY 1)"],
                 """SELECT start, n, round(accuracy, 6) AS accuracy, round(accuracy - lag(accuracy) OVER (ORDER BY start), 6) AS delta,
coalesce(round(max(accuracy) OVER (ORDER BY start ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) - accuracy, 12) > 0.05, false) AS alarm FROM w"""))
def drift_windows(spark, sf):
    """Accuracy by six hours of arrival, and where it falls enough to retrain."""
    return rounded(drift.schedule(_timed(spark, sf)), "accuracy", "delta")


def _timed(spark, sf) -> DataFrame:
    def make():
        df = task(spark, sf, "T6")
        space, m = learned(training(df))
        return score.predict(df.where("split in ('val', 'test')"), m, space, keep=("file_id", "label", "arrival"))

    return once(spark, ("timed", sf), make)


SNIPPETS = (5, 10, 20, 50, 100)


@query(sql.query([x for k in SNIPPETS for x in sql.chain(sql.P1, f"_{k}", cut=f"t[1:{k}]")], " UNION ALL ".join(f"SELECT {k} AS tokens, count(*) AS files, round(avg((label = pred)::INT), 6) AS accuracy FROM p_{k}" for k in SNIPPETS)))
def snippet_curve(spark, sf):
    """Accuracy from the first tokens alone (T1 test files)."""
    space, m = model(spark, sf)
    df = task(spark, sf, "T1").where("split = 'test'")
    parts = [score.snippets(df, m, space, k).agg(F.lit(k).alias("tokens"), F.count("*").alias("files"), F.round(F.avg((F.col("label") == F.col("pred")).cast("double")), 6).alias("accuracy")) for k in SNIPPETS]
    return reduce(DataFrame.unionByName, parts)


@query(sql.query([f"c AS ({sql.SNAPSHOTS})", f"tk AS (SELECT label, old AS o, {sql.tokens('content')} AS t FROM c)", "u AS (SELECT label, o, unnest(t) AS term FROM tk)",
                  "vv AS (SELECT DISTINCT o, term FROM (SELECT o, label, term, count(*) AS n FROM u GROUP BY ALL) JOIN (SELECT o, label, sum(len(t)) AS total FROM tk GROUP BY ALL) USING (o, label) WHERE n * 100 > total)"],
                 "SELECT count(*) FILTER (o) AS n_old, count(*) FILTER (NOT o) AS n_new, count(*) - count(DISTINCT term) AS both, round((count(*) - count(DISTINCT term)) / count(DISTINCT term), 6) AS jaccard FROM vv"))
def vocab_overlap(spark, sf):
    """How far the vocabularies of two snapshots agree."""
    old, new = (vocab.build(vocab.tokens(x)) for x in _snapshots(spark, sf))
    return rounded(vocab.overlap(old, new), "jaccard")


@query(sql.query([*WHOLE, _V1], "SELECT label, round(avg((term NOT IN (FROM v1))::INT), 6) AS share FROM u1 GROUP BY label"))
def unknown_shares(spark, sf):
    toks = vocab.tokens(CORPORA["T1"](spark, sf))
    return rounded(vocab.unknown_share(toks, vocab.as_list(vocab.build(toks))), "share")


@query(sql.query([f"c AS ({sql.T1})", f"r AS (SELECT *, row_number() OVER (PARTITION BY label ORDER BY {sql.bucket('sha', 'draw42', 1000000)}, md5(sha || ':balance42'), file_id) AS rk FROM c)",
                  "n AS (SELECT label, count(*) AS n, max(count(*)) OVER () AS most FROM c GROUP BY label)"],
                 "SELECT label, file_id, (most // n + (rk <= most % n)::INT)::BIGINT AS copies FROM r JOIN n USING (label)"))
def oversample(spark, sf):
    """Copies of each T1 file that bring every class to the size of the largest."""
    return balance.oversample(CORPORA["T1"](spark, sf)).groupBy("label", "file_id").agg(F.count("*").alias("copies"))


@query(sql.query([*TEST, f"""vs AS (SELECT label, file_id, sum(freq) AS mass FROM (SELECT label, file_id, n, term, count(*) / any_value(size) AS freq FROM f WHERE role = 1 AND split = 'train' GROUP BY label, file_id, n, term) GROUP BY ALL),
rs AS (SELECT *, row_number() OVER (PARTITION BY label ORDER BY md5(file_id || ':mix42'), file_id) - 1 AS k, count(*) OVER (PARTITION BY label) AS n FROM vs),
ps AS (SELECT a.label, a.mass AS own, b.mass AS mate, {sql.bucket("(a.file_id || ':1')", "lambda42", 1000)} / 1000.0 AS lam FROM rs a JOIN rs b ON a.label = b.label AND b.k = (a.k + 1) % a.n)"""],
                 "SELECT label, count(*) AS files, round(sum(own * (1 - lam) + mate * lam), 6) AS mass FROM ps GROUP BY label"))
def synthesized(spark, sf):
    """Convex mixes of vectors of one class; their mass is kept."""
    space, _ = model(spark, sf)
    v = vectorize_sql(training(task(spark, sf, "T1")).where("split = 'train'"), space, trimmed=True)
    made = balance.synthesize(v, k=1)
    return rounded(made.groupBy("label").agg(F.count_distinct("file_id").alias("files"), F.sum("freq").alias("mass")), "mass")


def _judged_query(name: str, label: str) -> None:
    def run(spark, sf):
        return rounded(_measured(predictions(spark, sf, name), label), "accuracy", "macro_recall", "macro_f1")

    QUERIES[f"task_{label}"], ORACLES[f"task_{label}"] = run, sql.query(sql.chain(sql.prepared(sql.judged(label))), _measured_sql("p", label))


_judged_query("T4", "quality")
_judged_query("T5", "toxic")


@query(sql.query(sql.chain(sql.P3, taus=((1, 100), (1, 1000), (1, 1000))), _measured_sql("p", "source")))
def negative_control(spark, sf):
    """T3: labels that have nothing to do with content; accuracy stays near one in twenty."""
    return rounded(_measured(predictions(spark, sf, "T3"), "source"), "accuracy", "macro_recall", "macro_f1")


_INPUTS = ["coalesce(value, 0) / 1000", "extract(hour FROM ts) / 24.0D", "extract(minute FROM ts) / 60.0D", "user_id % 10 / 10.0D", "CAST(event_type = 'error' AS INT)", "CAST(event_type = 'signup' AS INT)"]
_UNITS, _KINDS = 5, ["c0", "c1", "c2"]


def _forward_sql() -> str:
    x = ", ".join(f"({e.replace('.0D', '.0::DOUBLE')})::DOUBLE AS x{i}" for i, e in enumerate(_INPUTS))
    h = ", ".join("greatest(" + " + ".join(f"coalesce(x{i}, 0) * cos({i} * 3.0 + {j})" for i in range(len(_INPUTS))) + f", 0) AS h{j}" for j in range(_UNITS))
    z = ", ".join(" + ".join(f"h{j} * sin({j} * 2.0 + {k})" for j in range(_UNITS)) + f" AS z{k}" for k in range(len(_KINDS)))
    p = ", ".join(f"round(exp(z{k}) / (" + " + ".join(f"exp(z{m})" for m in range(len(_KINDS))) + f"), 6) AS {c}" for k, c in enumerate(_KINDS))
    return f"SELECT event_id, {p} FROM (SELECT event_id, {z} FROM (SELECT event_id, {h} FROM (SELECT event_id, {x} FROM events)))"


@query(_forward_sql())
def forward_check(spark, sf):
    """Forward pass of a small network whose weights are a formula of their indices, over every event: the probability of each class."""
    import numpy as np
    import pyarrow as pa

    from ..operators import mlp
    from ..sources.tables import load

    w = [np.cos(np.arange(len(_INPUTS))[:, None] * 3.0 + np.arange(_UNITS)), np.sin(np.arange(_UNITS)[:, None] * 2.0 + np.arange(len(_KINDS)))]
    net = mlp.Net(_KINDS, w, [np.zeros(_UNITS), np.zeros(len(_KINDS))])

    def run(batches):
        for b in batches:
            x = np.stack([c.to_numpy(zero_copy_only=False) for c in b.columns[1:]], axis=1)
            row, at = np.nonzero(x)
            cuts = np.cumsum(np.bincount(row, minlength=len(x)))[:-1]
            p = score.softmax(net.logits(list(zip(np.split(at, cuts), np.split(x[row, at], cuts), strict=True)) if len(x) else []))
            yield pa.RecordBatch.from_arrays([b.column(0), *map(pa.array, p.T)], ["event_id", *_KINDS])

    inputs = load(spark, sf, "events").select("event_id", *(F.coalesce(F.expr(e).cast("double"), F.lit(0.0)).alias(f"x{i}") for i, e in enumerate(_INPUTS)))
    return rounded(inputs.mapInArrow(run, "event_id long, " + ", ".join(f"{c} double" for c in _KINDS)), *_KINDS)
