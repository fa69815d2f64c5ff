"""SQL for the oracle: the same definitions, written for DuckDB."""

from __future__ import annotations

from ..functions.text import TOKEN
from ..operators.splits import SHARES

T1 = "SELECT 'd' || doc_id AS file_id, text AS content, lang AS label, 'documents' AS origin, sha1(text) AS sha FROM documents"
T3 = "SELECT 'd' || doc_id AS file_id, text AS content, source AS label, 'documents' AS origin, sha1(text) AS sha FROM documents"
T6 = "SELECT 'd' || doc_id AS file_id, text AS content, lang AS label, 'documents' AS origin, sha1(text) AS sha, ts AS arrival FROM documents JOIN events ON event_id = doc_id"


def judged(label: str) -> str:
    return f"SELECT 'd' || doc_id AS file_id, text AS content, '{label}' || {label} AS label, 'documents' AS origin, sha1(text) AS sha FROM documents JOIN labels USING (doc_id)"


def _lines(table: str, number: str, line: str, order: str, label: str) -> str:
    return f"SELECT '{table[:2]}' || f AS file_id, string_agg(line, chr(10) ORDER BY {order}) AS content, {label} AS label, '{table}' AS origin FROM (SELECT *, ({number})::BIGINT AS f, {line} AS line FROM {table}) GROUP BY f"


def _cents(c: str) -> str:
    return f"round({c} * 100)::BIGINT"


T2 = "SELECT *, sha1(content) AS sha FROM (" + " UNION ALL ".join((
    "SELECT 'd' || doc_id AS file_id, text AS content, 'txt_' || lang AS label, 'documents' AS origin FROM documents",
    "SELECT 'p' || page_id, regexp_replace(html, '<html lang=\"[a-z]+\"', '<html', 'g'), 'html_' || regexp_extract(html, '<html lang=\"([a-z]+)\"', 1), 'pages' FROM pages",
    "SELECT 'c_' || conv_id || '_' || turn, text, 'chat_' || role, 'conversations' FROM conversations",
    "SELECT 'b' || item_id, text, 'bench', 'benchmark' FROM benchmark",
    _lines("events", "event_id // 20", f"""'{{"id":' || event_id || ',"event_type":"' || event_type || '","user_id":"' || user_id || '","value":' || {_cents("value")} || ',"props":' || props || '}}'""", "event_id", "CASE WHEN f % 2 = 0 THEN 'json' ELSE 'jsonl' END"),
    _lines("orders", "(o_orderkey - 1) // 20", f"concat_ws(',', o_orderkey, o_custkey, o_orderstatus, {_cents('o_totalprice')}, strftime(o_orderdate, '%Y-%m-%d'), o_orderpriority)", "o_orderkey", "'csv'"),
    _lines("lineitem", "(l_orderkey - 1) // 20", f"concat_ws('|', l_orderkey, l_partkey, l_suppkey, {_cents('l_quantity')}, {_cents('l_extendedprice')}, l_returnflag, l_linestatus, strftime(l_shipdate, '%Y-%m-%d'))", "l_orderkey, l_linenumber, l_partkey, l_suppkey, line", "'tbl'"),
    _lines("part", "(p_partkey - 1) // 20", "'<part><name>' || p_name || '</name><brand>' || p_brand || '</brand><size>' || p_size || '</size></part>'", "p_partkey", "'xml'"),
    _lines("customer", "(c_custkey - 1) // 20", f"concat_ws(chr(9), c_custkey, c_name, c_nationkey, {_cents('c_acctbal')}, c_mktsegment)", "c_custkey", "'tsv'"),
    _lines("supplier", "(s_suppkey - 1) // 20", "'[' || s_suppkey || ']' || chr(10) || 'name = ' || s_name || chr(10) || 'nation = ' || s_nationkey", "s_suppkey", "'ini'"),
    _lines("embeddings", "vec_id // 20", "array_to_string(list_transform(embedding, lambda x: round(x::DOUBLE * 1000)::BIGINT), ' ')", "vec_id", "'vec'"),
)) + ")"

def prepared(corpus: str, num: int = 1, den: int = 10_000) -> str:
    """A corpus without copies, rare classes, binary contents and contents of several labels."""
    return f"""SELECT * FROM (WITH pc AS ({corpus}), pd AS (SELECT * FROM pc QUALIFY row_number() OVER (PARTITION BY sha, label ORDER BY file_id) = 1),
pf AS (SELECT * FROM pd WHERE label IN (SELECT label FROM pd GROUP BY label HAVING count(*) * {den} >= (SELECT count(*) FROM pd) * {num})),
px AS (SELECT * FROM pf WHERE coalesce(length(regexp_replace(content, '[\\x20-\\x7e\\t\\n\\r]', '', 'g')) / nullif(length(content), 0), 0) <= 0.2)
SELECT * FROM px WHERE sha NOT IN (SELECT sha FROM px GROUP BY sha HAVING count(DISTINCT label) > 1))"""


#: The corpora that models learn from. T2C is T2 without kinds that have less than one file in a hundred.
P1, P3, P6, T2C = prepared(T1), prepared(T3), prepared(T6), prepared(T2, 1, 100)
#: T6 in two snapshots, each prepared by itself; `old` tells which.
CUT6 = f"(SELECT (min(epoch_us(arrival)) + max(epoch_us(arrival))) // 2 FROM ({T6}))"
SNAPSHOTS = " UNION ALL ".join(f"SELECT *, {old} AS old FROM ({prepared(f'SELECT * FROM ({T6}) WHERE (epoch_us(arrival) < {CUT6}) = {old}')})" for old in ("true", "false"))


def bucket(key: str, seed, modulus: int) -> str:
    return f"(('0x' || substr(md5({key} || ':{seed}'), 1, 8))::BIGINT % {modulus})"


def tokens(content: str, ascii_: bool = True) -> str:
    if not ascii_:
        return f"regexp_extract_all(coalesce({content}, ''), '{TOKEN}')"
    return f"regexp_extract_all(regexp_replace(coalesce({content}, ''), '[^\\x00-\\x7f]', chr(26), 'g'), '{TOKEN}')"


def split(seed: int = 42) -> str:
    upto, cases = 0, []
    for name, share in SHARES.items():
        upto += share
        cases.append(f"WHEN b < {upto} THEN '{name}'")
    return f"CASE {' '.join(cases)} END"


def balanced(rows: str, seed: int = 42) -> str:
    """Rows (with split) cut to the smallest class of each split."""
    return f"""SELECT * EXCLUDE (rk, want) FROM (
  SELECT *, row_number() OVER (PARTITION BY split, label ORDER BY {bucket("sha", f"draw{seed}", 1000000)}, md5(sha || ':balance{seed}'), file_id) AS rk FROM {rows})
  JOIN (SELECT split, min(n) AS want FROM (SELECT split, label, count(*) AS n FROM {rows} GROUP BY ALL) GROUP BY split) USING (split) WHERE rk <= want"""


def _chosen(grams: str, totals: str, tau: tuple[int, int], combine: str) -> str:
    num, den = tau
    if combine == "global":
        return f"SELECT term FROM {grams} GROUP BY term HAVING count(*) * {den} > (SELECT sum(total) FROM ({totals})) * {num}"
    return f"SELECT DISTINCT term FROM (SELECT label, term, count(*) AS n FROM {grams} GROUP BY ALL) JOIN ({totals}) USING (label) WHERE n * {den} > total * {num}"


def chain(corpus: str, tag: str = "", orders=(1, 2), head: int = 10, tail: int = 10, balance: bool | str = True, combine: str = "any", holdout: str = "vocab",
          learn: str = "true", scored: str = "split = 'test'", cut: str = "t", taus=((1, 100), (1, 1000), (1, 1000)), ascii_: bool = True) -> list[str]:
    """Steps from a corpus to naive Bayes predictions (p{tag}: file_id, label, pred, p, and r{tag}: all classes of each file).

    balance: whether the vocab and train splits are balanced, or `vocab`: that one alone; learn: rows that may train; scored: rows that are predicted; cut: the tokens of these that are read.
    """
    def n(x: str) -> str:
        return x + tag

    taken = balanced(n("lr")) if balance else f"SELECT * FROM {n('lr')}"
    if balance == "vocab":
        taken = f"SELECT * FROM ({taken}) WHERE split = 'vocab' UNION ALL SELECT * FROM {n('lr')} WHERE split = 'train'"
    steps = [
        f"{n('c')} AS ({corpus})",
        f"{n('sp')} AS (SELECT *, {split()} AS split FROM (SELECT *, {bucket('sha', 42, 100)} AS b FROM {n('c')}))",
        f"{n('lr')} AS (SELECT * FROM {n('sp')} WHERE {learn} AND split IN ('vocab', 'train'))",
        f"{n('ba')} AS ({taken})",
        f"{n('tt')} AS (SELECT file_id, label, split, {tokens('content', ascii_)} AS t FROM {n('ba')})",
        f"{n('tr')} AS (SELECT file_id, label, split, CASE WHEN len(t) > {head + tail} THEN t[{head + 1}:len(t) - {tail}] ELSE [] END AS t FROM {n('tt')})",
        f"{n('hv')} AS (SELECT * FROM {n('tr')} WHERE split = '{holdout}')",
        f"{n('u1')} AS (SELECT label, unnest(t) AS term FROM {n('hv')})",
        f"{n('v1')} AS ({_chosen(n('u1'), f'SELECT label, sum(len(t)) AS total FROM {n('hv')} GROUP BY label', taus[0], combine)})",
        f"{n('te')} AS (SELECT file_id, label, 'scored' AS split, {cut} AS t FROM (SELECT file_id, label, {tokens('content', ascii_)} AS t FROM {n('sp')} WHERE {scored}))",
        f"{n('al')} AS (SELECT 1 AS role, * FROM {n('tr')} UNION ALL SELECT 2, * FROM {n('te')})",
        f"""{n('mp')} AS (SELECT role, file_id, label, split, size, pos, coalesce(v.term, '<unk>') AS tok
  FROM (SELECT role, file_id, label, split, len(t) AS size, unnest(t) AS raw, generate_subscripts(t, 1) AS pos FROM {n('al')}) x LEFT JOIN {n('v1')} v ON x.raw = v.term)""",
        f"""{n('g')} AS (SELECT role, file_id, label, split, size, tok, lead(tok, 1) OVER w AS t2, lead(tok, 2) OVER w AS t3 FROM {n('mp')} WINDOW w AS (PARTITION BY role, file_id ORDER BY pos))""",
    ]
    grams = {1: ("tok", "true"), 2: ("tok || ' ' || t2", "t2 IS NOT NULL"), 3: ("tok || ' ' || t2 || ' ' || t3", "t3 IS NOT NULL")}
    spaces, parts = [f"SELECT 1 AS n, term, false AS is_unknown FROM {n('v1')} UNION ALL SELECT 1, '<unk>', true"], [f"SELECT role, file_id, label, split, size, 1 AS n, tok AS term FROM {n('g')}"]
    for k in orders:
        if k == 1:
            continue
        expr, ok = grams[k]
        steps.append(f"{n(f'u{k}')} AS (SELECT label, {expr} AS term FROM {n('g')} WHERE role = 1 AND split = '{holdout}' AND {ok})")
        steps.append(f"{n(f'v{k}')} AS ({_chosen(n(f'u{k}'), f'SELECT label, sum(greatest(len(t) - {k - 1}, 0)) AS total FROM {n('hv')} GROUP BY label', taus[k - 1], combine)})")
        spaces.append(f"SELECT {k}, term, false FROM {n(f'v{k}')} UNION ALL SELECT {k}, '<unk{k}>', true")
        parts.append(f"SELECT role, file_id, label, split, size, {k}, coalesce(v.term, '<unk{k}>') FROM (SELECT *, {expr} AS gram FROM {n('g')} WHERE {ok}) x LEFT JOIN {n(f'v{k}')} v ON x.gram = v.term")
    return [
        *steps,
        f"{n('s')} AS (SELECT *, (row_number() OVER (ORDER BY n, is_unknown, term) - 1)::INT AS idx FROM ({' UNION ALL '.join(spaces)}))",
        f"{n('f')} AS ({' UNION ALL '.join(parts)})",
        f"{n('k')} AS (SELECT DISTINCT label AS class FROM {n('ba')} WHERE split = 'train')",
        f"{n('cn')} AS (SELECT label AS class, n, term, count(*) AS cnt FROM {n('f')} WHERE role = 1 AND split = 'train' GROUP BY ALL)",
        f"""{n('th')} AS (SELECT class, n, term, ln((coalesce(cnt, 0) + 1) / (sum(coalesce(cnt, 0)) OVER (PARTITION BY class) + count(*) OVER (PARTITION BY class))) AS lt
  FROM {n('k')} CROSS JOIN {n('s')} LEFT JOIN {n('cn')} USING (class, n, term))""",
        f"{n('fr')} AS (SELECT file_id, label, n, term, count(*) / any_value(size) AS freq FROM {n('f')} WHERE role = 2 GROUP BY file_id, label, n, term)",
        f"{n('sc')} AS (SELECT file_id, class, sum(freq * lt) AS score FROM {n('fr')} JOIN {n('th')} USING (n, term) GROUP BY ALL)",
        f"{n('z')} AS (SELECT t.file_id, t.label, k.class, coalesce(score, 0) AS score FROM {n('te')} t CROSS JOIN {n('k')} k LEFT JOIN {n('sc')} s ON s.file_id = t.file_id AND s.class = k.class)",
        f"{n('q')} AS (SELECT file_id, label, class, exp(score) / sum(exp(score)) OVER w AS p FROM {n('z')} WINDOW w AS (PARTITION BY file_id))",
        f"{n('r')} AS (SELECT *, row_number() OVER (PARTITION BY file_id ORDER BY round(p, 12) DESC, class) AS k FROM {n('q')})",
        f"{n('p')} AS (SELECT file_id, label, class AS pred, p FROM {n('r')} WHERE k = 1)",
    ]


def query(steps: list[str], final: str) -> str:
    return "WITH " + ",\n".join(steps) + "\n" + final


def t_s(tag: str = "", k: int = 5) -> list[str]:
    """tm{tag}: (i, j, t); sm{tag}: (i, j, s)."""
    return [
        f"tm{tag} AS (SELECT i, j, n / sum(n) OVER (PARTITION BY i) AS t FROM (SELECT label AS i, pred AS j, count(*) AS n FROM p{tag} GROUP BY label, pred))",
        f"tp{tag} AS (SELECT file_id, class, p / sum(p) OVER (PARTITION BY file_id) AS share FROM r{tag} WHERE k <= {k})",
        f"sm{tag} AS (SELECT pred AS i, class AS j, sum(share) / any_value(files) AS s FROM tp{tag} JOIN p{tag} USING (file_id) JOIN (SELECT pred, count(*) AS files FROM p{tag} GROUP BY pred) USING (pred) GROUP BY pred, class)",
    ]


def per_class(pred: str) -> str:
    return f"""SELECT label, support, tp, predicted - tp AS fp, support - tp AS fn, CASE WHEN predicted > 0 THEN tp / predicted END AS "precision",
       CASE WHEN support > 0 THEN tp / support END AS recall, 2 * tp / (support + predicted) AS f1
FROM (SELECT label, sum(support)::BIGINT AS support, sum(tp)::BIGINT AS tp, sum(predicted)::BIGINT AS predicted FROM (
  SELECT label, 1 AS support, (label = pred)::INT AS tp, 0 AS predicted FROM {pred} UNION ALL SELECT pred, 0, 0, 1 FROM {pred}) GROUP BY label)"""


def averages(classes: str) -> str:
    return f"""SELECT 'micro' AS kind, sum(tp) / sum(tp + fp) AS "precision", sum(tp) / sum(tp + fn) AS recall, 2 * sum(tp) / sum(2 * tp + fp + fn) AS f1 FROM {classes}
UNION ALL SELECT 'macro', avg(coalesce("precision", 0)), avg(coalesce(recall, 0)), avg(coalesce(f1, 0)) FROM {classes} WHERE support > 0
UNION ALL SELECT 'weighted', sum(coalesce("precision", 0) * support) / sum(support), sum(coalesce(recall, 0) * support) / sum(support), sum(coalesce(f1, 0) * support) / sum(support) FROM {classes}"""


def rounded(sql: str, columns: list[str], others: list[str]) -> str:
    return f"SELECT {', '.join([*others, *(f'round({c}, 6) AS {c}' for c in columns)])} FROM ({sql})"
