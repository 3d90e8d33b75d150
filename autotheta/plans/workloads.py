"""The experiment workloads on the given tables: two sides, their true pairs, tokens and similarity.

Each side is one SQL text for both engines; ``fixture`` reads it with Spark, the oracles use it in DuckDB.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from autotheta.functions import sims
from autotheta.functions.sims import SetSimilarity
from autotheta.operators.blocks import Blocks, write_blocks
from autotheta.operators.sets import Prepared, prepare
from autotheta.plans.dialects import Duck, Spark
from autotheta.sources.shared import exists, exists_at


@dataclass(frozen=True)
class Workload:
    name: str
    r: Callable[[Spark], str]
    s: Callable[[Spark], str]
    c: Callable[[Spark], str] | None
    tokens: str
    bag: bool
    sim: SetSimilarity


def _item_words(d: Spark) -> str:
    return f"SELECT DISTINCT w FROM (SELECT {d.explode(d.words('text'))} AS w FROM {d.table('benchmark')}) WHERE {d.matches('w', '[a-z]{5,12}')}"


def _typos(d: Spark) -> str:
    return f"""SELECT w, CASE {d.div('k', 4)} % 4
        WHEN 0 THEN concat(substr(w, 1, p), substr(w, p + 2))
        WHEN 1 THEN concat(substr(w, 1, p), substr(w, p + 2, 1), substr(w, p + 1, 1), substr(w, p + 3))
        WHEN 2 THEN concat(substr(w, 1, p + 1), substr(w, p + 1))
        ELSE concat(substr(w, 1, p), 'x', substr(w, p + 2)) END AS typo
      FROM (SELECT w, k, cast(1 + {d.div('k', 16)} % (length(w) - 2) AS int) AS p FROM (SELECT w, {d.h("concat('typo', w)")} AS k FROM ({_item_words(d)})))"""


def _w1_r(d: Spark) -> str:
    return f"SELECT DISTINCT {d.h('typo', 15)} AS id, typo AS text FROM ({_typos(d)}) WHERE typo <> w"


def _w1_s(d: Spark) -> str:
    return f"SELECT {d.h('w', 15)} AS id, w AS text FROM ({_item_words(d)})"


def _w1_c(d: Spark) -> str:
    return f"SELECT {d.h('typo', 15)} AS r, {d.h('w', 15)} AS s FROM ({_typos(d)}) WHERE typo <> w"


def _w2_parts(d: Spark) -> str:
    # Whole turns of all conversations, in one or both sides.
    return f"SELECT id, ws, {d.h(f"concat('part', {d.text('id')})")} % 3 AS m FROM (SELECT conv_id * 1000 + turn AS id, {d.words('text')} AS ws FROM {d.table('conversations')})"


def _w2_r(d: Spark) -> str:
    return f"SELECT id, {d.join('ws')} AS text FROM ({_w2_parts(d)}) WHERE m <> 2"


def _w2_s(d: Spark) -> str:
    kept = d.where("ws", "x", d.h(f"concat(x, '|', {d.text('id')})") + " % 4 <> 0")
    return f"SELECT id, {d.join(kept)} AS text FROM ({_w2_parts(d)}) WHERE m <> 0"


def _w2_c(d: Spark) -> str:
    return f"SELECT a.id AS r, b.id AS s FROM ({_w2_r(d)}) a JOIN ({_w2_s(d)}) b ON a.id = b.id"


def _half(odd: int) -> Callable[[Spark], str]:
    return lambda d: f"SELECT doc_id AS id, text FROM {d.table('documents')} WHERE doc_id % 2 = {odd}"


def _w3_c(d: Spark) -> str:
    # Sentences end with a full stop or a line.
    pieces = d.split("text", "[.\\n]")
    return f"""WITH se AS (SELECT DISTINCT doc_id, trim(x) AS x FROM (SELECT doc_id, {d.explode(pieces)} AS x FROM {d.table('documents')}) WHERE length(trim(x)) >= 20),
      sn AS (SELECT doc_id, count(*) AS n FROM se GROUP BY doc_id)
      SELECT a.doc_id AS r, b.doc_id AS s FROM se a JOIN se b ON a.x = b.x AND a.doc_id % 2 = 1 AND b.doc_id % 2 = 0
      JOIN sn na ON na.doc_id = a.doc_id JOIN sn nb ON nb.doc_id = b.doc_id
      GROUP BY a.doc_id, b.doc_id, na.n, nb.n HAVING 2 * count(*) >= greatest(na.n, nb.n)"""


def _docs(d: Spark) -> str:
    return f"SELECT doc_id AS id, text FROM {d.table('documents')}"


def _items(d: Spark) -> str:
    return f"SELECT item_id AS id, text FROM {d.table('benchmark')}"


def _w4_c(d: Spark) -> str:
    return f"SELECT a.doc_id AS r, b.item_id AS s FROM {d.table('documents')} a JOIN {d.table('benchmark')} b ON contains(a.text, b.text)"


def _dense(d: Spark) -> str:
    return f"SELECT doc_id AS id, text FROM {d.table('documents')} WHERE doc_id IN (SELECT r FROM ({_w4_c(d)}))"


def _part(odd: int) -> Callable[[Spark], str]:
    return lambda d: f"SELECT p_partkey AS id, concat_ws(' ', p_name, p_brand, p_type, {d.text('p_size')}) AS text FROM {d.table('part')} WHERE p_partkey % 2 = {odd}"


def _w5_c(d: Spark) -> str:
    bag = f"(SELECT id, {'array_sort(array_distinct' if d.name == 'spark' else 'list_sort(list_distinct'}({d.split('text', ' ')})) AS t FROM ({{}}))"
    return f"SELECT a.id AS r, b.id AS s FROM {bag.format(_part(1)(d))} a JOIN {bag.format(_part(0)(d))} b ON a.t = b.t"


def _titles(d: Spark) -> str:
    return f"SELECT page_id AS id, concat_ws(' ', {d.extract('html', '<title>([^<]*)</title>')}, url) AS text FROM {d.table('pages')}"


def _turns(role: str) -> Callable[[Spark], str]:
    return lambda d: f"SELECT conv_id * 1000 + turn AS id, text FROM {d.table('conversations')} WHERE role = '{role}'"


W = {
    w.name: w
    for w in (
        Workload("w1", _w1_r, _w1_s, _w1_c, "qgrams", True, sims.jaccard()),
        Workload("w2", _w2_r, _w2_s, _w2_c, "words", True, sims.jaccard()),
        Workload("w3", _half(1), _half(0), _w3_c, "words", True, sims.jaccard()),
        Workload("w4", _docs, _items, _w4_c, "words", True, sims.tversky("0.1")),
        Workload("w4set", _docs, _items, _w4_c, "words", False, sims.tversky("0.1")),
        Workload("w4dense", _dense, _items, _w4_c, "words", True, sims.tversky("0.1")),
        Workload("w5", _part(1), _part(0), _w5_c, "spaces", False, sims.jaccard()),
        Workload("w7", _titles, _docs, None, "words", True, sims.jaccard()),
        Workload("w8", _turns("user"), _turns("assistant"), None, "words", True, sims.jaccard()),
    )
}


def w6(parts: int) -> Workload:
    """W4 over the first ``parts`` of four files of documents and items. Ids divisible by 10 are in every file, so
    files overlap; both sides grow with them."""
    inside = lambda c: f"({c} % 4 < {parts} OR {c} % 10 = 0)"
    r = lambda d: f"SELECT doc_id AS id, text FROM {d.table('documents')} WHERE {inside('doc_id')}"
    s = lambda d: f"SELECT item_id AS id, text FROM {d.table('benchmark')} WHERE {inside('item_id')}"
    return Workload(f"w6_{parts}", r, s, lambda d: f"SELECT r, s FROM ({_w4_c(d)}) WHERE {inside('r')} AND {inside('s')}", "words", True, sims.tversky("0.1"))


W |= {f"w6_{k}": w6(k) for k in (1, 2, 3, 4)}


@dataclass
class Fixture:
    r: DataFrame
    s: DataFrame
    c: DataFrame | None
    prepared: Prepared


def sides(w: Workload, spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame | None]:
    d = Spark(sf_dir)
    return spark.sql(w.r(d)), spark.sql(w.s(d)), spark.sql(w.c(d)) if w.c else None


_PREPARED: dict[tuple, Fixture] = {}


def fixture(name: str, spark: SparkSession, sf_dir: str) -> Fixture:
    """A workload's sides, prepared: written once an application and used by all its queries while the files are there."""
    at = (spark.sparkContext.applicationId, name, sf_dir)
    if at not in _PREPARED or not exists(_PREPARED[at].prepared.order):
        w = W[name]
        r, s, c = sides(w, spark, sf_dir)
        _PREPARED[at] = Fixture(r, s, c, prepare(r, s, w.tokens, w.bag))
    return _PREPARED[at]


_BLOCKS: dict[tuple, Blocks] = {}


def blocks(name: str, spark: SparkSession, sf_dir: str) -> Blocks:
    """A workload's sides in blocks, written once an application too."""
    at = (spark.sparkContext.applicationId, name, sf_dir)
    if at not in _BLOCKS or not all(exists_at(spark, x.blocks[0][0]) for x in (_BLOCKS[at].r, _BLOCKS[at].s) if x.blocks):
        w = W[name]
        r, s, _ = sides(w, spark, sf_dir)
        _BLOCKS[at] = write_blocks(r, s, w.tokens, w.bag)
    return _BLOCKS[at]


# Equivalent SQL


def _element_list(tokens: str, d: Duck, x: str = "text") -> str:
    return {
        "words": d.words(x),
        "spaces": d.split(x, " "),
        "chars": f"list_distinct(string_split({x}, ''))",
        "qgrams": f"list_transform(range(1, length({x})), lambda i: substr({x}, i, 2))",
    }[tokens]


def elements_sql(w: Workload, side: str, d: Duck) -> str:
    rows = f"SELECT id, unnest({_element_list(w.tokens, d)}) AS tok FROM {side}"
    if not w.bag:
        return f"SELECT DISTINCT id, tok FROM ({rows})"
    return f"SELECT id, CASE WHEN occ = 1 THEN tok ELSE tok || chr(31) || occ END AS tok FROM (SELECT id, tok, row_number() OVER (PARTITION BY id, tok) AS occ FROM ({rows}))"


def key_sql(sim: SetSimilarity) -> str:
    a, b = sim.alpha.numerator, sim.alpha.denominator
    num, den = {
        "jaccard": ("o", "nr + ns - o"), "overlap": ("o", "greatest(nr, ns)"), "dice": ("2 * o", "nr + ns"),
        "cosine": ("o * o", "nr * ns"), "tversky": (f"{b} * o", f"{a} * nr + {b - a} * ns"),
    }[sim.name]
    return f"(({num})::DOUBLE / ({den}))"


def pairs_sql(name: str, sim: SetSimilarity | None = None, truth: bool = True) -> str:
    """CTEs ``r, s, c, er, es, pairs``, to follow WITH (RECURSIVE)."""
    w, d = W[name], Duck()
    c = f", c AS ({w.c(d)})" if w.c and truth else ""
    return f"""r AS ({w.r(d)}), s AS ({w.s(d)}){c},
  er AS MATERIALIZED ({elements_sql(w, 'r', d)}), es AS MATERIALIZED ({elements_sql(w, 's', d)}),
  nr AS (SELECT id, count(*) AS nr FROM er GROUP BY id), ns AS (SELECT id, count(*) AS ns FROM es GROUP BY id),
  shared AS (SELECT er.id AS r, es.id AS s, count(*) AS o FROM er JOIN es ON er.tok = es.tok GROUP BY er.id, es.id),
  pairs AS MATERIALIZED (SELECT r, s, o, nr, ns, {key_sql(sim or w.sim)} AS key FROM shared JOIN nr ON nr.id = r JOIN ns ON ns.id = s)"""


#: CTEs after ``pairs``: the state at every level.
STATE_SQL = """br AS (SELECT r, max(key) AS best FROM pairs GROUP BY r), bs AS (SELECT s, max(key) AS best FROM pairs GROUP BY s),
  piv AS (SELECT p.key, count(*) AS mutual FROM pairs p JOIN br ON p.r = br.r JOIN bs ON p.s = bs.s WHERE p.key = br.best AND p.key = bs.best GROUP BY p.key),
  lv AS (SELECT key, count(*) AS n FROM pairs GROUP BY key),
  cr AS (SELECT best AS key, count(*) AS n FROM br GROUP BY best), cs AS (SELECT best AS key, count(*) AS n FROM bs GROUP BY best),
  state AS MATERIALIZED (SELECT lv.key, piv.key IS NOT NULL AS pivotal,
    sum(lv.n) OVER (ORDER BY lv.key DESC)::BIGINT AS n_join, coalesce(sum(cr.n) OVER (ORDER BY lv.key DESC), 0)::BIGINT AS cov_r,
    coalesce(sum(cs.n) OVER (ORDER BY lv.key DESC), 0)::BIGINT AS cov_s, coalesce(sum(piv.mutual) OVER (ORDER BY lv.key DESC), 0)::BIGINT AS mutual,
    (SELECT count(*) FROM r) AS size_r, (SELECT count(*) FROM s) AS size_s
    FROM lv LEFT JOIN piv ON piv.key = lv.key LEFT JOIN cr ON cr.key = lv.key LEFT JOIN cs ON cs.key = lv.key)"""

#: CTEs after these: score and bound of the outer size at every level.
OUTER_SQL = """scored AS (SELECT *, cov_r + cov_s - n_join - size_r - size_s AS h, cov_r + cov_s - n_join - size_r - size_s + least(size_r - cov_r, size_s - cov_s) AS bound FROM state)"""

#: CTEs after ``state``: matched groups at the pivotal levels, by label propagation on the graph of each.
GROUPS_SQL = """edge AS MATERIALIZED (SELECT piv.key AS k, 2 * p.r::HUGEINT AS a, 2 * p.s::HUGEINT + 1 AS b FROM piv JOIN pairs p ON p.key >= piv.key),
  sym AS MATERIALIZED (SELECT k, a, b FROM edge UNION ALL SELECT k, b, a FROM edge),
  lab(k, v, l) USING KEY (k, v) AS (
    SELECT DISTINCT k, a, a FROM sym
    UNION
    SELECT x.k, x.v, min(x.l) FROM (SELECT sym.k, sym.b AS v, lab.l FROM lab JOIN sym ON lab.k = sym.k AND lab.v = sym.a) x
      JOIN recurring.lab cur ON cur.k = x.k AND cur.v = x.v WHERE x.l < cur.l GROUP BY x.k, x.v
  ),
  grp AS MATERIALIZED (SELECT k AS key, count(DISTINCT l) AS groups FROM lab GROUP BY k),
  scored AS (SELECT state.*, groups AS h, groups + least(size_r - cov_r, size_s - cov_s) AS bound FROM state JOIN grp ON grp.key = state.key)"""


def theta_sql(sim: SetSimilarity) -> str:
    return "sqrt(key)" if sim.name == "cosine" else "key"
