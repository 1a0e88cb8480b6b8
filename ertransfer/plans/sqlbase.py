"""The tasks and the encoder in DuckDB's SQL, as common table expressions that the oracles build on."""

from __future__ import annotations

from ertransfer.plans.tasks import DIRT, REACH, TASKS, WIDTH


def h32(expr: str) -> str:
    return f"('0x' || substr(md5({expr}), 1, 8))::BIGINT"


def dims(width: int = WIDTH) -> str:
    return f"range(1, {width + 1})"


def text(x: str) -> str:
    return f"array_to_string({x}, ',')"


def _sources() -> str:
    out = []
    for name, (table, where, key, attributes, block, _) in TASKS.items():
        out.append(f"SELECT '{name}' AS dataset, {key}::BIGINT AS id, concat_ws(' ', {', '.join(attributes)}) AS doc, concat_ws('|', {', '.join(block)}) AS block FROM {table} WHERE {where}")
    return " UNION ALL ".join(out)


_LIMIT = "CASE dataset " + " ".join(f"WHEN '{d}' THEN {n}" for d, n in DIRT.items()) + " ELSE 10 END"
_NEAR = "k.dataset = u.dataset AND k.id = u.id AND abs(k.pos - u.pos) <= 5 AND k.pos <> u.pos"


def words(doc: str) -> str:
    return f"list_filter(string_split_regex(lower({doc}), '[^\\p{{L}}\\p{{N}}]+'), lambda x: x <> '')"


def base(width: int = WIDTH) -> str:
    return f"""WITH src AS ({_sources()}),
wds AS (SELECT dataset, id, {words("doc")} AS l FROM src),
tok AS (SELECT dataset, id, unnest(l) AS token, unnest(range(len(l))) AS pos FROM wds),
tokr AS (SELECT * FROM tok WHERE {h32("'d:' || dataset || ':' || id || ':' || pos")} % 100 >= {_LIMIT}),
freq AS (SELECT token, count(*) AS n, count(*) / (SELECT count(*) FROM tok)::DOUBLE AS p FROM tok GROUP BY token),
emb AS (SELECT vec_id AS k, embedding::DOUBLE[] AS e FROM embeddings),
top AS (SELECT max(k) + 1 AS n FROM emb),
known AS (SELECT token, {h32("'a:' || token")} % (SELECT n FROM top) AS ka, {h32("'b:' || token")} % (SELECT n FROM top) AS kb FROM freq WHERE {h32("'oov:' || token")} % 10 <> 0),
dict AS (SELECT token, list_transform({dims(width)}, lambda i: round((a.e[i] + b.e[i]) / sqrt(2.0) * 1000000)::BIGINT) AS vec FROM known JOIN emb a ON a.k = ka JOIN emb b ON b.k = kb),
dlong AS (SELECT token, unnest({dims(width)}) AS i, unnest(vec) AS v FROM dict),
oov AS (SELECT token FROM freq ANTI JOIN dict USING (token)),
occ AS (SELECT u.token, u.dataset, u.id, u.pos, d.i, round(sum(d.v)::DOUBLE / count(*))::BIGINT AS v FROM tok u SEMI JOIN oov ON oov.token = u.token JOIN tok k ON {_NEAR} JOIN dlong d ON d.token = k.token GROUP BY ALL),
ctxl AS (SELECT token, i, round(sum(v)::DOUBLE / count(*))::BIGINT AS v FROM occ GROUP BY token, i),
ctx AS (SELECT token, list(v ORDER BY i) AS vec FROM ctxl GROUP BY token),
xlong AS (SELECT token, i, v, round(1000000 * 0.0001 / (0.0001 + p))::BIGINT AS w FROM (SELECT * FROM dlong UNION ALL SELECT * FROM ctxl) JOIN freq USING (token)),
nl AS (SELECT dataset, id, count(*) AS n_tokens, string_agg(token, ' ' ORDER BY pos) AS doc FROM tok GROUP BY dataset, id),
nr AS (SELECT dataset, id, count(*) AS n_tokens, string_agg(token, ' ' ORDER BY pos) AS doc FROM tokr GROUP BY dataset, id),
ordered AS (SELECT dataset, block, id, side, row_number() OVER (PARTITION BY dataset, block ORDER BY doc, side, id) AS at FROM (SELECT dataset, block, id, nl.doc, 0 AS side FROM nl JOIN src USING (dataset, id) UNION ALL SELECT dataset, block, id, nr.doc, 1 FROM nr JOIN src USING (dataset, id))),
cand AS (SELECT l.dataset, l.id AS id_l, r.id AS id_r, (l.id = r.id)::INT AS y FROM ordered l JOIN ordered r ON l.dataset = r.dataset AND l.block = r.block AND r.at BETWEEN l.at - {REACH} AND l.at + {REACH} WHERE l.side = 0 AND r.side = 1),
{encoded("encl", "tok", "nl", "xlong", "v * w", "/ 1000000", width)},
{encoded("encr", "tokr", "nr", "xlong", "v * w", "/ 1000000", width)},
sim AS (SELECT c.dataset, c.id_l, c.id_r, c.y, list_transform({dims(width)}, lambda i: abs(l.x[i] - r.x[i])) AS x FROM cand c JOIN encl l ON l.dataset = c.dataset AND l.id = id_l JOIN encr r ON r.dataset = c.dataset AND r.id = id_r),
cut AS (SELECT *, dataset || ':' || id_l || ':' || id_r AS key, {h32("'split:' || dataset || ':' || id_l || ':' || id_r")} % 100 AS h FROM sim)
"""


def encoded(name: str, tokens: str, sizes: str, long: str, value: str, by: str, width: int = WIDTH, extra: str = "") -> str:
    """A table expression (dataset, id, n_tokens, x) of tuple vectors."""
    zeros = f"list_transform({dims(width)}, lambda i: 0::BIGINT)"
    return f"""{name} AS (SELECT s.dataset, s.id, s.n_tokens, coalesce(x, {zeros}) AS x FROM {sizes} s LEFT JOIN (
  SELECT dataset, id, list(round(s::DOUBLE / n_tokens {by})::BIGINT ORDER BY i) AS x FROM (SELECT t.dataset, t.id, i, sum({value})::BIGINT AS s FROM {tokens} t JOIN {long} d ON d.token = t.token {extra} GROUP BY t.dataset, t.id, i) JOIN {sizes} USING (dataset, id) GROUP BY dataset, id) USING (dataset, id))"""


def phi_s(x: str, width: int, i: int = 1, n: int = 1) -> str:
    return f"list_concat({x}, {_zeros((i - 1) * width)}, {x}, {_zeros((n - i + 1) * width)})"


def phi_t(x: str, width: int, n: int = 1) -> str:
    return f"list_concat({x}, {_zeros(n * width)}, {x})"


def phi_u(x: str, width: int, n: int = 1, i: int | None = None) -> str:
    i = i or n
    return f"list_concat({_zeros(i * width)}, {x}, {_zeros((n - i) * width)}, list_transform({x}, lambda v: -v))"


def _zeros(n: int) -> str:
    return f"list_transform(range({n}), lambda i: 0::BIGINT)"


def bayes(train: str, test: str, tag: str = "") -> str:
    """Expressions up to ``scored{tag}`` (key, truth, p): naive Bayes of ``train`` (z, y, w) on ``test`` (key, truth, z)."""
    return f"""train{tag} AS ({train}), test{tag} AS ({test}),
long{tag} AS (SELECT y, w, unnest(z)::DOUBLE AS v, unnest(range(len(z))) AS i FROM train{tag}),
fit{tag} AS (SELECT y, i, sum(w * v) / sum(w) AS m, greatest(10000.0, sum(w * v * v) / sum(w) - power(sum(w * v) / sum(w), 2)) AS s FROM long{tag} GROUP BY y, i),
prior{tag} AS (SELECT y, sum(w) / (SELECT sum(w) FROM train{tag}) AS q FROM train{tag} GROUP BY y),
cells{tag} AS (SELECT key, truth, unnest(z)::DOUBLE AS v, unnest(range(len(z))) AS i FROM test{tag}),
sides{tag} AS (SELECT key, truth, f.y, ln(max(q)) - 0.5 * sum(ln(s) + (v - m) * (v - m) / s) AS g FROM cells{tag} JOIN fit{tag} f USING (i) JOIN prior{tag} p ON p.y = f.y GROUP BY key, truth, f.y),
scored{tag} AS (SELECT key, truth, 1 / (1 + exp(greatest(-500.0, least(500.0, sum(CASE WHEN y = 0 THEN g ELSE -g END))))) AS p FROM sides{tag} GROUP BY key, truth)"""


def confusion(scored: str, by: str = "", hit: str = "p >= 0.5") -> str:
    group = f" GROUP BY {by}" if by else ""
    pick = f"{by}, " if by else ""
    return f"SELECT {pick}count(*) FILTER ({hit} AND truth = 1) AS tp, count(*) FILTER ({hit} AND truth = 0) AS fp, count(*) FILTER (NOT ({hit}) AND truth = 1) AS fn, count(*) FILTER (NOT ({hit}) AND truth = 0) AS tn FROM {scored}{group}"


PRF = "round(coalesce(tp::DOUBLE / nullif(tp + fp, 0), 0), 6) AS precision, round(coalesce(tp::DOUBLE / nullif(tp + fn, 0), 0), 6) AS recall, round(coalesce(2.0 * tp / nullif(2.0 * tp + fp + fn, 0), 0), 6) AS f"
MCC = "round(coalesce((tp::DOUBLE * tn - fp::DOUBLE * fn) / nullif(sqrt((tp + fp)::DOUBLE * (tp + fn) * (tn + fp) * (tn + fn)), 0), 0), 6) AS mcc, round(2 * ((tp + tn)::DOUBLE / (tp + fp + fn + tn) - 0.5), 6) AS d_a"
