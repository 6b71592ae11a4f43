"""DuckDB SQL for comparison, generated by unrolling rounds, epochs and features."""

from __future__ import annotations

from collections.abc import Sequence

FEW = ("x1", "x2", "x6", "x7")
D = len(FEW) + 1
EPS = "1.0e-12"

#: Order lines with keys, features, labels and the test flag.
BASE = """base AS MATERIALIZED (
  SELECT *, CASE WHEN late <> flipped THEN 1.0e0 ELSE 0.0e0 END AS label, CASE WHEN late THEN 1.0e0 ELSE 0.0e0 END AS clean_label, mix % 7 = 0 AS is_test
  FROM (SELECT l_orderkey AS k1, l_partkey AS k2, l_suppkey AS k3, l_linenumber AS k4, l_extendedprice AS k5, l_linestatus, l_shipdate,
    CAST(l_quantity AS DOUBLE) AS x1, CAST(l_extendedprice AS DOUBLE) AS x2,
    CAST(datediff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) AS DOUBLE) AS x6, CAST(datediff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS DOUBLE) AS x7,
    l_shipdate > o_orderdate AS late, (l_orderkey * 31 + l_linenumber * 7 + l_suppkey * 13 + l_partkey) % 100 < 15 AS flipped,
    l_orderkey * 7919 + l_partkey * 104729 + l_suppkey * 1299709 + CAST(l_linenumber AS BIGINT) * 15485863 AS mix
    FROM lineitem JOIN orders ON l_orderkey = o_orderkey))"""

#: The same with four features scaled by the training rows, ten clients by supplier, three sub-servers, two static clusters.
SCALED = (
    BASE
    + """,
few AS MATERIALIZED (
  SELECT k1, k2, k3, k4, k5, label, is_test, mix, CAST(k3 % 10 AS INTEGER) AS client_id, CAST((k3 % 10) % 3 AS INTEGER) AS subserver_id, CAST(CASE WHEN x1 > 25 THEN 1 ELSE 0 END AS INTEGER) AS cluster_id, """
    + ", ".join(f"(b.{c} - m_{c}) / s_{c} AS {c}" for c in FEW)
    + " FROM base b, (SELECT "
    + ", ".join(f"avg({c}) AS m_{c}, stddev_samp({c}) AS s_{c}" for c in FEW)
    + " FROM base WHERE NOT is_test))"
)

#: The literal vector at which rows are scored.
AT = (0.1, 0.2, -0.1, 0.9, -0.8)


def margin(w: tuple[float, ...] | str = AT, a: str = "", features: Sequence[str] = FEW) -> str:
    """Linear score; w: numbers, or a table's name whose columns are w0, w1, ..."""
    parts = [f"{x!r}e0" for x in w] if not isinstance(w, str) else [f"{w}.w{k}" for k in range(len(features) + 1)]
    return " + ".join([f"({parts[0]})", *(f"{a}{c} * ({p})" for c, p in zip(features, parts[1:], strict=True))])


def sigmoid(z: str) -> str:
    return f"(1.0e0 / (1.0e0 + exp(-greatest(least({z}, 30.0e0), -30.0e0))))"


def tidy(x: str, name: str, digits: int = 6) -> str:
    return f"round({x}, {digits}) + 0.0e0 AS {name}"


SCORED = f"{SCALED},\nscored AS MATERIALIZED (SELECT k1, k2, k3, k4, k5, client_id, label, {sigmoid(margin())} AS score FROM few WHERE is_test)"

COLUMNS = ", ".join(f"w{k}" for k in range(D))


def merge(name: str, source: str, parent: str, rule: str, total: str | None = None, width: int = D) -> list[str]:
    """CTEs that merge members (parent, n, w0, ...) of a source; the last one is ``name`` (parent, n, w0, ...)."""
    over = f"OVER (PARTITION BY {parent})"
    whole = total or f"sum(n) {over}"
    means = ", ".join(f"sum(w{k} * n / tt) {over} AS m{k}" for k in range(width))
    distance = "sqrt(" + " + ".join(f"(w{k} - m{k}) * (w{k} - m{k})" for k in range(width)) + ")"
    weights = {"proportional": "r / rr", "complement": "(1.0e0 - r / rr) / (mm - 1)", "inverse": f"(1.0e0 / greatest(r, {EPS} * (1.0e0 + rr))) / sum(1.0e0 / greatest(r, {EPS} * (1.0e0 + rr))) {over}", "samples": "s", "uniform": "1.0e0 / mm"}
    guard = weights[rule] if rule in ("samples", "uniform") else f"CASE WHEN mm = 1 OR rr <= {EPS} THEN s ELSE {weights[rule]} END"
    return [
        f"{name}_t AS MATERIALIZED (SELECT *, CAST(n AS DOUBLE) / sum(n) {over} AS s, CAST({whole} AS DOUBLE) AS tt FROM {source})",
        f"{name}_m AS MATERIALIZED (SELECT *, {means} FROM {name}_t)",
        f"{name}_r AS MATERIALIZED (SELECT *, {distance} AS r FROM {name}_m)",
        f"{name}_a AS MATERIALIZED (SELECT *, sum(r) {over} AS rr, count(*) {over} AS mm FROM {name}_r)",
        f"{name}_w AS MATERIALIZED (SELECT *, {guard} AS weight FROM {name}_a)",
        f"{name} AS MATERIALIZED (SELECT {parent}, sum(n) AS n, {', '.join(f'sum(w{k} * weight) AS w{k}' for k in range(width))} FROM {name}_w GROUP BY {parent})",
    ]


#: A sample's slope by its linear score, for each loss.
SLOPES = {"logistic": "{s} - y", "squared": "({z}) - y", "hinge": "CASE WHEN (2 * y - 1) * ({z}) < 1 THEN 1 - 2 * y ELSE 0.0e0 END"}

#: The rows that the small training queries read.
ROWS = "SELECT client_id, subserver_id, cluster_id, label AS y, k1, k2, k3, k4, k5, " + ", ".join(FEW) + " FROM few WHERE NOT is_test"


def training_ctes(
    rounds: int, epochs: int = 1, lr: float = 0.5, split: bool = True, local_mode: str = "params", client_rule: str = "proportional", server_rule: str = "proportional", three: bool = False, subserver_rule: str | None = None, sub_share: str = "local", sub_rounds: int = 1,
    only: dict[int, str] | None = None, client_rounds: int = 1, loss: str = "logistic", batch_size: int | None = None, batches: int = 1, source: Sequence[str] = (SCALED,), rows: str = ROWS, features: Sequence[str] = FEW, tag: str = "",
) -> list[str]:
    """CTEs of rounds of training on rows (client_id, subserver_id, cluster_id, y, features), keys too if there are batches; ``at_t`` holds round t's vector.

    only: by round, a condition on client_id. batches: the most that a cluster's rows make, in order of their keys.
    """
    width, names = len(features) + 1, ("1.0e0", *features)
    columns = ", ".join(f"w{k}" for k in range(width))
    cluster, server = "cluster_id" if split else "0", "subserver_id" if three else "0"
    batch = f"(row_number() OVER (PARTITION BY client_id, {cluster} ORDER BY k1, k2, k3, k4, k5) - 1) // {batch_size}" if batch_size else "0"
    n_batches = batches if batch_size else 1
    data = f"{tag}data"
    ctes = [
        *source,
        f"{data} AS MATERIALIZED (SELECT client_id, {server} AS server_id, {cluster} AS part, {batch} AS batch, y, {', '.join(features)} FROM ({rows}))",
        f"{tag}units AS MATERIALIZED (SELECT server_id, client_id, part, count(*) AS n FROM {data} GROUP BY ALL)",
        f"{tag}at_0 AS MATERIALIZED (SELECT DISTINCT server_id, " + ", ".join(f"0.0e0 AS w{k}" for k in range(width)) + f" FROM {tag}units)",
    ]
    before = f"{tag}at_0"
    z = margin("v", "d.", features)
    error = SLOPES[loss].format(s=sigmoid(z), z=z)
    for t in range(1, rounds + 1):
        chosen = f" WHERE {only[t]}" if only and t in only else ""
        for s in range(sub_rounds if three else 1):
            start = f"(SELECT DISTINCT u.client_id, {', '.join(f'b.w{k}' for k in range(width))} FROM {tag}units u JOIN {before} b ON u.server_id = b.server_id{chosen})"
            for c in range(client_rounds):
                name = f"{tag}r{t}_{s}_{c}"
                now = f"{name}_e0"
                ctes.append(f"{name}_o AS MATERIALIZED (SELECT * FROM {start})")
                ctes.append(f"{now} AS MATERIALIZED (SELECT u.client_id, part, u.n, {columns} FROM {tag}units u JOIN {name}_o b ON u.client_id = b.client_id)")
                for e in range(1, (epochs if local_mode == "params" else 1) * n_batches + 1):
                    step = ", ".join(f"avg(e * {c}) AS g{k}" for k, c in enumerate(names))
                    here = f" WHERE d.batch = {(e - 1) % n_batches}" if batch_size else ""
                    ctes.append(f"{name}_g{e} AS MATERIALIZED (SELECT client_id, part, {step} FROM (SELECT d.*, {error} AS e FROM {data} d JOIN {now} v ON d.client_id = v.client_id AND d.part = v.part{here}) GROUP BY client_id, part)")
                    moved = ", ".join(f"w{k} - {lr!r}e0 * coalesce(g{k}, 0.0e0) AS w{k}" if local_mode == "params" else f"g{k} AS w{k}" for k in range(width))
                    ctes.append(f"{name}_e{e} AS MATERIALIZED (SELECT v.client_id, v.part, n, {moved} FROM {now} v LEFT JOIN {name}_g{e} g ON v.client_id = g.client_id AND v.part = g.part)")
                    now = f"{name}_e{e}"
                ctes += merge(f"{name}_c", now, "client_id", client_rule, width=width)
                moved = ", ".join(f"o.w{k} - {lr!r}e0 * c.w{k} AS w{k}" if local_mode == "gradient" else f"c.w{k}" for k in range(width))
                ctes.append(f"{name}_k AS MATERIALIZED (SELECT c.client_id, c.n, {moved} FROM {name}_c c JOIN {name}_o o ON c.client_id = o.client_id)")
                start = f"(SELECT client_id, {columns} FROM {name}_k)"
            members = f"(SELECT u.server_id, c.* FROM {name}_k c JOIN (SELECT DISTINCT server_id, client_id FROM {tag}units) u ON c.client_id = u.client_id)"
            ctes += merge(f"{tag}r{t}_{s}_s", members, "server_id", (subserver_rule or server_rule) if three else server_rule, "sum(n) OVER ()" if three and sub_share == "global" else None, width)
            before = f"{tag}r{t}_{s}_s"
        if three:
            ctes += merge(f"{tag}r{t}_z", f"(SELECT 0 AS centre, n, {columns} FROM {before})", "centre", server_rule, width=width)
            ctes.append(f"{tag}at_{t} AS MATERIALIZED (SELECT s.server_id, {', '.join(f'z.w{k}' for k in range(width))} FROM (SELECT DISTINCT server_id FROM {tag}units) s, {tag}r{t}_z z)")
        else:
            ctes.append(f"{tag}at_{t} AS MATERIALIZED (SELECT server_id, {columns} FROM {before})")
        before = f"{tag}at_{t}"
    return ctes


def training(rounds: int, *args, **options) -> str:
    """Rounds of training; a row (round, w0, ...) for each."""
    ctes = training_ctes(rounds, *args, **options)
    return "WITH " + ",\n".join(ctes) + "\n" + vectors(rounds, len(options.get("features", FEW)) + 1)


def vectors(rounds: int, width: int = D, tag: str = "", name: str = "") -> str:
    first = f"'{name}' AS method, " if name else ""
    return " UNION ALL ".join(f"(SELECT {first}CAST({t} AS BIGINT) AS round, {', '.join(tidy(f'w{k}', f'w{k}') for k in range(width))} FROM {tag}at_{t} LIMIT 1)" for t in range(1, rounds + 1))


def evaluated(rounds: int, methods: dict[str, str], test: str, features: Sequence[str] = FEW) -> tuple[list[str], str]:
    """CTEs, and a selection of (method, round, accuracy, recall, ks, logloss) on test rows (y, features) of every round; methods: their tags by name."""
    scored = " UNION ALL ".join(f"SELECT '{name}' AS method, CAST({t} AS BIGINT) AS round, y, {margin('v', 'd.', features)} AS z FROM tests d, (SELECT * FROM {tag}at_{t} LIMIT 1) v" for name, tag in methods.items() for t in range(1, rounds + 1))
    ctes = [
        f"tests AS MATERIALIZED ({test})",
        f"scored AS MATERIALIZED ({scored})",
        "points AS (SELECT method, round, z, sum(y) AS p, sum(1 - y) AS n FROM scored GROUP BY ALL)",
        "steps AS (SELECT method, round, sum(p) OVER d / nullif(sum(p) OVER w, 0) - sum(n) OVER d / nullif(sum(n) OVER w, 0) AS gap FROM points WINDOW d AS (PARTITION BY method, round ORDER BY z DESC), w AS (PARTITION BY method, round))",
        "curve AS (SELECT method, round, greatest(coalesce(max(gap), 0), 0) AS ks FROM steps GROUP BY ALL)",
        f"counted AS (SELECT method, round, avg(CASE WHEN (s >= 0.5e0) = (y = 1) THEN 1.0e0 ELSE 0.0e0 END) AS accuracy, count_if(s >= 0.5e0 AND y = 1) / nullif(CAST(count_if(y = 1) AS DOUBLE), 0) AS recall, avg(-ln(CASE WHEN y = 1 THEN s ELSE 1 - s END)) AS loss FROM (SELECT *, {sigmoid('z')} AS s FROM scored) GROUP BY ALL)",
    ]
    return ctes, f"SELECT c.method, c.round, {tidy('accuracy', 'accuracy')}, {tidy('recall', 'recall')}, {tidy('ks', 'ks')}, {tidy('loss', 'logloss')} FROM counted c JOIN curve k ON c.method = k.method AND c.round = k.round"


def one_merge(rule: str, zero: bool = False) -> str:
    """Ten clients' vectors after one local step, merged; zero: all vectors equal."""
    value = [f"avg(({sigmoid(margin())} - label) * {c})" for c in ("1.0e0", *FEW)]
    columns = ", ".join(f"{'0.25e0' if zero else v} AS w{k}" for k, v in enumerate(value))
    members = f"members AS MATERIALIZED (SELECT 0 AS parent, client_id, count(*) AS n, {columns} FROM few WHERE NOT is_test GROUP BY client_id)"
    return "WITH " + ",\n".join([SCALED, members, *merge("z", "members", "parent", rule)]) + f"\nSELECT CAST(client_id AS INTEGER) AS client_id, {tidy('weight', 'weight')}, {tidy('r', 'deviation')}, " + ", ".join(f"round(z.w{k}, 6) + 0.0e0 AS merged{k}" for k in range(D)) + " FROM z_w CROSS JOIN z"


ROC = """points AS (SELECT score AS threshold, sum(CASE WHEN label = 1 THEN 1 ELSE 0 END) AS p, sum(CASE WHEN label = 0 THEN 1 ELSE 0 END) AS n FROM {source} GROUP BY score
  UNION ALL SELECT CAST('infinity' AS DOUBLE), 0, 0),
roc AS (SELECT threshold, CAST(sum(p) OVER w AS BIGINT) AS tp, CAST(sum(n) OVER w AS BIGINT) AS fp, sum(p) OVER w / CAST(sum(p) OVER () AS DOUBLE) AS tpr, sum(n) OVER w / CAST(sum(n) OVER () AS DOUBLE) AS fpr
  FROM points WINDOW w AS (ORDER BY threshold DESC ROWS UNBOUNDED PRECEDING))"""


def tile_counts(order: str, k: int = 20) -> str:
    """Clients by ntile over a global order: rows, label rate, and sums that tell rows apart."""
    return f"WITH {BASE}\nSELECT CAST(client_id AS INTEGER) AS client_id, count(*) AS n, round(avg(label), 6) + 0.0e0 AS rate, CAST(sum(mix % 1000003) AS BIGINT) AS mark FROM (SELECT *, ntile({k}) OVER (ORDER BY {order}, k1, k2, k3, k4, k5) - 1 AS client_id FROM base WHERE NOT is_test) GROUP BY client_id"


def client_counts(expression: str) -> str:
    return f"WITH {BASE}\nSELECT CAST(client_id AS INTEGER) AS client_id, count(*) AS n, round(avg(label), 6) + 0.0e0 AS rate, CAST(sum(mix % 1000003) AS BIGINT) AS mark FROM (SELECT *, {expression} AS client_id FROM base WHERE NOT is_test) GROUP BY client_id"


STRUCT = "{'a': k1, 'b': k2, 'c': k3, 'd': k4, 'e': k5}"
_DISTANCE = "sqrt(" + " + ".join(f"({{0}}.{c} - {{1}}.{c}) * ({{0}}.{c} - {{1}}.{c})" for c in FEW) + ")"

#: What the first centre is the least of, by rule.
SEEDS = {"first": STRUCT, "medoid": "{'d': " + " + ".join(f"{c} * {c}" for c in FEW) + ", 'k': " + STRUCT + "}", "hash": "{'m': md5(concat_ws('|', " + ", ".join(f"CAST(k{k} AS VARCHAR)" for k in range(1, 6)) + ")), 'k': " + STRUCT + "}"}


def splitting(centres: int, cap: str = "1000000", clients: int = 10, seed: str = "first", tag: str = "", source: str | None = None) -> list[str]:
    """CTEs of max-min growth within clients up to a number of centres: ``s_j``, rows with nearest and cluster_id after j centres, ``c_j``, the j-th centres, and ``fars`` (client_id, j, far, gap, n): how far from j centres the next one lies.

    cap: an expression of {n}, a client's rows, that bounds its centres. source: training rows with client_id, in place of
    owners by a key's remainder. Names begin with the tag.
    """
    z = ", ".join(f"CASE WHEN stddev_samp({c}) OVER w > 0 THEN ({c} - avg({c}) OVER w) / stddev_samp({c}) OVER w ELSE 0.0e0 END AS {c}" for c in FEW)
    point = lambda of: ", ".join(f"arg_min({c}, {of}) AS {c}" for c in FEW)
    far_key = "{'d': -nearest, 'k': " + STRUCT + "}"
    ctes = [
        f"{tag}own AS MATERIALIZED (SELECT k1, k2, k3, k4, k5, client_id, {z} FROM {source or f'(SELECT *, CAST(k3 % {clients} AS INTEGER) AS client_id FROM base WHERE NOT is_test)'} WINDOW w AS (PARTITION BY client_id))",
        f"{tag}c_1 AS MATERIALIZED (SELECT client_id, {point(SEEDS[seed])}, count(*) AS n FROM {tag}own GROUP BY client_id)",
        f"{tag}s_1 AS MATERIALIZED (SELECT r.*, {_DISTANCE.format('r', 'p')} AS nearest, 0 AS cluster_id FROM {tag}own r JOIN {tag}c_1 p ON r.client_id = p.client_id)",
    ]
    for j in range(1, centres):
        ctes += [
            f"{tag}c_{j + 1} AS MATERIALIZED (SELECT client_id, {point(far_key)}, max(nearest) AS far, count(*) AS n FROM {tag}s_{j} GROUP BY client_id HAVING max(nearest) > 0 AND {j} < {cap.format(n='count(*)')})",
            f"{tag}d_{j + 1} AS (SELECT r.*, {_DISTANCE.format('r', 'p')} AS dd FROM {tag}s_{j} r LEFT JOIN {tag}c_{j + 1} p ON r.client_id = p.client_id)",
            f"{tag}s_{j + 1} AS MATERIALIZED (SELECT k1, k2, k3, k4, k5, client_id, {', '.join(FEW)}, CASE WHEN dd < nearest THEN dd ELSE nearest END AS nearest, CASE WHEN dd < nearest THEN {j} ELSE cluster_id END AS cluster_id FROM {tag}d_{j + 1})",
        ]
    fars = " UNION ALL ".join(f"SELECT client_id, {j} AS j, far FROM {tag}c_{j + 1}" for j in range(1, centres)) if centres > 1 else f"SELECT client_id, 1 AS j, 0.0e0 AS far FROM {tag}c_1 WHERE false"
    # centres follow one another as long as each lies far enough, and ever nearer
    ctes.append(f"{tag}fars AS MATERIALIZED (SELECT *, max(far) OVER (PARTITION BY client_id) AS gap FROM ({fars}))")
    return ctes


def grown(centres: int, theta: float | None, name: str, tag: str = "") -> list[str]:
    """CTEs of the split at one theta: ``name_j`` (client_id, j: its number of centres) and ``name`` (rows with cluster_id, nearest)."""
    enough = f"j = 1 OR far > {theta!r}e0 * gap" if theta else "true"
    rows = " UNION ALL ".join(f"SELECT s.* FROM {tag}s_{j} s JOIN {name}_j g ON s.client_id = g.client_id AND g.j = {j}" for j in range(1, centres + 1))
    return [
        f"{name}_j AS MATERIALIZED (SELECT c.client_id, 1 + count_if(f.j IS NOT NULL AND ({enough.replace('j =', 'f.j =')})) AS j FROM {tag}c_1 c LEFT JOIN {tag}fars f ON c.client_id = f.client_id GROUP BY c.client_id)",
        f"{name} AS MATERIALIZED ({rows})",
    ]


def accepting(centres: int, name: str, tag: str = "") -> list[str]:
    """CTEs of the figures of a split: ``name_f`` (client_id, j, overall, spread, gap), over all pairs of rows."""
    pairs = f"SELECT a.client_id, a.cluster_id AS ca, b.cluster_id AS cb, {_DISTANCE.format('a', 'b')} AS d FROM {name}_n a JOIN {name}_n b ON a.client_id = b.client_id AND a.rn < b.rn"
    points = " UNION ALL ".join(f"SELECT client_id, {j} AS j, {', '.join(FEW)} FROM {tag}c_{j}" for j in range(1, centres + 1))
    return [
        f"{name}_n AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY client_id) AS rn FROM {name})",
        f"{name}_m AS MATERIALIZED (SELECT client_id, sum(d) / sum(c) AS overall, coalesce(max(CASE WHEN own THEN d / c END), 0) AS spread FROM (SELECT client_id, ca = cb AS own, CASE WHEN ca = cb THEN ca ELSE -1 END AS cluster_id, sum(d) AS d, CAST(count(*) AS DOUBLE) AS c FROM ({pairs}) GROUP BY ALL) GROUP BY client_id)",
        f"{name}_c AS MATERIALIZED (SELECT p.* FROM ({points}) p JOIN {name}_j g ON p.client_id = g.client_id AND p.j <= g.j)",
        f"{name}_g AS (SELECT a.client_id, min({_DISTANCE.format('a', 'b')}) AS gap FROM {name}_c a JOIN {name}_c b ON a.client_id = b.client_id AND a.j < b.j GROUP BY a.client_id)",
        f"{name}_f AS MATERIALIZED (SELECT j.client_id, j.j, overall, spread / overall AS spread, coalesce(gap, 0) / overall AS gap FROM {name}_j j JOIN {name}_m m ON j.client_id = m.client_id LEFT JOIN {name}_g g ON j.client_id = g.client_id)",
    ]
