"""DuckDB SQL for the same runs: hashes, ranks and left-to-right folds give the same bits."""

from __future__ import annotations

from gossamer.config import DescentConfig

POINTS = {
    "line4": "SELECT concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey) AS sample_id, [l_quantity / 50.0::double, l_extendedprice / 105000.0::double, l_discount * 10.0::double, l_tax * 12.5::double] AS x FROM lineitem",
    "emb64": "SELECT vec_id::varchar AS sample_id, embedding::double[] AS x FROM embeddings",
    "evt3": "SELECT event_id::varchar AS sample_id, [value / 600.0::double, hour(ts) / 24.0::double, (props->>'$.k')::double / 100.0::double] AS x FROM events",
}
DIMS = {"line4": 4, "emb64": 64, "evt3": 3}


def documents(buckets: int = 128) -> str:
    """Hashed token counts of each document, of unit length."""
    counts = f"SELECT doc_id, {int_('token')} % {buckets} AS bucket, count(*) AS n FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^a-z0-9]+')) AS token FROM documents) t WHERE token <> '' GROUP BY ALL"
    dense = f"list_transform(range(0, {buckets}), lambda i: coalesce(m[i], 0) / s)"
    return f"SELECT doc_id::varchar AS sample_id, {dense} AS x FROM (SELECT doc_id, map(list(bucket), list(n)) AS m, sqrt(sum(n * n)) AS s FROM ({counts}) c GROUP BY doc_id) d"


def hex_(*key) -> str:
    return f"md5(concat_ws(':', {', '.join(map(str, key))}))"


def int_(*key) -> str:
    return f"('0x' || substr({hex_(*key)}, 1, 8))::bigint"


def fold(terms: str) -> str:
    return f"list_reduce(list_prepend(0.0::double, {terms}), lambda p, q: p + q)"


def d2(a: str, b: str, dims: int) -> str:
    js = list(range(1, dims + 1))
    return fold(f"list_transform({js}, lambda jj: ({a}[jj] - {b}[jj]) * ({a}[jj] - {b}[jj]))")


def scalars(of: str, more: str = "") -> str:
    """Points as ``sample_id, dim, value``."""
    return f"SELECT sample_id, (d - 1)::int AS dim, x[d] AS value FROM ({of}) p, range(1, len(x) + 1) r(d) {more}"


def ranked(points: str, seed: int) -> str:
    return f"SELECT *, row_number() OVER (ORDER BY {hex_(seed, chr(39) + 'part' + chr(39), 'sample_id')}, sample_id) - 1 AS rank FROM ({points}) p"


def parted(points: str, cfg: DescentConfig) -> str:
    n = cfg.workers
    cut = "" if cfg.remainder == "spread" else f"WHERE rank < (SELECT count(*) // {n} * {n} FROM ({points}) q)"
    return f"SELECT sample_id, x, (rank % {n})::int AS worker, rank // {n} AS pos FROM ({ranked(points, cfg.seed)}) r {cut}"


def minibatches(points: str, cfg: DescentConfig) -> str:
    if cfg.partition == "hash":
        own = f"SELECT *, ({int_(cfg.seed, chr(39) + 'part' + chr(39), 'sample_id')} % {cfg.workers})::int AS worker FROM ({points}) p"
        walked = f"SELECT *, row_number() OVER (PARTITION BY worker ORDER BY {hex_(cfg.seed, chr(39) + 'order' + chr(39), 0, 'sample_id')}, sample_id) - 1 AS pos FROM ({own}) o"
        return f"SELECT worker, (pos // {cfg.b})::int AS round, (pos % {cfg.b})::int AS slot, sample_id, x FROM ({walked}) p WHERE pos < {cfg.b * cfg.steps}"
    if cfg.draw == "shuffle":
        per = f"(SELECT count(*) // {cfg.workers} FROM ({points}) q)"
        later = f"SELECT unnest(range(1, ({cfg.b * cfg.steps} + {per} - 1) // {per})) AS epoch"  # a fresh local order each
        again = f"SELECT sample_id, x, worker, row_number() OVER (PARTITION BY worker, epoch ORDER BY {hex_(cfg.seed, chr(39) + 'order' + chr(39), 'epoch', 'sample_id')}, sample_id) - 1 + epoch * {per} AS pos FROM ({parted(points, cfg)}) p, ({later}) l"
        return f"SELECT worker, (pos // {cfg.b})::int AS round, (pos % {cfg.b})::int AS slot, sample_id, x FROM (SELECT sample_id, x, worker, pos FROM ({parted(points, cfg)}) p UNION ALL {again}) e WHERE pos < {cfg.b * cfg.steps}"
    if cfg.draw_from == "global":
        slots = f"SELECT w.i::int AS worker, r.i::int AS round, s.i::int AS slot, {int_(cfg.seed, chr(39) + 'draw' + chr(39), 'w.i', 'r.i', 's.i')} % (SELECT count(*) FROM ({points}) q) AS rank FROM range({cfg.workers}) w(i), range({cfg.steps}) r(i), range({cfg.b}) s(i)"
        return f"SELECT worker, round, slot, sample_id, x FROM ({slots}) s JOIN ({ranked(points, cfg.seed)}) p USING (rank)"
    h = f"(SELECT count(*) // {cfg.workers} FROM ({points}) q)"
    slots = f"SELECT w.i::int AS worker, r.i::int AS round, s.i::int AS slot, {int_(cfg.seed, chr(39) + 'draw' + chr(39), 'w.i', 'r.i', 's.i')} % {h} AS pos FROM range({cfg.workers}) w(i), range({cfg.steps}) r(i), range({cfg.b}) s(i)"
    return f"SELECT worker, round, slot, sample_id, x FROM ({slots}) s JOIN ({parted(points, cfg)}) p USING (worker, pos)"


def acting(workers: int) -> str:
    """The hours in which a worker's users act."""
    return f"SELECT DISTINCT ((user_id % {workers} + {workers}) % {workers})::int AS sender, (epoch_us(ts) // {3600 * 10**6})::int AS sent_round FROM events WHERE user_id IS NOT NULL AND ts IS NOT NULL"


def sends(cfg: DescentConfig, senders: str | None = None) -> str:
    """Messages of a run, or of ``senders (sender, sent_round)``."""
    n, s = cfg.workers, cfg.seed
    to, age, buf = int_(s, "'to'", "w.i", "t.i"), int_(s, "'age'", "w.i", "t.i", "c.i"), int_(s, "'buffer'", "w.i", "t.i", "c.i")
    gone = "false" if cfg.comm == "silent" or n < 2 else "true"
    own = cfg.threads if cfg.scope == "other_node" else 1
    base = f"(w.i // {own} * {own} + {own - 1})"
    old = f"{age} % {cfg.max_age}" if cfg.delay == "uniform" else " + ".join(["0", *[f"({age} % {2**a} = 0)::int" for a in range(1, cfg.max_age)]])
    of = f"range({n}) w(i), range({cfg.steps}) t(i), range({cfg.fanout}) c(i) WHERE {gone} AND (t.i + 1) % {cfg.comm_every} = 0"
    if senders is not None:
        of = f"(SELECT {{'i': sender}} AS w, {{'i': sent_round}} AS t FROM ({senders}) a) q, range({cfg.fanout}) c(i)"
    return f"SELECT w.i::int AS sender, t.i::int AS sent_round, (({base} + 1 + ({to} + c.i) % {max(1, n - own)}) % {n})::int AS recipient, (t.i + 1 + {old})::int AS due_round, ({buf} % {cfg.buffers})::int AS buffer FROM {of}"


def blocks(cfg: DescentConfig, senders: str | None = None) -> str:
    share = max(1, round(cfg.block_frac * cfg.k))
    every = f"SELECT m.*, b.i::int AS block FROM ({sends(cfg, senders)}) m, range({cfg.k}) b(i)"
    if share >= cfg.k:
        return every
    order = f"dense_rank() OVER (PARTITION BY sender, sent_round ORDER BY {hex_(cfg.seed, chr(39) + 'block' + chr(39), 'sender', 'sent_round', 'block')}, block)"
    return f"SELECT sender, sent_round, recipient, due_round, buffer, block FROM (SELECT *, {order} AS nn FROM ({every}) e) f WHERE nn <= {share}"


def settled(cfg: DescentConfig, senders: str | None = None) -> str:
    """What stands in the buffers when they are read."""
    keep = {"none": "true", "overwrite": "last = (sent_round, sender)", "torn": "last = (sent_round, sender)"}[cfg.race]
    per = "recipient, due_round, buffer" + ", block" * (cfg.race == "torn")
    return f"SELECT DISTINCT recipient, due_round AS round, buffer, block, sender, sent_round FROM (SELECT *, max((sent_round, sender)) OVER (PARTITION BY {per}) AS last FROM ({blocks(cfg, senders)}) b) c WHERE {keep}"


def inbox(cfg: DescentConfig, senders: str | None = None) -> str:
    """The settled mail of a run, or of ``senders`` up to the last round in which one sends."""
    stood = f"{settled(cfg, senders)} AND due_round < {cfg.steps if senders is None else f'(SELECT max(sent_round) + 1 FROM ({senders}) a)'}"
    if cfg.consume:
        return stood
    keys = "recipient, buffer" + ", block" * (cfg.race == "torn")
    return f"SELECT m.recipient, t.i::int AS round, m.buffer, m.block, m.sender, m.sent_round FROM ({stood}) m JOIN (SELECT {keys}, round, lead(round, 1, {cfg.steps}) OVER (PARTITION BY {keys} ORDER BY round) AS until FROM (SELECT DISTINCT {keys}, round FROM ({stood}) d) e) u USING ({keys}, round) JOIN range({cfg.steps}) t(i) ON t.i >= m.round AND t.i < u.until"


def initial(points: str, cfg: DescentConfig) -> str:
    if cfg.loss != "prototypes":
        return f"SELECT [list_transform(x[1:len(x) - 1], lambda v: 0.0::double)] AS w FROM ({points}) p LIMIT 1"
    if cfg.init == "sample":
        at = f"SELECT c, {int_(cfg.seed, chr(39) + 'sample' + chr(39), 'c')} % (SELECT count(*) FROM ({points}) q) AS rank FROM range({cfg.k}) r(c)"
        return f"SELECT list(x ORDER BY c) AS w FROM ({at}) a JOIN ({ranked(points, cfg.seed)}) b USING (rank)"
    return f"SELECT list(x ORDER BY h, sample_id) AS w FROM (SELECT x, sample_id, {hex_(cfg.seed, chr(39) + 'init' + chr(39), 'sample_id')} AS h FROM ({points}) p ORDER BY h, sample_id LIMIT {cfg.k}) i"


def run(points: str, cfg: DescentConfig, dims: int, select: str) -> str:
    """``select`` reads ``done (worker, w, received, good)``, the workers after the last round, or ``walk`` and ``pts``."""
    cs, js = list(range(1, cfg.k + 1)), list(range(1, dims + 1))
    sync = cfg.comm == "sync"
    pair = lambda left: fold(f"flatten(list_transform(list_filter({cs}, lambda c: e.e[c] IS NOT NULL), lambda c: list_transform({js}, lambda j: ({left} - e.e[c][j]) * ({left} - e.e[c][j]))))")
    there = ["true"]
    if cfg.window_scope == "state":
        there.append(f"len(list_filter({cs}, lambda c: e.e[c] IS NULL)) = 0")
    if cfg.empty_rule == "zero_norm":
        there.append(f"len(list_filter({cs}, lambda c: e.e[c] IS NOT NULL AND len(list_filter(e.e[c], lambda v: v <> 0)) > 0)) > 0")
    if cfg.window:
        there.append(f"{pair(f'(w[c][j] - {cfg.eps}::double * g[c][j])')} < {pair('w[c][j]')}")
    window = f"list_filter(es, lambda e: {' AND '.join(there)})"
    summed = "list_reduce(list_prepend(w[c][j], list_transform(list_filter(ok, lambda e: e.e[c] IS NOT NULL), lambda e: e.e[c][j])), lambda p, q: p + q)"
    count = "(1 + len(list_filter(ok, lambda e: e.e[c] IS NOT NULL)))"
    modified = f"((w[c][j] - {summed} / {count}) + g[c][j])"
    over = {"mean": {"batch": " / len(xs)", "cluster": " / greatest(len(list_filter(near, lambda v: v = c)), 1)"}[cfg.normalise], "sum": ""}[cfg.reduce]
    if cfg.loss == "prototypes":
        g = f"list_transform({cs}, lambda c: list_transform({js}, lambda j: {fold('list_transform(range(1, len(xs) + 1), lambda s: CASE WHEN near[s] = c THEN w[c][j] - xs[s][j] ELSE 0.0::double END)')}{over}))"
        each, near = "list_transform(xs, lambda x: list_transform(w, lambda c: " + d2("x", "c", dims) + "))", "list_transform(ds, lambda d: list_position(d, list_min(d)))"
    else:
        score = fold(f"list_transform({js}, lambda j: x[j] * w[1][j])")
        value = score if cfg.loss == "squares" else f"1.0::double / (1.0::double + exp(-({score})))"
        each, near = f"list_transform(xs, lambda x: {value} - x[{dims + 1}])", "ds"
        g = f"list_transform({cs}, lambda c: list_transform({js}, lambda j: {fold('list_transform(range(1, len(xs) + 1), lambda s: near[s] * xs[s][j])')}{over}))"
    moved = f"w[c][j] - {cfg.eps}::double * {modified}" if cfg.blend_gain == "eps" else f"w[c][j] - (({modified} - g[c][j]) + {cfg.eps}::double * g[c][j])"
    stepped = f"""SELECT *, {g} AS g FROM (
        SELECT *, {near} AS near FROM (
          SELECT *, {each} AS ds FROM (
            SELECT r.*, r.hist[r.t + 1] AS w, mb.xs FROM walk r JOIN mb ON mb.worker = r.worker AND mb.round = r.t WHERE r.t < {cfg.steps}) a) b) c"""
    letter = lambda of: f"list({{'e': list_transform({cs}, lambda c: CASE WHEN list_contains(b.blocks, (c - 1)::int) THEN {of}[c] END)}} ORDER BY b.buffer, b.sent_round, b.sender) AS es"
    fresh = f"list_transform({cs}, lambda c: list_transform({js}, lambda j: s.w[c][j] - {cfg.eps}::double * s.g[c][j]))"
    mail = f"SELECT b.recipient, {letter('s.f')} FROM box b JOIN (SELECT s.t, s.worker, {fresh} AS f FROM ({stepped}) s) s ON s.worker = b.sender AND b.round = s.t + 1 GROUP BY b.recipient" if sync else f"SELECT b.recipient, {letter('s.hist[b.sent_round + 2]')} FROM box b JOIN walk s ON s.worker = b.sender AND s.t = b.round GROUP BY b.recipient"
    return f"""
WITH RECURSIVE pts AS MATERIALIZED ({points}),
mb AS MATERIALIZED (SELECT worker, round, list(x ORDER BY slot) AS xs FROM ({minibatches('SELECT * FROM pts', cfg)}) b GROUP BY worker, round),
box AS MATERIALIZED (SELECT recipient, round, buffer, sender, sent_round, list(block ORDER BY block) AS blocks FROM ({inbox(cfg.with_(steps=cfg.steps + sync))}) i GROUP BY ALL),
walk AS (
  SELECT 0 AS t, i::int AS worker, [w] AS hist, 0::bigint AS received, 0::bigint AS good FROM ({initial('SELECT * FROM pts', cfg)}) z, range({cfg.workers}) r(i)
  UNION ALL
  SELECT t + 1, worker, list_append(hist, list_transform({cs}, lambda c: list_transform({js}, lambda j: {moved}))), received + len(es), good + len(ok) FROM (
    SELECT *, {window} AS ok FROM (
      SELECT z.*, coalesce(mail.es, []) AS es FROM ({stepped}) z LEFT JOIN ({mail}) mail ON mail.recipient = z.worker) d) e),
done AS (SELECT worker, hist[{cfg.steps + 1}] AS w, received, good FROM walk WHERE t = {cfg.steps})
{select}"""


def trace(points: str, cfg: DescentConfig, dims: int, run_id: str) -> str:
    """``run_id, round, touched, error``: the first worker's mean error after each round."""
    return run(points, cfg, dims, f"SELECT '{run_id}' AS run_id, t::int AS round, t::bigint * {cfg.b * cfg.workers} AS touched, round(avg(list_min(list_transform(hist[t + 1], lambda c: {d2('x', 'c', dims)})) * 0.5) + 1.7e-11, 9) AS error FROM walk, pts WHERE worker = 0 AND t > 0 GROUP BY t")


ALL_STATES = "SELECT worker, (c - 1)::int AS block, (d - 1)::int AS dim, w[c][d] AS value FROM done, range(1, len(w) + 1) r(c), range(1, len(w[1]) + 1) s(d)"
FIRST = f"SELECT block, dim, value FROM ({ALL_STATES}) s WHERE worker = 0"
AVERAGE = f"SELECT block, dim, round(avg(value), 9) AS value FROM ({ALL_STATES}) s GROUP BY block, dim"


def batch(points: str, cfg: DescentConfig, dims: int) -> str:
    """Full passes; sums over all samples are rounded at the end only."""
    cs, js = list(range(1, cfg.k + 1)), list(range(1, dims + 1))
    return f"""
WITH RECURSIVE pts AS MATERIALIZED ({points}),
walk AS (
  SELECT 0 AS t, w FROM ({initial('SELECT * FROM pts', cfg)}) z
  UNION ALL
  SELECT t + 1, list_transform({cs}, lambda c: list_transform({js}, lambda j: w[c][j] - {cfg.eps}::double * ((n[c] * w[c][j] - s[c][j]) / m))) FROM (
    SELECT any_value(t) AS t, any_value(w) AS w, count(*) AS m, {[f'count(*) FILTER (near = {c})' for c in cs]} AS n, {[[f'coalesce(sum(x[{j}]) FILTER (near = {c}), 0)' for j in js] for c in cs]} AS s FROM (
      SELECT *, list_position(ds, list_min(ds)) AS near FROM (SELECT r.t, r.w, p.x, list_transform(r.w, lambda c: {d2('p.x', 'c', dims)}) AS ds FROM walk r, pts p WHERE r.t < {cfg.steps}) a) b HAVING count(*) > 0) c)
SELECT (c - 1)::int AS block, (d - 1)::int AS dim, round(w[c][d] + 1.7e-11, 9) AS value FROM walk, range(1, {cfg.k} + 1) r(c), range(1, {dims} + 1) s(d) WHERE t = {cfg.steps}""".replace("'count", "count").replace(")'", ")").replace("'coalesce", "coalesce")
