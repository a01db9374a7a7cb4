"""DuckDB texts that recompute the graph queries from their definitions."""

from __future__ import annotations

from .functions.exact import BY_ID, BY_ROUND, BY_SEED, DRAWS, PRIME, Share

EMB = """p AS (SELECT vec_id AS id, list_transform(embedding, lambda x: floor(CAST(x AS DOUBLE) * 16777216)) AS v FROM embeddings),
q AS (SELECT id, v, list_inner_product(v, v) AS n FROM p),
d AS MATERIALIZED (SELECT a.id AS a, b.id AS b, a.n + b.n - 2 * list_inner_product(a.v, b.v) AS d FROM q a, q b)"""


def embeddings_by(distance: str) -> str:
    """The same points under another distance of x.v and y.v."""
    return EMB.split("q AS")[0] + f"d AS MATERIALIZED (SELECT x.id AS a, y.id AS b, {distance} AS d FROM p x, p y)"



def need(share: Share, n: str = "(SELECT count(*) FROM p)") -> str:
    return f"(({share.num} * ({n} - 1) + {share.den - 1}) // {share.den})"


#: The nearest point left is linked and what it covers leaves, a step at a time.
PRUNE = """u AS (SELECT 1 AS step, a AS src, b AS r, d, first_value(b) OVER (PARTITION BY a ORDER BY d, b) AS s FROM d WHERE a <> b
  UNION ALL SELECT step + 1, src, r, dd, first_value(r) OVER (PARTITION BY src ORDER BY dd, r)
  FROM (SELECT u.step, u.src, u.r, u.d AS dd FROM u JOIN d x ON x.a = u.s AND x.b = u.r WHERE u.r <> u.s AND NOT x.d < u.d)),
c AS (SELECT src, step, any_value(s) AS dst, min(d) AS dist, count(*) AS k FROM u GROUP BY 1, 2),
e AS (SELECT src, CAST(step AS INTEGER) AS rank, dst, dist, k - coalesce(lead(k) OVER w, 0) AS gain, {n} - 1 - coalesce(lead(k) OVER w, 0) AS cum FROM c WINDOW w AS (PARTITION BY src ORDER BY step))"""


def prune(tail: str, base: str = EMB, n: str = "(SELECT count(*) FROM p)") -> str:
    return f"WITH RECURSIVE {base}, {PRUNE.format(n=n)} {tail}"


def cut(share) -> str:
    return f"cum - gain < {need(Share.of(share))}"


def hashed(x: str, turn: int, seed: int) -> str:
    z = f"((({x}) % {PRIME} * {BY_ID} + {(BY_ROUND * turn + BY_SEED * seed) % PRIME}) % {PRIME})"
    z = f"(({z} * {z} % {PRIME} * {BY_ID} + 11) % {PRIME})"
    return f"({z} * {z} % {PRIME})"


def drawn(i: str, turn: int, seed: int, n: str) -> str:
    return f"(({hashed(f'2 * {i}', turn + DRAWS, seed)} * {PRIME} + {hashed(f'2 * {i} + 1', turn + DRAWS, seed)}) % {n})"


#: Token counts of documents in 64 buckets, equal vectors collapsed.
TEXT = r"""tok AS (SELECT doc_id, unnest(list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}_]+'), lambda t: t <> '')) AS t FROM documents),
cnt AS (SELECT doc_id, CAST('0x' || substr(md5(t), 1, 8) AS BIGINT) % 64 AS b, count(*) AS k FROM tok GROUP BY 1, 2),
mp AS (SELECT doc_id, map_from_entries(list(row(b, k))) AS m FROM cnt GROUP BY 1),
p AS (SELECT min(doc_id) AS id, v FROM (SELECT doc_id, list_transform(range(64), lambda i: CAST(coalesce(m[i], 0) AS DOUBLE)) AS v FROM mp) GROUP BY v),
q AS (SELECT id, v, list_inner_product(v, v) AS n FROM p),
d AS MATERIALIZED (SELECT a.id AS a, b.id AS b, a.n + b.n - 2 * list_inner_product(a.v, b.v) AS d FROM q a, q b)"""
#: Sets of token buckets under Jaccard's distance; no document without a token is there, so none is empty.
SETS = TEXT.replace("coalesce(m[i], 0)", "least(coalesce(m[i], 0), 1)").replace("a.n + b.n - 2 * list_inner_product(a.v, b.v)", "1 - list_inner_product(a.v, b.v) / (a.n + b.n - list_inner_product(a.v, b.v))")

ORDERS = {"hash": lambda t, seed: hashed("id", t, seed), "id": lambda t, seed: "id", "locality": lambda t, seed: f"(SELECT list_sum(list_transform(range(1, len(v) + 1), lambda i: v[i] * (1 - 2 * ({hashed('(i - 1)', t, seed)} % 2)))) FROM p z WHERE z.id = l{t - 1}.id)"}


def peel(share, tail: str, delta: float | None = None, rounds: int = 3, seed: int = 1, base: str = EMB, order: str = "hash") -> str:
    """Rounds of chunks, ownership and carried points, unrolled; l holds the points left at the end."""
    share = Share.of(share)
    size = share.clique(2 if delta is None else 4)
    parts = [base, "n AS (SELECT count(*) AS n FROM p)", "l0 AS (SELECT id FROM p)"]
    for t in range(1, rounds + 1):
        parts.append(f"k{t} AS (SELECT id, row_number() OVER (ORDER BY {ORDERS[order](t, seed)}, id) - 1 AS pos, count(*) OVER () AS m FROM l{t - 1})")
        parts.append(f"c{t} AS (SELECT id, pos // {size} AS chunk FROM k{t} WHERE pos < m // {size} * {size})")
        if delta is None:
            parts.append(f"w{t} AS (SELECT id, 1 AS mult FROM p)")
            keep = f"owned * {share.den} <= {share.den - share.num} * (SELECT n FROM n)"
        else:
            w = f"CAST(ceil(16 * ln((SELECT n FROM n) / {delta}) * {share.den} / {share.den - share.num}) AS BIGINT)"
            parts.append(f"w{t} AS (SELECT id, count(*) AS mult FROM (SELECT {drawn('i', t, seed, '(SELECT n FROM n)')} AS pos FROM range({w}) r(i)) x JOIN (SELECT id, row_number() OVER (ORDER BY id) - 1 AS pos FROM p) y USING (pos) GROUP BY id)")
            keep = f"owned * {2 * share.den} <= {share.den - share.num} * {w}"
        parts.append(f"o{t} AS (SELECT {t} AS round, chunk, member, CAST(sum(mult) FILTER (WHERE dd = least_d) AS BIGINT) AS owned FROM (SELECT chunk, c{t}.id AS member, mult, d.d AS dd, min(d.d) OVER (PARTITION BY chunk, w{t}.id) AS least_d FROM c{t}, w{t} JOIN d ON d.b = w{t}.id WHERE d.a = c{t}.id) GROUP BY 2, 3)")
        parts.append(f"m{t} AS (SELECT round, chunk, member, coalesce(owned, 0) AS owned, coalesce({keep}, true) AS kept FROM o{t})")
        parts.append(f"l{t} AS (SELECT id FROM l{t - 1} WHERE id NOT IN (SELECT member FROM m{t} WHERE kept))")
    every = " UNION ALL ".join(f"SELECT * FROM m{t}" for t in range(1, rounds + 1))
    parts += [f"m AS ({every})", f"l AS (SELECT id FROM l{rounds})"]
    parts.append("g AS (SELECT x.member AS src, y.member AS dst FROM m x JOIN m y ON x.round = y.round AND x.chunk = y.chunk AND x.kept AND x.member <> y.member UNION SELECT l.id, p.id FROM l, p WHERE l.id <> p.id)")
    return f"WITH RECURSIVE {', '.join(parts)} {tail}"


#: Points strictly nearer to an out-neighbour (edges g) than to the source.
COVERED = "SELECT p.id AS src, count(t.id) AS covered FROM p LEFT JOIN (SELECT DISTINCT g.src, x.b AS id FROM g JOIN d x ON x.a = g.dst JOIN d y ON y.a = g.src AND y.b = x.b WHERE x.d < y.d AND x.b <> g.src) t ON t.src = p.id GROUP BY 1"


def greedy(share, name: str = "w", start: str = "(SELECT min(id) FROM x)") -> str:
    """Walks over edges e of a share, with x(qid, id, dist): each step to the nearest out-neighbour while it is nearer."""
    return f"""{name} AS (SELECT qid, id AS at_id, dist, 0 AS steps FROM x WHERE id = {start}
  UNION ALL SELECT qid, nid, nd, steps + 1 FROM (SELECT z.qid, z.dist AS cur, z.steps, arg_min(e.dst, row(x.dist, e.dst)) AS nid, min(x.dist) AS nd
  FROM {name} z JOIN e ON e.src = z.at_id AND {share} JOIN x ON x.qid = z.qid AND x.id = e.dst GROUP BY 1, 2, 3) WHERE nd < cur)"""


#: Beam walks g(share, need, qid, start) over lists e and distances d, a step of each at a time: what is open, what was
#: evaluated, the distances of what was expanded. A width's stop is the first step at which so many are as near.
ASKED = "x AS MATERIALIZED (SELECT a AS qid, b AS id, d AS dist FROM d WHERE a % 100 = 0)"
ASKED_SPLIT = ",\n-- walks\n"
BEAM = """{asked},
-- walks
f AS MATERIALIZED (SELECT share, src, dst FROM e, (SELECT DISTINCT share, need FROM g) WHERE cum - gain < need),
w AS (SELECT g.share, g.qid, 0 AS step, 0::BIGINT AS scanned, [{{'d': x.dist, 'id': x.id}}] AS opened, [x.id] AS seen, []::DOUBLE[] AS done
  FROM g JOIN x ON x.qid = g.qid AND x.id = g.start
  UNION ALL SELECT t.share, t.qid, any_value(t.step) + 1, any_value(t.scanned) + count(f.dst),
    list_concat(any_value(t.rest), coalesce(list({{'d': x.dist, 'id': x.id}}) FILTER (x.id IS NOT NULL), [])),
    list_concat(any_value(t.seen), coalesce(list(x.id) FILTER (x.id IS NOT NULL), [])), list_append(any_value(t.done), any_value(t.top.d))
  FROM (SELECT share, qid, step, scanned, seen, done, top, list_filter(opened, lambda o: o.id <> top.id) AS rest
    FROM (SELECT *, list_min(opened) AS top FROM w WHERE len(opened) > 0)
    WHERE len(list_filter(done, lambda z: z <= top.d)) < {most}) t
  LEFT JOIN f ON f.share = t.share AND f.src = t.top.id
  LEFT JOIN x ON x.qid = t.qid AND x.id = f.dst AND NOT list_contains(t.seen, f.dst)
  GROUP BY t.share, t.qid),
m AS (SELECT *, CASE WHEN len(opened) = 0 THEN 1000000000 ELSE len(list_filter(done, lambda z: z <= top.d)) END AS near FROM (SELECT *, list_min(opened) AS top FROM w)),
st AS (SELECT m.share, m.qid, b, min(step) AS step FROM m JOIN (SELECT unnest([{widths}]) AS b) ON near >= b GROUP BY 1, 2, 3),
z AS (SELECT st.share, st.qid, b, len(seen) AS evals, scanned, st.step AS expanded, seen FROM st JOIN m USING (share, qid, step)),
found AS (SELECT share, qid, b, evals, id, x.dist, row_number() OVER (PARTITION BY share, qid, b ORDER BY x.dist, id) AS pos
  FROM (SELECT share, qid, b, evals, unnest(seen) AS id FROM z) JOIN x USING (qid, id) WHERE {other}),
truth AS (SELECT qid, id, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS tpos FROM x WHERE {other}),
rc AS (SELECT share, qid, b, k, any_value(evals) AS evals, count(*) FILTER (pos <= k AND tpos <= k) / k AS recall
  FROM found JOIN truth USING (qid, id), (SELECT unnest([{ks}]) AS k) WHERE b >= k GROUP BY 1, 2, 3, 4)"""

#: Recall against cost, and what is made of it.
POINTS = """pts AS (SELECT CAST(share AS DOUBLE) AS share, degree, k, b, avg(recall) AS recall, avg(evals) AS dc FROM rc
  JOIN (SELECT share, count(*) / (SELECT count(*) FROM p) AS degree FROM f GROUP BY 1) USING (share) GROUP BY 1, 2, 3, 4)"""
RATIOS = """s AS (SELECT *, lag(recall) OVER v AS r0, lag(dc) OVER v AS c0 FROM pts WINDOW v AS (PARTITION BY share, k ORDER BY b)),
cr AS (SELECT share, degree, k, target, CASE WHEN r0 IS NULL THEN dc ELSE c0 + (target - r0) / (recall - r0) * (dc - c0) END AS dc, r0 IS NULL AS censored,
  row_number() OVER (PARTITION BY share, k, target ORDER BY b) AS n FROM s, (SELECT unnest([{targets}]) AS target) WHERE recall >= target AND (r0 IS NULL OR r0 < target)),
lo AS (SELECT *, row_number() OVER (PARTITION BY k, target ORDER BY dc, share, degree, censored) AS i FROM cr WHERE n = 1 AND share < 1),
ratio AS (SELECT h.k, h.target, lo.share, lo.dc / h.dc AS dc_ratio, lo.degree / h.degree AS degree_ratio, h.censored AS ref_censored, lo.censored AS num_censored
  FROM cr h LEFT JOIN lo ON lo.k = h.k AND lo.target = h.target AND lo.i = 1 WHERE h.n = 1 AND h.share = 1)"""
PARETO = """fu AS (SELECT k, dc AS hi, recall AS r_hi, lag(dc) OVER v AS lo, lag(recall) OVER v AS r_lo FROM pts WHERE share = 1 WINDOW v AS (PARTITION BY k ORDER BY dc)),
best AS (SELECT k, max(recall) AS top, max(dc) AS top_dc FROM pts WHERE share = 1 GROUP BY 1),
pa AS (SELECT y.share, y.k, y.b, y.recall, y.dc, coalesce(CASE WHEN fu.hi IS NULL THEN NULL WHEN fu.lo IS NULL THEN r_hi ELSE r_lo + (y.dc - fu.lo) / (fu.hi - fu.lo) * (r_hi - r_lo) END,
  CASE WHEN y.dc > top_dc THEN top END, 0.0) AS full_recall
  FROM pts y JOIN best USING (k) LEFT JOIN fu ON fu.k = y.k AND y.dc <= fu.hi AND ((fu.lo IS NULL AND y.dc = fu.hi) OR y.dc > fu.lo) WHERE y.share < 1)"""


def walks(shares, start: str = "(SELECT min(id) FROM p)", queries: str = "SELECT id AS qid FROM p WHERE id % 100 = 0") -> str:
    """g for every query and share."""
    each = " UNION ALL ".join(f"SELECT '{t}' AS share, {need(Share.of(t))} AS need" for t in shares)
    return f"g AS (SELECT share, need, qid, {start} AS start FROM ({each}), ({queries}))"


def beams(shares, widths, ks, tail: str, *more: str, starts: str | None = None, base: str = EMB, asked: str = ASKED, queries: str | None = None) -> str:
    """Walks and their recall. queries: held-out ones, which `asked` gives distances x; else ids that 100 divides, which don't find themselves."""
    walk = BEAM.format(asked=asked, other="true" if queries else "id <> qid", most=max(widths), widths=", ".join(map(str, widths)), ks=", ".join(map(str, ks)))
    first, _, rest = walk.partition(ASKED_SPLIT)
    parts = [first, starts or (walks(shares, queries=queries) if queries else walks(shares)), rest, *more]
    return prune(", " + ", ".join(parts) + " " + tail, base).replace("e AS (SELECT src, CAST(step", "e AS MATERIALIZED (SELECT src, CAST(step")


#: Benchmark items as held-out queries of the documents' text vectors.
ITEMS = TEXT.split("p AS (SELECT min")[0].replace("tok AS", "itok AS").replace("cnt AS", "icnt AS").replace("mp AS", "imp AS").replace("FROM tok", "FROM itok").replace("FROM cnt", "FROM icnt").replace("doc_id", "item_id").replace("FROM documents", "FROM benchmark")
ITEMS += "iv AS (SELECT item_id AS qid, list_transform(range(64), lambda i: CAST(coalesce(m[i], 0) AS DOUBLE)) AS v FROM imp)"
ASKED_ITEMS = ITEMS + ", x AS MATERIALIZED (SELECT qid, q.id, list_inner_product(iv.v, iv.v) + q.n - 2 * list_inner_product(iv.v, q.v) AS dist FROM iv, q)"


def candidates_only(k: int, tail: str) -> str:
    """PRUNE whose links come from each node's k nearest points."""
    first = "first_value({0}) OVER (PARTITION BY src ORDER BY rk > " + str(k) + ", d, r)"
    pick = first.format("r") + " AS s, " + first.format(f"rk <= {k}") + " AS ok"
    return f"""WITH RECURSIVE {EMB}, c0 AS MATERIALIZED (SELECT a AS src, b AS r, d, row_number() OVER (PARTITION BY a ORDER BY d, b) AS rk FROM d WHERE a <> b),
u AS (SELECT 1 AS step, src, r, d, rk, {pick} FROM c0
  UNION ALL SELECT step + 1, src, r, d, rk, {pick} FROM (SELECT u.step, u.src, u.r, u.d, u.rk FROM u JOIN d x ON x.a = u.s AND x.b = u.r WHERE u.ok AND u.r <> u.s AND NOT x.d < u.d)),
g AS (SELECT DISTINCT src, s AS dst FROM u WHERE ok) {tail}"""


def slack_edges(slack: str, share: str) -> str:
    return prune(f"SELECT '{slack}' AS slack, count(*) AS edges FROM e WHERE {cut(share)}").replace("NOT x.d < u.d", f"NOT {slack}::DOUBLE * x.d < u.d")
