"""SQL that repeats whole methods: spanning forests, the degree split, and the sample contraction with portable coins."""

from __future__ import annotations

COIN = "('0x' || substr(md5(concat_ws('|', '{seed}', '{purpose}', {keys})), 1, 8))::BIGINT / 4294967296.0"


def coin(seed: int, purpose: str, *keys: str) -> str:
    return COIN.format(seed=seed, purpose=purpose, keys=", ".join(f"{k}::VARCHAR" for k in keys))


def spanning_forest(edges: str) -> str:
    """src, dst, weight of the minimum spanning forest of edges (src, dst, weight).

    One row of lists is the state: each round finds every component's lightest outgoing edge, drops one end of mutual
    choices and follows the others to their roots by doubling."""
    jumps = "".join(f", j{k} AS (SELECT step, lab, picks, new, list_transform(p, lambda x: p[x]) AS p FROM j{k - 1})" for k in range(1, 18))
    return f"""WITH RECURSIVE e0 AS (SELECT src, dst, min(weight) AS weight FROM ({edges}) GROUP BY 1, 2),
v AS (SELECT vid, row_number() OVER (ORDER BY vid) AS i FROM (SELECT src AS vid FROM e0 UNION SELECT dst FROM e0)),
e AS MATERIALIZED (SELECT a.i AS a, b.i AS b, src, dst, weight, row_number() OVER (ORDER BY weight, src, dst) AS r FROM e0 JOIN v a ON src = a.vid JOIN v b ON dst = b.vid),
k(step, lab, picks) AS (SELECT 0, (SELECT range(1, max(i) + 1) FROM v), []::BIGINT[]
UNION ALL SELECT step + 1, list_transform(lab, lambda x: p[x]), list_concat(picks, new) FROM (
WITH x AS (SELECT k.lab[e.a] AS ca, k.lab[e.b] AS cb, e.r AS r FROM e, k),
m AS (SELECT c, min(r) AS r FROM (SELECT ca AS c, r FROM x WHERE ca <> cb UNION ALL SELECT cb, r FROM x WHERE ca <> cb) GROUP BY c),
h AS (SELECT m.c, CASE WHEN x.ca = m.c THEN x.cb ELSE x.ca END AS t, m.r FROM m JOIN x ON m.r = x.r),
f AS (SELECT v.i, CASE WHEN h.t IS NULL OR (o.t = h.c AND h.c < h.t) THEN v.i ELSE h.t END AS t, h.r FROM v LEFT JOIN h ON v.i = h.c LEFT JOIN h o ON h.t = o.c),
j0 AS (SELECT k.step, k.lab, k.picks, q.new, q.p FROM k, (SELECT list(t ORDER BY i) AS p, list_distinct(list(r) FILTER (WHERE r IS NOT NULL)) AS new FROM f) q WHERE len(q.new) > 0){jumps}
SELECT * FROM j17))
SELECT src, dst, round(weight, 6) AS weight FROM e JOIN (SELECT unnest(picks) AS r FROM (SELECT picks FROM k ORDER BY step DESC LIMIT 1)) USING (r)"""


def contraction(edges: str, vertices: str, seed: int, m: str = "ceil(sqrt(n))", pe: str = "1 / l", pl: str = "1 / l") -> str:
    """Tables of one sample contraction with portable coins: e, v, q (n, l, m, pe, pl), s (samples), ld (leaders),
    msg (messages), pt (pointers), lab (vid, comp), gr (growable comp).  To stand behind WITH RECURSIVE."""
    return f"""e AS MATERIALIZED ({edges}), v AS MATERIALIZED (SELECT DISTINCT vid FROM ({vertices} UNION SELECT src AS vid FROM e UNION SELECT dst FROM e)),
q AS MATERIALIZED (SELECT n, l, ({m})::BIGINT AS m, {pe} AS pe, {pl} AS pl FROM (SELECT n, greatest(2.0, log2(greatest(log2(greatest(n, 2)), 2))) AS l FROM (SELECT count(*) AS n FROM v))),
s AS MATERIALIZED (SELECT * FROM (SELECT unnest(range(1, (SELECT m FROM q) + 1)) AS sample, src, dst FROM e) WHERE {coin(seed, "sample", "sample", "src", "dst")} < (SELECT pe FROM q)),
ld AS MATERIALIZED (SELECT vid FROM v WHERE {coin(seed, "leader", "vid")} < (SELECT pl FROM q)),
b AS MATERIALIZED (SELECT sample, src AS x, dst AS y FROM s UNION ALL SELECT sample, dst, src FROM s),
cs(sample, x, comp) USING KEY (sample, x) AS (SELECT DISTINCT sample, x, x FROM b
UNION (SELECT b.sample, b.y, min(cs.comp) FROM cs JOIN b ON cs.sample = b.sample AND cs.x = b.x JOIN recurring.cs k ON k.sample = b.sample AND k.x = b.y WHERE cs.comp < k.comp GROUP BY b.sample, b.y)),
w AS MATERIALIZED (SELECT sample, comp, count(*) AS size, bool_or(ld.vid IS NOT NULL) AS led FROM cs LEFT JOIN ld ON x = vid GROUP BY sample, comp),
ds(sample, x, d) USING KEY (sample, x) AS (SELECT cs.sample, cs.x, 0 FROM cs JOIN w ON cs.sample = w.sample AND cs.comp = w.comp LEFT JOIN ld ON cs.x = vid WHERE vid IS NOT NULL OR (NOT led AND cs.x = cs.comp)
UNION (SELECT b.sample, b.y, min(ds.d + 1) FROM ds JOIN b ON ds.sample = b.sample AND ds.x = b.x LEFT JOIN recurring.ds k ON k.sample = b.sample AND k.x = b.y WHERE k.x IS NULL OR ds.d + 1 < k.d GROUP BY b.sample, b.y)),
hp AS (SELECT b.sample, b.x, min(b.y) AS hop FROM b JOIN ds f ON f.sample = b.sample AND f.x = b.x JOIN ds t ON t.sample = b.sample AND t.x = b.y WHERE t.d = f.d - 1 GROUP BY b.sample, b.x),
msg AS MATERIALIZED (SELECT cs.x AS v, CASE WHEN led THEN n - d ELSE 0 END AS x, size, cs.sample, hop, led, cs.comp FROM cs JOIN w ON cs.sample = w.sample AND cs.comp = w.comp JOIN ds ON ds.sample = cs.sample AND ds.x = cs.x
LEFT JOIN hp ON hp.sample = cs.sample AND hp.x = cs.x, q),
pt AS MATERIALIZED (SELECT vid, coalesce(hop, vid) AS parent FROM v LEFT JOIN (SELECT v AS mv, hop FROM msg QUALIFY row_number() OVER (PARTITION BY v ORDER BY x DESC, size DESC, sample DESC, coalesce(hop, -1) DESC) = 1) ON vid = mv),
up(vid, top) AS (SELECT vid, parent FROM pt UNION SELECT up.vid, pt.parent FROM up JOIN pt ON up.top = pt.vid),
lab AS MATERIALIZED (SELECT up.vid, up.top AS comp FROM up JOIN pt ON up.top = pt.vid AND pt.parent = pt.vid),
cr AS MATERIALIZED (SELECT a.comp AS ca, z.comp AS cb FROM e JOIN lab a ON src = a.vid JOIN lab z ON dst = z.vid WHERE a.comp <> z.comp),
gr AS MATERIALIZED (SELECT ca AS comp FROM cr UNION SELECT cb FROM cr)"""


def classes(small: str = "sqrt(log2(n))") -> str:
    """Behind ``contraction``: fin (comp, size, has_leader, grows), kls (vid, class, bad)."""
    return f"""fin AS MATERIALIZED (SELECT lab.comp, count(*) AS size, bool_or(ld.vid IS NOT NULL) AS has_leader, bool_or(gr.comp IS NOT NULL) AS grows FROM lab LEFT JOIN ld USING (vid) LEFT JOIN gr ON lab.comp = gr.comp GROUP BY lab.comp),
al AS (SELECT v AS vid FROM msg WHERE led UNION SELECT vid FROM ld),
kls AS MATERIALIZED (SELECT lab.vid, CASE WHEN al.vid IS NOT NULL THEN 'alpha' WHEN NOT grows AND size <= {small} THEN 'beta' ELSE 'gamma' END AS class, grows AND NOT has_leader AS bad, has_leader
FROM lab JOIN fin USING (comp) LEFT JOIN al ON lab.vid = al.vid, q)"""


def degree_split(edges: str, vertices: str, s: str = "greatest(2, ceil(greatest(2.0, log2(greatest(log2(greatest(n, 2)), 2)))))") -> str:
    """Tables of the degree split: e, v, d (vid, d), h1, c1 (vid, comp), h2, c2 (comp, top), fin (vid, top, awake), p (n, s).  To stand behind WITH RECURSIVE."""
    hook = lambda key: f"QUALIFY row_number() OVER (PARTITION BY y.a ORDER BY {key}) = 1"
    return f"""e AS MATERIALIZED ({edges}), v AS MATERIALIZED (SELECT DISTINCT vid FROM ({vertices} UNION SELECT src AS vid FROM e UNION SELECT dst FROM e)),
p AS MATERIALIZED (SELECT n, {s} AS s FROM (SELECT count(*) AS n FROM v)),
y AS MATERIALIZED (SELECT src AS a, dst AS b FROM e UNION ALL SELECT dst, src FROM e),
d AS MATERIALIZED (SELECT vid, count(a) AS d FROM v LEFT JOIN y ON vid = a GROUP BY vid),
h1 AS MATERIALIZED (SELECT y.a, y.b FROM y JOIN d ON y.b = d.vid {hook("d DESC, y.b DESC")}),
l1 AS (SELECT a, b FROM h1 UNION SELECT b, a FROM h1),
c1(vid, comp) USING KEY (vid) AS (SELECT vid, vid FROM v UNION (SELECT l1.b, min(c1.comp) FROM c1 JOIN l1 ON c1.vid = l1.a JOIN recurring.c1 k ON k.vid = l1.b WHERE c1.comp < k.comp GROUP BY l1.b)),
m1 AS MATERIALIZED (SELECT comp, max(d) AS cdeg FROM c1 JOIN d USING (vid) GROUP BY comp),
h2 AS MATERIALIZED (SELECT y.a, y.b, f.comp AS ca, t.comp AS cb FROM y JOIN c1 f ON y.a = f.vid JOIN c1 t ON y.b = t.vid JOIN m1 ON t.comp = m1.comp WHERE f.comp <> t.comp {hook("cdeg DESC, t.comp DESC, y.b DESC")}),
l2 AS (SELECT ca AS a, cb AS b FROM h2 UNION SELECT cb, ca FROM h2),
c2(comp, top) USING KEY (comp) AS (SELECT comp, comp FROM m1 UNION (SELECT l2.b, min(c2.top) FROM c2 JOIN l2 ON c2.comp = l2.a JOIN recurring.c2 k ON k.comp = l2.b WHERE c2.top < k.top GROUP BY l2.b)),
t2 AS MATERIALIZED (SELECT top, max(cdeg) AS cdeg FROM c2 JOIN m1 USING (comp) GROUP BY top),
fin AS MATERIALIZED (SELECT vid, top, cdeg >= s AS awake FROM c1 JOIN c2 USING (comp) JOIN t2 USING (top), p),
sd AS MATERIALIZED (SELECT src, dst, a.awake AND b.awake AS in_a FROM e JOIN fin a ON src = a.vid JOIN fin b ON dst = b.vid)"""


#: One row behind ``degree_split``.
SPLIT_COUNTS = """(SELECT count(DISTINCT top) FROM fin WHERE awake) AS awake_components,
coalesce((SELECT min(size) FROM (SELECT count(*) AS size FROM fin WHERE awake GROUP BY top)), 0) AS least_size,
coalesce((SELECT max(k) FROM (SELECT count(*) AS k FROM (SELECT src AS x FROM sd WHERE NOT in_a UNION ALL SELECT dst FROM sd WHERE NOT in_a) GROUP BY x)), 0) AS deg_b,
(SELECT count(*) FROM sd WHERE in_a) AS edges_a, (SELECT count(*) FROM sd WHERE NOT in_a) AS edges_b"""
