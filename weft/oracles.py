"""SQL of the named queries: the same rows worked out by a database, without any of the engine's code.

``word_sql`` builds words from the given tables.  ``RELATIONS`` turns words to profiles, pairs and
multiplicities; ``CONFLICT_SETS`` partitions symbols by repeated maximum independent sets over bit
masks; ``ACYCLIC`` repairs cyclic sets; ``CHAINS`` orders each set and writes the schema.
"""

from __future__ import annotations

import re

RELATIONS = """
p AS (SELECT element, word_id, unnest(symbols) AS s, generate_subscripts(symbols, 1) AS i FROM w),
prof AS (SELECT element, word_id, s, min(i) AS f, max(i) AS l, count(*) AS c FROM p GROUP BY ALL),
pairs AS (SELECT a.element, a.s AS x, b.s AS y, count(*) AS n_words FROM prof a JOIN prof b USING (element, word_id) WHERE a.s <> b.s AND a.f < b.l GROUP BY ALL),
total AS (SELECT element, count(*) AS words FROM w GROUP BY element),
counts AS (SELECT element, s AS symbol, CASE WHEN count(*) < any_value(words) THEN 0 ELSE min(least(c, 2)) END AS min_n, max(least(c, 2)) AS max_n, count(*) AS in_words, any_value(words) AS words
           FROM prof JOIN total USING (element) GROUP BY element, s),
mults AS (SELECT *, CASE WHEN min_n = 0 THEN CASE WHEN max_n > 1 THEN '*' ELSE '?' END WHEN max_n > 1 THEN '+' ELSE '1' END AS mult FROM counts)
"""

#: Repeated maximum independent sets as bit masks over the symbols in conflict; a symbol's weight falls with its
#: place, so of equally large sets the greatest mask is the lexicographically smallest.  The others join the first.
CONFLICT_SETS = """
k AS (SELECT a.element, a.x, a.y FROM pairs a JOIN pairs b ON a.element = b.element AND a.x = b.y AND a.y = b.x),
st AS (SELECT q.element, q.x, q.y FROM pairs q WHERE NOT EXISTS (SELECT 1 FROM pairs r WHERE r.element = q.element AND r.x = q.y AND r.y = q.x)),
bits AS (SELECT element, s, (1 << (n - i)::INTEGER)::BIGINT AS b, n FROM (SELECT element, x AS s, row_number() OVER (PARTITION BY element ORDER BY x) AS i, count(*) OVER (PARTITION BY element) AS n FROM (SELECT DISTINCT element, x FROM k))),
masks AS (SELECT element, unnest(range(1, 1 << any_value(n)::INTEGER)) AS m FROM bits GROUP BY element),
bad AS (SELECT DISTINCT masks.element, m FROM masks JOIN k ON k.element = masks.element JOIN bits x ON x.element = k.element AND x.s = k.x JOIN bits y ON y.element = k.element AND y.s = k.y WHERE m & x.b <> 0 AND m & y.b <> 0),
ind AS (SELECT * FROM masks ANTI JOIN bad USING (element, m)),
it AS (
  SELECT element, 0 AS no, sum(b)::BIGINT AS rest, 0::BIGINT AS pick FROM bits GROUP BY element
  UNION ALL
  SELECT it.element, it.no + 1, it.rest - z.best, z.best FROM it JOIN LATERAL (SELECT arg_max(m, bit_count(m) * 1000000 + m)::BIGINT AS best FROM ind WHERE ind.element = it.element AND m & it.rest = m) z ON true WHERE it.rest > 0),
sets AS (SELECT it.element, no, s FROM it JOIN bits ON bits.element = it.element AND pick & b <> 0 WHERE no > 0
         UNION ALL SELECT element, 1, symbol FROM counts WHERE NOT EXISTS (SELECT 1 FROM k WHERE k.element = counts.element AND k.x = counts.symbol))
"""

#: The same by excluding cliques.  ``duo`` holds for every mask, in ascending order, the clique and the independent set that a
#: split at its smallest symbol (the highest bit) gives; both parts of a split are smaller masks.  A set is the best of those met
#: while cliques are taken away.
EXCLUDED_SETS = CONFLICT_SETS[: CONFLICT_SETS.index("masks AS")].rstrip() + """
around AS (SELECT element, list(m ORDER BY b) AS near, count(*) AS n FROM (SELECT x.element, x.b, sum(y.b)::BIGINT AS m FROM bits x JOIN k ON k.element = x.element AND k.x = x.s JOIN bits y ON y.element = k.element AND y.s = k.y GROUP BY x.element, x.b) GROUP BY element),
duo AS (
  SELECT element, near, n, 0::BIGINT AS m, [0]::BIGINT[] AS c, [0]::BIGINT[] AS i FROM around
  UNION ALL
  SELECT element, near, n, m, list_append(c, CASE WHEN bit_count(c[inside + 1] | p) >= bit_count(c[outside + 1]) THEN c[inside + 1] | p ELSE c[outside + 1] END),
         list_append(i, CASE WHEN bit_count(i[outside + 1] | p) >= bit_count(i[inside + 1]) THEN i[outside + 1] | p ELSE i[inside + 1] END)
  FROM (SELECT *, (m & near[spot + 1])::BIGINT AS inside, (m & ~near[spot + 1] & ~p)::BIGINT AS outside
        FROM (SELECT *, (1 << spot)::BIGINT AS p FROM (SELECT element, near, n, m + 1 AS m, c, i, (length(bin(m + 1)) - 1)::INTEGER AS spot FROM duo WHERE m + 1 < (1 << n::INTEGER))))),
met AS (SELECT element, c, i, m AS whole FROM duo WHERE m + 1 = (1 << n::INTEGER)),
it AS (
  SELECT element, c, i, 1 AS no, whole AS todo, whole AS rest, 0::BIGINT AS best FROM met
  UNION ALL
  SELECT element, c, i, CASE WHEN rest = 0 THEN no + 1 ELSE no END, CASE WHEN rest = 0 THEN todo & ~best ELSE todo END, CASE WHEN rest = 0 THEN todo & ~best ELSE rest & ~c[rest + 1] END,
         CASE WHEN rest = 0 THEN 0 WHEN bit_count(i[rest + 1]) * 1000000 + i[rest + 1] > bit_count(best) * 1000000 + best THEN i[rest + 1] ELSE best END
  FROM it WHERE todo <> 0),
sets AS (SELECT it.element, no, s FROM it JOIN bits ON bits.element = it.element AND best & b <> 0 WHERE rest = 0 AND todo <> 0
         UNION ALL SELECT element, 1, symbol FROM counts WHERE NOT EXISTS (SELECT 1 FROM k WHERE k.element = counts.element AND k.x = counts.symbol))
"""

#: Masks that have no cycle are grown by symbols without a successor in them; a set keeps its symbols in ascending
#: order as long as it stays such a mask, and the others make the next set.
ACYCLIC = """
ab AS (SELECT element, symbol AS s, (1 << (row_number() OVER (PARTITION BY element ORDER BY symbol) - 1)::INTEGER)::BIGINT AS b FROM counts),
nx AS (SELECT a.element, a.b, coalesce(bit_or(y.b), 0)::BIGINT AS succ FROM ab a LEFT JOIN st ON st.element = a.element AND st.x = a.s LEFT JOIN ab y ON y.element = st.element AND y.s = st.y GROUP BY ALL),
ac AS (SELECT DISTINCT element, 0::BIGINT AS m FROM ab UNION SELECT ac.element, (ac.m | nx.b)::BIGINT FROM ac JOIN nx USING (element) WHERE ac.m & nx.b = 0 AND nx.succ & ac.m = 0),
rep AS (
  SELECT sets.element, no, 0 AS sub, sum(b)::BIGINT AS todo, 0::BIGINT AS kept, 0::BIGINT AS away FROM sets JOIN ab ON ab.element = sets.element AND ab.s = sets.s GROUP BY ALL
  UNION ALL
  SELECT r.element, r.no, CASE WHEN r.todo = 0 THEN r.sub + 1 ELSE r.sub END,
         (CASE WHEN r.todo = 0 THEN r.away ELSE r.todo & (r.todo - 1) END)::BIGINT,
         (CASE WHEN r.todo = 0 THEN 0 WHEN ac.m IS NULL THEN r.kept ELSE ac.m END)::BIGINT,
         (CASE WHEN r.todo = 0 THEN 0 WHEN ac.m IS NULL THEN r.away | (r.todo & (-r.todo)) ELSE r.away END)::BIGINT
  FROM rep r LEFT JOIN ac ON ac.element = r.element AND ac.m = r.kept | (r.todo & (-r.todo)) WHERE r.todo <> 0 OR r.away <> 0),
fs AS (SELECT rep.element, no, sub, s FROM rep JOIN ab ON ab.element = rep.element AND kept & b <> 0 WHERE todo = 0)
"""

#: For workloads of more symbols than masks can hold and no cycle.
WHOLE = "fs AS (SELECT element, no, 0 AS sub, s FROM sets)"

CHAINS = """
node AS (SELECT f.element, f.no, f.sub, f.s, coalesce(list(st.x) FILTER (st.x IS NOT NULL), []) AS pre FROM fs f LEFT JOIN st ON st.element = f.element AND st.y = f.s GROUP BY ALL),
chain AS (
  SELECT element, no, sub, list({'s': s, 'pre': pre} ORDER BY s) AS rest, 0 AS pos, '' AS s FROM node GROUP BY ALL
  UNION ALL
  SELECT element, no, sub, list_filter(rest, lambda r: r.s <> v), pos + 1, v
  FROM (SELECT element, no, sub, rest, pos, list_filter(rest, lambda r: len(list_intersect(r.pre, list_transform(rest, lambda q: q.s))) = 0)[1].s AS v FROM chain WHERE len(rest) > 0)),
placed AS (SELECT c.element, c.no, c.sub, c.pos, c.s, mult FROM chain c JOIN mults ON mults.element = c.element AND mults.symbol = c.s WHERE pos > 0),
factors AS (SELECT element, no, sub, string_agg(s || CASE WHEN mult = '1' THEN '' ELSE mult END, ' ' ORDER BY pos) AS t, count(*) AS n, count(*) FILTER (WHERE mult <> '1') AS ops, arg_min(s, pos) AS head FROM placed GROUP BY ALL),
texts AS (SELECT total.element, any_value(total.words) AS words, coalesce(max(sub), 0) > 0 AS repaired, coalesce(string_agg(t, ' & ' ORDER BY n DESC, head), '') AS text,
                 count(n) AS factors, coalesce(string_agg(n::VARCHAR, ',' ORDER BY n DESC), '') AS sizes FROM total LEFT JOIN factors USING (element) GROUP BY total.element)
"""

#: Words ``u`` under the schemas: unknown symbols first, then counts, then order.
MEMBERSHIP = """
uprof AS (SELECT element, word_id, s, min(i) AS f, max(i) AS l, count(*) AS c FROM (SELECT element, word_id, unnest(symbols) AS s, generate_subscripts(symbols, 1) AS i FROM u) GROUP BY ALL),
unknown AS (SELECT DISTINCT element, word_id FROM uprof ANTI JOIN placed USING (element, s)),
miscount AS (SELECT DISTINCT u.element, u.word_id FROM u JOIN placed USING (element) LEFT JOIN uprof ON uprof.element = u.element AND uprof.word_id = u.word_id AND uprof.s = placed.s
             WHERE coalesce(c, 0) < CASE WHEN mult IN ('1', '+') THEN 1 ELSE 0 END OR coalesce(c, 0) > 1 AND mult IN ('1', '?')),
disorder AS (SELECT DISTINCT a.element, a.word_id FROM uprof a JOIN uprof b USING (element, word_id) JOIN placed x ON x.element = a.element AND x.s = a.s JOIN placed y ON y.element = b.element AND y.s = b.s
             WHERE x.no = y.no AND x.sub = y.sub AND x.pos < y.pos AND b.f < a.l),
verdict AS (SELECT u.element, u.word_id, CASE WHEN total.element IS NULL THEN 'no_schema' WHEN unknown.word_id IS NOT NULL THEN 'unknown_symbol' WHEN miscount.word_id IS NOT NULL THEN 'count' WHEN disorder.word_id IS NOT NULL THEN 'order' ELSE 'ok' END AS reason
            FROM u LEFT JOIN total ON total.element = u.element LEFT JOIN unknown ON unknown.element = u.element AND unknown.word_id = u.word_id
            LEFT JOIN miscount ON miscount.element = u.element AND miscount.word_id = u.word_id LEFT JOIN disorder ON disorder.element = u.element AND disorder.word_id = u.word_id)
"""

REVERSE = "EXISTS (SELECT 1 FROM pairs r WHERE r.element = q.element AND r.x = q.y AND r.y = q.x)"
NEXT = "SELECT DISTINCT element, word_id, a.s AS x, b.s AS y FROM p a JOIN p b USING (element, word_id) WHERE b.i = a.i + 1"
TOGETHER = "SELECT a.element, a.s AS x, b.s AS y, count(*) AS n_words FROM prof a JOIN prof b USING (element, word_id) WHERE a.s < b.s GROUP BY ALL"

#: The chain baseline: symbols that reach each other are one class, lone symbols with equal neighbours are merged.
CLASSES = f"""
adj AS (SELECT DISTINCT element, x, y FROM ({NEXT})),
reach AS (SELECT element, x, y FROM adj UNION SELECT r.element, r.x, a.y FROM reach r JOIN adj a ON a.element = r.element AND a.x = r.y),
part AS (SELECT c.element, c.symbol AS s, least(c.symbol, coalesce(min(f.y), c.symbol)) AS rep, count(f.y) > 0 AS many
         FROM counts c LEFT JOIN (SELECT a.element, a.x, a.y FROM reach a JOIN reach b ON a.element = b.element AND a.x = b.y AND a.y = b.x) f ON f.element = c.element AND f.x = c.symbol GROUP BY c.element, c.symbol),
sides AS (SELECT part.*, (SELECT coalesce(string_agg(DISTINCT x, '|' ORDER BY x), '') FROM adj WHERE adj.element = part.element AND adj.y = part.s) AS bef,
                 (SELECT coalesce(string_agg(DISTINCT y, '|' ORDER BY y), '') FROM adj WHERE adj.element = part.element AND adj.x = part.s) AS aft FROM part),
homes AS (SELECT element, s, min(s) OVER (PARTITION BY element, CASE WHEN many THEN 'many ' || rep ELSE 'one ' || bef || ' / ' || aft END) AS home FROM sides),
step AS (SELECT DISTINCT adj.element, a.home AS x, b.home AS y FROM adj JOIN homes a ON a.element = adj.element AND a.s = adj.x JOIN homes b ON b.element = adj.element AND b.s = adj.y WHERE a.home <> b.home),
stops AS (SELECT h.element, h.home, coalesce(list(step.x) FILTER (step.x IS NOT NULL), []) AS pre FROM (SELECT DISTINCT element, home FROM homes) h LEFT JOIN step ON step.element = h.element AND step.y = h.home GROUP BY ALL),
line AS (
  SELECT element, list({{'s': home, 'pre': pre}} ORDER BY home) AS rest, 0 AS pos, '' AS home FROM stops GROUP BY ALL
  UNION ALL
  SELECT element, list_filter(rest, lambda r: r.s <> v), pos + 1, v
  FROM (SELECT element, rest, pos, list_filter(rest, lambda r: len(list_intersect(r.pre, list_transform(rest, lambda q: q.s))) = 0)[1].s AS v FROM line WHERE len(rest) > 0)),
held AS (SELECT prof.element, word_id, home, sum(least(c, 2)) AS c FROM prof JOIN homes ON homes.element = prof.element AND homes.s = prof.s GROUP BY ALL),
ranged AS (SELECT held.element, home, CASE WHEN count(*) < any_value(words) THEN 0 ELSE min(c) END AS low, max(c) AS high FROM held JOIN total USING (element) GROUP BY ALL),
named AS (SELECT element, home, string_agg(s, '|' ORDER BY s) AS names, count(*) AS n FROM homes GROUP BY ALL),
links AS (SELECT line.element, pos, CASE WHEN n > 1 THEN '(' || names || ')' ELSE names END || CASE WHEN low = 0 THEN CASE WHEN high > 1 THEN '*' ELSE '?' END WHEN high > 1 THEN '+' ELSE '' END AS t
          FROM line JOIN named USING (element, home) JOIN ranged USING (element, home) WHERE pos > 0)
"""

#: Choices of symbols that never share a word, grown from the smallest symbol on.
CHOICES = f"""
together AS ({TOGETHER}),
near AS (SELECT c.element, c.symbol AS s, row_number() OVER (PARTITION BY c.element ORDER BY c.symbol) AS i, list(o.y) FILTER (o.y IS NOT NULL) AS others
         FROM counts c LEFT JOIN (SELECT element, x, y FROM together UNION ALL SELECT element, y, x FROM together) o ON o.element = c.element AND o.x = c.symbol GROUP BY c.element, c.symbol),
grow AS (
  SELECT element, 0::BIGINT AS i, []::VARCHAR[][] AS g FROM total
  UNION ALL
  SELECT element, i, CASE WHEN slot IS NULL THEN list_append(g, [s]) ELSE list_transform(g, lambda x, j: CASE WHEN j = slot THEN list_append(x, s) ELSE x END) END
  FROM (SELECT grow.element, near.i, near.s, g, list_filter(range(1, len(g) + 1), lambda j: len(list_intersect(g[j], coalesce(others, []))) = 0)[1] AS slot FROM grow JOIN near ON near.element = grow.element AND near.i = grow.i + 1)),
final AS (SELECT element, arg_max(g, i) AS g FROM grow GROUP BY element),
each AS (SELECT element, unnest(g) AS members, generate_subscripts(g, 1) AS no FROM final),
judged AS (SELECT each.element, no, string_agg(symbol, '|' ORDER BY symbol) AS names, count(*) AS n, max(max_n) > 1 AS many, sum(in_words) = any_value(words) AS always
           FROM each JOIN counts ON counts.element = each.element AND list_contains(members, symbol) GROUP BY ALL)
"""

#: What each schema's language is to that of the chain baseline, by counts of classes and order of pairs.
AGAINST_CHAIN = """SELECT t.element, 'exact' AS learner, CASE WHEN up AND down THEN 'equal' WHEN up THEN 'subset' WHEN down THEN 'superset' ELSE 'incomparable' END AS relation FROM (
  SELECT total.element,
    NOT EXISTS (SELECT 1 FROM (SELECT h.element, h.home, sum(CASE WHEN mult IN ('1', '+') THEN 1 ELSE 0 END) AS low, sum(CASE WHEN mult IN ('+', '*') THEN 1000 ELSE 1 END) AS high FROM homes h JOIN placed f ON f.element = h.element AND f.s = h.s GROUP BY ALL) a
                JOIN ranged r ON r.element = a.element AND r.home = a.home WHERE a.element = total.element AND (a.low < least(r.low, 1) OR a.high > CASE WHEN r.high > 1 THEN 1000000 ELSE 1 END))
    AND NOT EXISTS (SELECT 1 FROM homes x JOIN homes y ON x.element = y.element JOIN line a ON a.element = x.element AND a.home = x.home AND a.pos > 0 JOIN line b ON b.element = y.element AND b.home = y.home AND b.pos > 0
                    WHERE x.element = total.element AND a.pos < b.pos AND NOT EXISTS (SELECT 1 FROM placed f JOIN placed g ON f.element = g.element AND f.no = g.no AND f.sub = g.sub AND f.pos < g.pos WHERE f.element = x.element AND f.s = x.s AND g.s = y.s)) AS up,
    NOT EXISTS (SELECT 1 FROM homes h JOIN placed f ON f.element = h.element AND f.s = h.s JOIN named n ON n.element = h.element AND n.home = h.home JOIN ranged r ON r.element = h.element AND r.home = h.home
                WHERE h.element = total.element AND (mult IN ('1', '+') AND (n.n > 1 OR r.low = 0) OR mult IN ('1', '?') AND r.high > 1))
    AND NOT EXISTS (SELECT 1 FROM placed f JOIN placed g ON f.element = g.element AND f.no = g.no AND f.sub = g.sub AND f.pos < g.pos JOIN homes x ON x.element = f.element AND x.s = f.s JOIN homes y ON y.element = g.element AND y.s = g.s
                    JOIN line a ON a.element = x.element AND a.home = x.home AND a.pos > 0 JOIN line b ON b.element = y.element AND b.home = y.home AND b.pos > 0 JOIN ranged r ON r.element = x.element AND r.home = x.home
                    WHERE f.element = total.element AND (b.pos < a.pos OR x.home = y.home AND r.high > 1)) AS down
  FROM total) t"""

#: kind of query: SELECT over the relations above.
SELECT = {
    "words": "SELECT element, word_id, array_to_string(symbols, ' ') AS symbols FROM w",
    "precedence": "SELECT * FROM pairs",
    "conflicts": f"SELECT element, x, y FROM pairs q WHERE {REVERSE}",
    "stable": f"SELECT element, x, y FROM pairs q WHERE NOT {REVERSE}",
    "conflict_graph": f"SELECT element, string_agg(x || '-' || y, ' ' ORDER BY x, y) AS edges FROM pairs q WHERE x < y AND {REVERSE} GROUP BY element",
    "multiplicities": "SELECT element, symbol, min_n::BIGINT AS min_n, max_n::BIGINT AS max_n, in_words, words, mult FROM mults",
    "conflict_density": f"SELECT element, symbols, conflict_pairs, round(CASE WHEN symbols > 1 THEN conflict_pairs / (symbols * (symbols - 1) / 2) ELSE 0 END, 6) AS density FROM (SELECT c.element, count(*) AS symbols, (SELECT count(*) FROM pairs q WHERE q.element = c.element AND q.x < q.y AND {REVERSE}) AS conflict_pairs FROM counts c GROUP BY c.element)",
    "multiplicity_only": "SELECT element, any_value(words) AS words, string_agg(symbol || CASE WHEN mult = '1' THEN '' ELSE mult END, ' & ' ORDER BY symbol) AS text FROM mults GROUP BY element",
    "sample_sizes": "SELECT element, count(*) AS words, count(DISTINCT symbols) AS distinct_words FROM w GROUP BY element",
    "star": "SELECT element, any_value(words) AS words, '(' || string_agg(symbol, '|' ORDER BY symbol) || ')*' AS text FROM counts GROUP BY element",
    "adjacency": f"SELECT element, x, y, count(*) AS n_words FROM ({NEXT}) GROUP BY ALL",
    "together": TOGETHER,
    "partition_exact": "SELECT element, string_agg(s, ' ' ORDER BY s) AS symbols FROM fs GROUP BY element, no, sub",
    "interleavings_exact": "SELECT element, factors - 1 AS interleavings FROM texts",
    "simplified_exact": "SELECT element, sizes FROM texts",
    "schema_exact": "SELECT element, 'exact' AS learner, words, 'ok' AS status, repaired, text FROM texts",
    "schema_is": "SELECT element, 'is' AS learner, words, 'ok' AS status, repaired, text FROM texts",
    "compare_chain": AGAINST_CHAIN,
    "chain": "SELECT total.element, coalesce(string_agg(t, ' ' ORDER BY pos), '') AS text FROM total LEFT JOIN links USING (element) GROUP BY total.element",
    "chain_coverage": "SELECT element, words, words AS accepted FROM total",
    "disjunctive": "SELECT element, string_agg(CASE WHEN n > 1 THEN '(' || names || ')' ELSE names END || CASE WHEN always THEN CASE WHEN many THEN '+' ELSE '' END WHEN many THEN '*' ELSE '?' END, ' & ' ORDER BY no) AS text FROM judged GROUP BY element",
    "exclusive_pairs": "SELECT a.element, a.symbol AS x, b.symbol AS y FROM counts a JOIN counts b ON a.element = b.element AND a.symbol < b.symbol ANTI JOIN (SELECT element, x AS symbol, y FROM together) t ON t.element = a.element AND t.symbol = a.symbol AND t.y = b.symbol",
    "global_order": "SELECT element, CASE WHEN 2 * up >= t THEN u ELSE v END AS x, CASE WHEN 2 * up >= t THEN v ELSE u END AS y, round(greatest(up, t - up) / t, 6) AS share FROM (SELECT a.element, a.s AS u, b.s AS v, count(*) AS t, count(*) FILTER (WHERE a.f < b.f) AS up FROM prof a JOIN prof b USING (element, word_id) WHERE a.s < b.s GROUP BY ALL) WHERE round(greatest(up, t - up) / t, 6) > 0.5",
    "length": "SELECT element, 'exact' AS learner, (symbols + ops + factors - 1)::BIGINT AS tokens, (orders * (symbols + ops) + orders - 1)::DOUBLE AS block_tokens FROM (SELECT element, count(*) AS factors, sum(n) AS symbols, sum(ops) AS ops, factorial(sum(n)::INTEGER) // product(factorial(n::INTEGER)) AS orders FROM factors GROUP BY element)",
    "coverage": "SELECT element, learner, count(*) AS words, count(*) FILTER (WHERE learner <> 'exact' OR reason = 'ok') AS accepted, round(accepted / words, 6) AS coverage FROM verdict, (VALUES ('exact'), ('is'), ('dag')) l(learner) GROUP BY ALL",
    "compare_star": f"SELECT element, CASE WHEN bool_and(mult = '*') AND (SELECT count(*) FROM pairs q WHERE q.element = c.element AND {REVERSE}) = count(*) * (count(*) - 1) THEN 'equal' ELSE 'subset' END AS relation FROM mults c GROUP BY element",
}

#: Workloads of too many symbols for masks over all of them; none of their sets is cyclic.
LARGE = ("pages", "planted")


def over(words: str, select: str, u: str = "", large: bool = False, excluded: bool = False) -> str:
    """``select`` over the words of a SELECT, with the relations that it uses.

    ``u``: words to be judged, the same ones if empty; ``excluded``: sets by excluding cliques.
    """
    blocks = [RELATIONS, EXCLUDED_SETS if excluded else CONFLICT_SETS, WHOLE if large else ACYCLIC, CHAINS, CLASSES, CHOICES, u or "u AS (SELECT * FROM w)", MEMBERSHIP]
    used, text = [], select
    for block in reversed(blocks):
        if set(re.findall(r"^(\w+) AS \(", block, re.M)) & set(re.findall(r"\w+", text)):
            used.insert(0, block.strip())
            text += block
    return f"WITH RECURSIVE w AS ({words}),\n" + ",\n".join(used or [RELATIONS.strip()]) + f"\n{select}"


#: Three changed words for each word: first two symbols swapped, last one doubled, first one left out.
PERTURBED = """u AS (
  SELECT element, word_id || '/' || kind AS word_id, CASE kind WHEN 'swap' THEN CASE WHEN len(symbols) > 1 THEN [symbols[2], symbols[1]] || symbols[3:] ELSE symbols END WHEN 'double' THEN list_append(symbols, symbols[-1]) ELSE symbols[2:] END AS symbols
  FROM w, (VALUES ('swap'), ('double'), ('drop')) changed(kind) WHERE len(symbols) > 0)"""

#: All orders of some of an element's symbols, named by symbols with their multiplicities.  Every multiplicity allows a symbol once.
PERMUTED = """u AS (
  SELECT element, '' AS word_id, []::VARCHAR[] AS symbols FROM total
  UNION ALL
  SELECT u.element, u.word_id || CASE WHEN u.word_id = '' THEN '' ELSE ' ' END || mults.symbol || CASE WHEN mult = '1' THEN '' ELSE mult END, list_append(u.symbols, mults.symbol)
  FROM u JOIN mults ON mults.element = u.element WHERE NOT list_contains(u.symbols, mults.symbol))"""

#: All words of up to three of an element's symbols.
UP_TO_THREE = """u AS (
  SELECT element, array_to_string(symbols, ' ') AS word_id, symbols FROM (
    SELECT element, []::VARCHAR[] AS symbols FROM total UNION ALL SELECT element, [symbol] FROM counts
    UNION ALL SELECT a.element, [a.symbol, b.symbol] FROM counts a JOIN counts b USING (element)
    UNION ALL SELECT a.element, [a.symbol, b.symbol, c.symbol] FROM counts a JOIN counts b USING (element) JOIN counts c USING (element)))"""
