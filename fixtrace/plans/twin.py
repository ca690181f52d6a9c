"""The history corpus once more, in SQL for the checking engine; the twins of workloads build on these.

The engine's twin shares the templates and the table of sensitive functions with the Spark side, nothing else.
"""

from fixtrace.operators import weights
from fixtrace.sources import code

HISTORY = """
ordered AS (
  SELECT c_nationkey AS repo_id, o_orderkey AS commit_id, o_orderdate AS committed_at, CASE WHEN o_orderstatus = 'P' THEN 'feature' ELSE 'main' END AS lane,
         (c_nationkey * 1000 + o_custkey % 12)::INT AS file_id, o_orderpriority AS priority, o_totalprice AS price,
         row_number() OVER (PARTITION BY c_nationkey ORDER BY o_orderdate, o_orderkey)::INT AS seq
  FROM orders JOIN customer ON o_custkey = c_custkey
), placed AS (SELECT *, ((seq - 1) // 12)::INT AS block FROM ordered),
branch AS (
  SELECT repo_id, block, min(seq) AS first_feature, max(seq) AS tip,
    coalesce((SELECT max(m.seq) FROM placed m WHERE m.repo_id = p.repo_id AND m.lane = 'main' AND m.seq < min(p.seq)), 0) AS fork,
    CASE WHEN block % 5 <> 0 THEN (SELECT min(m.seq) FROM placed m WHERE m.repo_id = p.repo_id AND m.lane = 'main' AND m.block > p.block) END AS mseq
  FROM placed p WHERE lane = 'feature' GROUP BY repo_id, block
), commits AS (
  SELECT p.*, CASE WHEN lane = 'main' THEN seq ELSE b.fork END AS fork, CASE WHEN lane = 'feature' THEN b.mseq END AS mseq
  FROM placed p LEFT JOIN branch b USING (repo_id, block)
), edges AS (
  SELECT c.repo_id, c.commit_id AS child_id, p.commit_id AS parent_id, 0 AS parent_no FROM (
    SELECT repo_id, commit_id, CASE WHEN lane = 'main' THEN lag(seq) OVER (PARTITION BY repo_id, lane ORDER BY seq)
      ELSE coalesce(lag(seq) OVER (PARTITION BY repo_id, lane, block ORDER BY seq), fork) END AS pseq FROM commits
  ) c JOIN commits p ON p.repo_id = c.repo_id AND p.seq = c.pseq
  UNION ALL
  SELECT b.repo_id, m.commit_id, t.commit_id, 1 FROM branch b JOIN commits m ON m.repo_id = b.repo_id AND m.seq = b.mseq JOIN commits t ON t.repo_id = b.repo_id AND t.seq = b.tip
), tags AS (
  SELECT repo_id, 'v' || (r // 10) AS tag, (r // 10)::INT AS tag_no, commit_id, seq FROM (
    SELECT *, row_number() OVER (PARTITION BY repo_id ORDER BY seq) AS r FROM commits WHERE lane = 'main') WHERE r % 10 = 0
), lines AS (
  SELECT l_orderkey AS commit_id, l_linenumber::INT AS slot, l_partkey AS part, floor(l_quantity)::INT AS quantity, l_returnflag AS flag FROM lineitem
  QUALIFY row_number() OVER (PARTITION BY l_orderkey, l_linenumber ORDER BY l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_shipdate, l_returnflag) = 1
), touches AS (
  SELECT repo_id, file_id, slot, commit_id, committed_at, seq, block, lane, fork, mseq, CASE flag WHEN 'A' THEN 'add' WHEN 'R' THEN 'del' ELSE 'ctx' END AS op, quantity % 4 AS edit_kind
  FROM lines JOIN commits USING (commit_id)
), cases AS (
  SELECT commit_id AS vuln_id, repo_id, commit_id AS fix_commit_id, seq AS fix_seq, file_id,
    CASE WHEN added = 0 THEN 'del' WHEN deleted = 0 THEN 'add' ELSE 'both' END AS patch_class, (part % 7)::INT AS vuln_type, added, deleted, trigger_slot,
    committed_at AS published_at, least(10.0, round(price / 50000, 1)) AS severity
  FROM commits JOIN (
    SELECT commit_id, count(*) FILTER (WHERE flag = 'A') AS added, count(*) FILTER (WHERE flag = 'R') AS deleted, min(part) AS part,
      min(slot) FILTER (WHERE flag IN ('A', 'R')) AS trigger_slot FROM lines GROUP BY commit_id) USING (commit_id)
  WHERE lane = 'main' AND priority = '1-URGENT' AND commit_id % 16 = 0 AND added + deleted > 0
)"""


def _quoted(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"


def _listed(families) -> str:
    """The templates of a family as nested SQL lists."""
    return "[" + ", ".join(f"[{_quoted(a)}, {_quoted(b)}]" for a, b in families) + "]"


_CALLED = r"regexp_extract_all({}, '([A-Za-z_]\w*)\s*\(', 1)"

#: Touches of patched files with path counts, texts and predecessors; pairs of texts with their line similarity.
STATES = f"""
patched AS (SELECT DISTINCT file_id FROM cases),
mains AS (
  SELECT *, lag(commit_id) OVER w AS pred0, {", ".join(f"count(*) FILTER (WHERE edit_kind = {k}) OVER w AS n{k}" for k in range(4))}
  FROM touches WHERE lane = 'main' AND file_id IN (FROM patched) WINDOW w AS (PARTITION BY file_id, slot ORDER BY seq)
), branched AS (
  SELECT t.*, m.commit_id AS base, m.seq AS base_seq, {", ".join(f"coalesce(m.n{k}, 0) AS b{k}" for k in range(4))}
  FROM (SELECT * FROM touches WHERE lane = 'feature' AND file_id IN (FROM patched)) t ASOF LEFT JOIN mains m ON m.file_id = t.file_id AND m.slot = t.slot AND t.fork >= m.seq
), states AS (
  SELECT file_id, slot, commit_id, repo_id, seq, block, lane, fork, mseq, edit_kind, pred0, n0, n1, n2, n3 FROM mains
  UNION ALL SELECT file_id, slot, commit_id, repo_id, seq, block, lane, fork, mseq, edit_kind, coalesce(lag(commit_id) OVER w, base),
    {", ".join(f"b{k} + count(*) FILTER (WHERE edit_kind = {k}) OVER w" for k in range(4))} FROM branched WINDOW w AS (PARTITION BY file_id, slot, block ORDER BY seq)
), spelled AS (
  SELECT *, replace(replace(replace(CASE WHEN (file_id + slot) % 3 = 0 THEN {_listed(code.LISTED)}[(n2 % 4 + 1)::INT][(n1 % 2 + 1)::INT] ELSE {_listed(code.PLAIN)}[(n2 % 4 + 1)::INT][(n1 % 2 + 1)::INT] END,
    '_S', '_' || slot), '_F', '_' || file_id), 'K', (100 + n0 % 900)::VARCHAR) AS bare FROM states
), content AS (SELECT *, CASE WHEN n3 % 2 = 1 THEN '    ' || replace(bare, ', ', ',  ') || ' /* kept */' ELSE bare END AS text FROM spelled),
pairs AS (
  SELECT *, CASE WHEN a = b OR greatest(length(a), length(b)) = 0 THEN 1.0::DOUBLE ELSE 1 - levenshtein(a, b)::DOUBLE / greatest(length(a), length(b)) END AS sim FROM (
    SELECT s.*, p.text AS pre, trim(regexp_replace(regexp_replace(p.text, '(?s)/\\*.*?\\*/|//[^\\n]*', ' ', 'g'), '\\s+', ' ', 'g')) AS a,
      trim(regexp_replace(regexp_replace(s.text, '(?s)/\\*.*?\\*/|//[^\\n]*', ' ', 'g'), '\\s+', ' ', 'g')) AS b
    FROM content s LEFT JOIN content p ON p.file_id = s.file_id AND p.slot = s.slot AND p.commit_id = s.pred0)
)"""

#: Statements of the patches as they were before the fix, with what makes them sensitive.
STATEMENTS = f"""
listed(vuln_type, fn) AS (VALUES {", ".join(f"({k}, {_quoted(fn)})" for k, fns in enumerate(weights.SENSITIVE.values()) for fn in fns)}),
helpers(name, body) AS (VALUES {", ".join(f"({_quoted(n)}, {_quoted(b)})" for n, _, _, b in code.CALLEES)}),
hot AS (SELECT vuln_type, list(fn) AS fns FROM (FROM listed UNION SELECT l.vuln_type, h.name FROM helpers h JOIN listed l ON list_contains({_CALLED.format("h.body")}, l.fn)) GROUP BY vuln_type),
stmts AS (
  SELECT s.*, list_has_any(fns, list_concat({_CALLED.format("text")}, CASE WHEN regexp_matches(text, '[^+]\\+[^+]') THEN ['+'] ELSE [] END,
    CASE WHEN regexp_matches(text, '[\\w)\\]]\\s*\\*\\s*[\\w(]') THEN ['*'] ELSE [] END, CASE WHEN contains(text, '<<') THEN ['<<'] ELSE [] END)) AS sensitive
  FROM (SELECT c.vuln_id, c.repo_id, c.file_id, c.fix_seq, c.vuln_type, l.slot, l.flag, arg_max(t.text, t.seq) AS text, arg_max(t.b, t.seq) AS line FROM cases c
    JOIN lines l ON l.commit_id = c.vuln_id AND l.flag IN ('A', 'R') JOIN pairs t ON t.file_id = c.file_id AND t.slot = l.slot AND t.lane = 'main' AND t.seq < c.fix_seq GROUP BY ALL) s
  JOIN hot USING (vuln_type)
)"""

#: Whether a compared touch lost its statement: planted kinds stand for both levels, the computed similarity for the line level.
BOTH_LEVELS = "pred0 IS NULL OR (edit_kind = 2 AND sim < 0.8995)"


def by_line(permille: int) -> str:
    return f"pred0 IS NULL OR round(sim * 1000) < {permille}"


def engine(name: str, lost: str = BOTH_LEVELS, weight: str = "CASE WHEN sensitive THEN 2.0 ELSE 1.0 END", merges: bool = True, theta: str = "700", of: str = "stmts", params: str = "") -> str:
    """CTEs up to ``name`` (vuln_id, repo_id, oseq, score, and the columns of ``params``): the origin that the walk finds."""
    p = f"{name}_"
    key = "".join(f"{c}, " for c in params.split())
    marked = f"SELECT *, {lost} AS lost FROM pairs" + (" CROSS JOIN params" if params else "")
    inside = f"""UNION ALL SELECT {key}vuln_id, slot, own FROM {p}met WHERE own IS NOT NULL
      UNION ALL SELECT {key}vuln_id, slot, seq FROM (SELECT {"".join(f"m.{c}, " for c in params.split())}m.vuln_id, m.slot, m.at_fork, max(t.seq) AS seq FROM {p}met m JOIN {p}lost t ON t.file_id = m.file_id AND t.slot = m.slot {"".join(f"AND t.{c} = m.{c} " for c in params.split())}
        AND t.lane = 'main' AND t.lost AND t.seq <= m.at_fork WHERE m.own IS NULL GROUP BY ALL)""" if merges else ""
    return f"""
{p}lost AS MATERIALIZED ({marked}),
{p}main AS (SELECT {key}s.vuln_id, s.repo_id, s.file_id, s.slot, s.fix_seq, max(t.seq) AS stop FROM {of} s JOIN {p}lost t ON t.file_id = s.file_id AND t.slot = s.slot AND t.lane = 'main' AND t.lost AND t.seq < s.fix_seq GROUP BY ALL),
{p}branch AS (SELECT {key}file_id, slot, block, any_value(fork) AS at_fork, any_value(mseq) AS at, max(seq) FILTER (WHERE lost) AS own FROM {p}lost WHERE lane = 'feature' AND mseq IS NOT NULL GROUP BY ALL),
{p}met AS (SELECT m.*, b.at_fork, b.own FROM {p}main m JOIN {p}branch b ON b.file_id = m.file_id AND b.slot = m.slot {"".join(f"AND b.{c} = m.{c} " for c in params.split())}WHERE b.at <= m.fix_seq AND b.at > m.stop),
{p}stops AS (SELECT {key}vuln_id, slot, min(stop) AS stop FROM (SELECT {key}vuln_id, slot, stop FROM {p}main {inside}) GROUP BY ALL),
{scored(name, f"{p}stops", weight, theta, of, params)}"""


def scored(name: str, stops: str, weight: str = "CASE WHEN sensitive THEN 2.0 ELSE 1.0 END", theta: str = "700", of: str = "stmts", params: str = "") -> str:
    """CTEs up to ``name``: the latest stop at which the kept weight falls below theta."""
    p, key = f"{name}_", "".join(f"{c}, " for c in params.split())
    using = f"JOIN params USING ({params.replace(' ', ', ')})" if params else ""
    return f"""{p}per AS (SELECT {key}s.vuln_id, s.repo_id, x.stop, sum({weight}) AS w FROM {of} s JOIN {stops} x ON x.vuln_id = s.vuln_id AND x.slot = s.slot {using} GROUP BY ALL),
{p}run AS (SELECT *, 1 - sum(w) OVER (PARTITION BY {key}vuln_id ORDER BY stop DESC) / sum(w) OVER (PARTITION BY {key}vuln_id) AS score FROM {p}per),
{name} AS (SELECT {key}vuln_id, repo_id, stop AS oseq, score::DOUBLE AS score FROM {p}run {using} WHERE round(score * 1000) < {theta} QUALIFY row_number() OVER (PARTITION BY {key}vuln_id ORDER BY stop DESC) = 1)"""


def holds(outer: str, inner: str) -> str:
    """Whether the commit of row ``outer`` has that of row ``inner`` in its history, from branch labels."""
    return f"""({outer}.repo_id = {inner}.repo_id AND (coalesce(CASE WHEN {inner}.lane = 'main' THEN {inner}.seq ELSE {inner}.mseq END <= {outer}.fork, FALSE)
      OR ({inner}.lane = 'feature' AND {outer}.lane = 'feature' AND {inner}.block = {outer}.block AND {inner}.seq <= {outer}.seq)))"""


#: Touches that a touch was made upon, and the walk back over all of them; it ends where a statement is lost.
WALKS = f"""
held_pairs AS MATERIALIZED (SELECT c.file_id, c.slot, c.commit_id, x.commit_id AS pred FROM states c JOIN states x ON x.file_id = c.file_id AND x.slot = c.slot AND x.commit_id <> c.commit_id AND {holds("c", "x")}),
preds AS MATERIALIZED (SELECT * FROM held_pairs h WHERE NOT EXISTS (SELECT 1 FROM held_pairs y JOIN held_pairs z ON z.file_id = y.file_id AND z.slot = y.slot AND z.commit_id = y.pred
  WHERE y.file_id = h.file_id AND y.slot = h.slot AND y.commit_id = h.commit_id AND z.pred = h.pred)),
gone AS MATERIALIZED (SELECT file_id, slot, commit_id, seq FROM pairs WHERE {BOTH_LEVELS}),
steps AS (
  SELECT s.vuln_id, s.slot, s.file_id, p.commit_id, p.pred, 0 AS later FROM stmts s JOIN preds p ON p.file_id = s.file_id AND p.slot = s.slot AND p.commit_id = s.vuln_id
  UNION SELECT t.vuln_id, t.slot, t.file_id, p.commit_id, p.pred, 1 FROM steps t JOIN preds p ON p.file_id = t.file_id AND p.slot = t.slot AND p.commit_id = t.pred
  WHERE NOT EXISTS (SELECT 1 FROM gone g WHERE g.file_id = t.file_id AND g.slot = t.slot AND g.commit_id = t.pred)
), walked AS (SELECT t.vuln_id, t.slot, min(g.seq) AS stop FROM steps t JOIN gone g ON g.file_id = t.file_id AND g.slot = t.slot AND g.commit_id = t.pred GROUP BY ALL)"""

#: The patched file of each case at each tag, just before the fix, and what the fix puts in and takes out, as lists of lines.
SNAPSHOTS = """
snaps AS (SELECT k.vuln_id, k.repo_id, g.tag_no, t.slot, arg_max(t.b, t.seq) AS line FROM cases k JOIN tags g ON g.repo_id = k.repo_id JOIN pairs t ON t.file_id = k.file_id AND t.lane = 'main' AND t.seq <= g.seq GROUP BY ALL),
versions AS (SELECT vuln_id, repo_id, tag_no, list(line ORDER BY slot) AS held FROM snaps GROUP BY ALL),
ahead AS (SELECT k.vuln_id, t.slot, arg_max(t.b, t.seq) AS line FROM cases k JOIN pairs t ON t.file_id = k.file_id AND t.lane = 'main' AND t.seq < k.fix_seq GROUP BY ALL),
bodies AS (SELECT vuln_id, list(line ORDER BY slot) AS body FROM ahead GROUP BY ALL),
changed AS (SELECT s.vuln_id, list(s.line) FILTER (WHERE s.flag = 'R') AS deleted, list(t.b) AS added FROM stmts s JOIN pairs t ON t.file_id = s.file_id AND t.slot = s.slot AND t.commit_id = s.vuln_id GROUP BY s.vuln_id)"""


def blamed(name: str, touched: str, lost: str) -> str:
    """CTE ``name`` (vuln_id, repo_id, oseq): the earliest over deleted lines of the last main touch that ``lost`` holds for."""
    return f"""{name} AS (SELECT vuln_id, repo_id, min(seq) AS oseq FROM (
      SELECT s.vuln_id, s.repo_id, s.slot, max(t.seq) AS seq FROM stmts s JOIN {touched} t ON t.file_id = s.file_id AND t.slot = s.slot AND t.lane = 'main' AND t.seq < s.fix_seq
      WHERE s.flag = 'R' AND ({lost}) GROUP BY ALL) GROUP BY ALL)"""


def affected(name: str, origins: str, key: str = "") -> str:
    """CTE ``name`` (vuln_id, repo_id, tag_no): tags between the arrival of an origin and the fix."""
    return f"""{name} AS (SELECT DISTINCT {key}o.vuln_id, o.repo_id, g.tag_no FROM {origins} o JOIN commits c ON c.repo_id = o.repo_id AND c.seq = o.oseq JOIN cases k ON k.vuln_id = o.vuln_id
      JOIN tags g ON g.repo_id = o.repo_id AND g.seq >= CASE WHEN c.lane = 'main' THEN c.seq ELSE c.mseq END AND g.seq < k.fix_seq)"""
