"""SQL twins of the workloads, for the checking engine."""

from __future__ import annotations

from fixtrace.plans import twin
from fixtrace.plans.twin import HISTORY

TRUTH = HISTORY + """, origins AS (
  SELECT c.vuln_id, c.repo_id, c.fix_seq, c.trigger_slot, coalesce(max(t.seq) FILTER (WHERE t.edit_kind = 2), min(t.seq)) AS oseq
  FROM cases c LEFT JOIN touches t ON t.file_id = c.file_id AND t.slot = c.trigger_slot AND t.lane = 'main' AND t.seq < c.fix_seq GROUP BY ALL
), truth AS (
  SELECT o.vuln_id, o.repo_id, g.tag_no, g.tag FROM origins o JOIN tags g ON g.repo_id = o.repo_id AND g.seq >= o.oseq AND g.seq < o.fix_seq
), claims AS (
  SELECT c.vuln_id, c.repo_id, c.severity, s.first + (c.vuln_id // 16) % s.n AS source_id, x.a, x.b,
    ['exact', 'single', 'all_before', 'missing', 'stale'][((s.first + (c.vuln_id // 16) % s.n) % 5 + 1)::INT] AS pattern
  FROM cases c CROSS JOIN (SELECT min(s_suppkey) AS first, count(*) AS n FROM supplier) s
  LEFT JOIN (SELECT vuln_id, min(tag_no) AS a, max(tag_no) AS b FROM truth GROUP BY vuln_id) x USING (vuln_id)
), bounds AS (
  SELECT *, CASE WHEN a IS NOT NULL THEN CASE pattern WHEN 'single' THEN b WHEN 'all_before' THEN 1 WHEN 'missing' THEN NULL ELSE a END END AS lo,
    CASE WHEN a IS NOT NULL THEN CASE pattern WHEN 'stale' THEN b - 1 WHEN 'missing' THEN NULL ELSE b END END AS hi FROM claims
), audited AS (
  SELECT *, CASE WHEN pattern <> 'missing' THEN greatest(0, coalesce(b - a + 1, 0) - n_both) END AS n_missing, CASE WHEN pattern <> 'missing' THEN n_claimed - n_both END AS n_extra
  FROM (SELECT *, CASE WHEN lo <= hi THEN hi - lo + 1 ELSE 0 END AS n_claimed, CASE WHEN lo <= hi THEN greatest(0, least(hi, b) - greatest(lo, a) + 1) ELSE 0 END AS n_both FROM bounds)
), named AS (
  SELECT *, CASE WHEN pattern = 'missing' THEN 'missing' WHEN n_missing > 0 AND n_extra > 0 THEN 'mixed' WHEN n_missing > 0 THEN 'incomplete' WHEN n_extra > 0 THEN 'over_inclusive' ELSE 'correct' END AS audit FROM audited
)"""
_RATES = """round(CASE WHEN tp + fp > 0 THEN tp / (tp + fp) END, 6) AS precision, round(CASE WHEN tp + fn > 0 THEN tp / (tp + fn) END, 6) AS recall,
  round(CASE WHEN tp + fp > 0 AND tp + fn > 0 AND tp > 0 THEN 2.0 * tp / (2 * tp + fp + fn) END, 6) AS f1"""
_CLAIMED = TRUTH + """, claimed AS (SELECT b.vuln_id, b.repo_id, g.tag_no FROM bounds b JOIN tags g ON g.repo_id = b.repo_id AND g.tag_no BETWEEN lo AND hi),
  met AS (SELECT coalesce(c.vuln_id, t.vuln_id) AS vuln_id, coalesce(c.repo_id, t.repo_id) AS repo_id, c.vuln_id IS NOT NULL AS p, t.vuln_id IS NOT NULL AS r
          FROM claimed c FULL JOIN truth t ON c.vuln_id = t.vuln_id AND c.tag_no = t.tag_no)"""
_COUNTS = "count(*) FILTER (WHERE p AND r) AS tp, count(*) FILTER (WHERE p AND NOT r) AS fp, count(*) FILTER (WHERE r AND NOT p) AS fn"
_RUNS = "runs AS (SELECT user_id AS vuln_id, (event_id % 10)::INT AS run_no, event_type AS stmt, json_extract(props, '$.k')::INT AS tokens_in, (event_id % 97)::INT AS tokens_out FROM events)"
_LINES = """l AS (SELECT doc_id, i - 1 AS line_no, x[i] AS x FROM (SELECT doc_id, x, unnest(range(1, len(x) + 1)) AS i FROM (SELECT doc_id, string_split(text, chr(10)) AS x FROM documents WHERE text IS NOT NULL))),
  near AS (SELECT doc_id, source, lead(doc_id) OVER (PARTITION BY source ORDER BY doc_id) AS doc_b FROM documents),
  lp AS (SELECT source, a.x AS a, b.x AS b FROM near n JOIN l a ON a.doc_id = n.doc_id JOIN l b ON b.doc_id = n.doc_b AND b.line_no = a.line_no)"""
#: This engine's levenshtein counts bytes, so the letters of the four languages become single unused ones.
_LETTERS = "èéÍÊÄñÉßêçíÇÈÑüöÖóÓäÜáàâîôûú"
_SINGLE = f"translate({{}}, '{_LETTERS}', " + " || ".join(f"chr({k})" for k in [*range(1, 10), *range(11, 32)][: len(_LETTERS)]) + ")"

SQL = {
    "w01_dataset_profile": f"""WITH {HISTORY} SELECT n_nationkey AS repo_id, n_name AS name, r_name AS domain, (SELECT count(*) FROM commits c WHERE c.repo_id = n_nationkey) AS n_commits,
      (SELECT count(*) FROM tags t WHERE t.repo_id = n_nationkey) AS n_tags, (SELECT count(*) FROM cases k WHERE k.repo_id = n_nationkey) AS n_cases FROM nation JOIN region ON n_regionkey = r_regionkey""",
    "w02_patch_classes": f"WITH {HISTORY} SELECT patch_class, count(*) AS n_fixes, sum(added)::BIGINT AS added, sum(deleted)::BIGINT AS deleted, count(*) FILTER (WHERE added + deleted > 50) AS n_large FROM cases GROUP BY patch_class",
    "w02_weakness_types": f"""WITH {HISTORY} SELECT t AS vuln_type, count(*) AS n_cases, ['buffer overflow', 'integer overflow', 'null dereference', 'pointer out of bounds', 'use after free', 'format string', 'command execution'][t + 1] AS weakness
      FROM (SELECT vuln_type AS t FROM cases UNION ALL SELECT (vuln_type + 1) % 7 FROM cases WHERE (vuln_id // 16) % 5 = 0) GROUP BY t""",
    "w03_truth": f"""WITH {TRUTH} SELECT o.vuln_id, o.trigger_slot, c.commit_id AS origin_commit_id, (SELECT count(*) FROM truth t WHERE t.vuln_id = o.vuln_id) AS n_versions
      FROM origins o LEFT JOIN commits c ON c.repo_id = o.repo_id AND c.seq = o.oseq""",
    "w03_claims": f"WITH {_CLAIMED} SELECT *, {_RATES} FROM (SELECT repo_id, {_COUNTS} FROM met GROUP BY repo_id)",
    "w03_basic_blame": f"""WITH {HISTORY}, last AS (SELECT c.vuln_id, c.repo_id, l.slot, max(t.seq) AS seq FROM cases c JOIN lines l ON l.commit_id = c.vuln_id AND l.flag = 'R'
      JOIN touches t ON t.file_id = c.file_id AND t.slot = l.slot AND t.lane = 'main' AND t.seq < c.fix_seq GROUP BY ALL)
      SELECT vuln_id, commit_id AS origin_commit_id, m.seq AS origin_seq FROM (SELECT vuln_id, repo_id, min(seq) AS seq FROM last GROUP BY ALL) m JOIN commits c ON c.repo_id = m.repo_id AND c.seq = m.seq""",
    "w03_engine_first_parent": f"""WITH {HISTORY}, stops AS (SELECT c.vuln_id, c.repo_id, l.slot, coalesce(max(t.seq) FILTER (WHERE t.edit_kind = 2), min(t.seq)) AS seq FROM cases c JOIN lines l ON l.commit_id = c.vuln_id AND l.flag IN ('A', 'R')
      JOIN touches t ON t.file_id = c.file_id AND t.slot = l.slot AND t.lane = 'main' AND t.seq < c.fix_seq GROUP BY ALL),
      run AS (SELECT vuln_id, repo_id, seq, 1 - sum(n) OVER (PARTITION BY vuln_id ORDER BY seq DESC) / sum(n) OVER (PARTITION BY vuln_id) AS score FROM (SELECT vuln_id, repo_id, seq, count(*) AS n FROM stops GROUP BY ALL)),
      top AS (SELECT * FROM run WHERE round(score * 1000) < 700 QUALIFY row_number() OVER (PARTITION BY vuln_id ORDER BY seq DESC) = 1)
      SELECT vuln_id, commit_id AS origin_commit_id, round(score, 6) AS score FROM top t JOIN commits c ON c.repo_id = t.repo_id AND c.seq = t.seq""",
    "w08_vote": f"WITH {_RUNS} SELECT vuln_id, stmt, count(DISTINCT run_no) AS votes FROM runs GROUP BY ALL HAVING count(DISTINCT run_no) >= 6",
    "w08_agreement": f"WITH {_RUNS} SELECT count(*) FILTER (WHERE n = 10) AS n_unanimous, count(*) AS n_statements, round(count(*) FILTER (WHERE n = 10) / count(*), 6) AS agreement FROM (SELECT count(DISTINCT run_no) AS n FROM runs GROUP BY vuln_id, stmt)",
    "w08_jaccard": f"""WITH {_RUNS}, s AS (SELECT vuln_id, run_no, list(DISTINCT stmt) AS s FROM runs GROUP BY ALL),
      j AS (SELECT a.vuln_id, len(list_intersect(a.s, b.s)) / len(list_distinct(list_concat(a.s, b.s))) AS j FROM s a JOIN s b ON a.vuln_id = b.vuln_id AND a.run_no < b.run_no),
      c AS (SELECT avg(j) AS j FROM j GROUP BY vuln_id HAVING min(j) < 1) SELECT count(*) AS n_cases, round(avg(j), 6) AS mean_jaccard FROM c""",
    "w09_cutoff_split": f"""WITH {_CLAIMED}, q AS (SELECT quantile_cont((published_at::DATE - DATE '1970-01-01')::DOUBLE, [0.25, 0.5, 0.75]) AS q FROM cases),
      cuts AS (SELECT unnest([0, 1, 2]) AS cut, last_day(DATE '1970-01-01' + floor(unnest(q))::INT) AS until FROM q),
      side AS (SELECT vuln_id, cut, CASE WHEN published_at::DATE <= until THEN 'pre' ELSE 'post' END AS side FROM cases CROSS JOIN cuts)
      SELECT *, {_RATES} FROM (SELECT cut, side, {_COUNTS} FROM met JOIN side USING (vuln_id) GROUP BY cut, side)""",
    "w11_edit": f"""WITH {_LINES}, one AS (SELECT source, {_SINGLE.format('a')} AS a, {_SINGLE.format('b')} AS b FROM lp)
      SELECT source, count(*) AS n_pairs, count(*) FILTER (WHERE a = b OR (abs(length(a) - length(b)) <= (200 * greatest(length(a), length(b))) // 1000
      AND levenshtein(a, b) <= (200 * greatest(length(a), length(b))) // 1000)) AS n_similar FROM one GROUP BY source""",
    "w11_md5": f"WITH {_LINES} SELECT source, count(*) AS n_pairs, count(*) FILTER (WHERE trim(regexp_replace(a, ' +', ' ', 'g'), ' ') = trim(regexp_replace(b, ' +', ' ', 'g'), ' ')) AS n_equal FROM lp GROUP BY source",
    "w11_cosine": """WITH p AS (SELECT a.label = b.label AS same, list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) AS c FROM embeddings a JOIN embeddings b ON a.vec_id % 100 = 0 AND a.vec_id <> b.vec_id)
      SELECT theta, count(*) FILTER (WHERE c >= theta AND same) AS tp, count(*) FILTER (WHERE c >= theta AND NOT same) AS fp, count(*) FILTER (WHERE c < theta AND same) AS fn
      FROM p CROSS JOIN (SELECT unnest([0.1, 0.2, 0.3, 0.4, 0.5])::DOUBLE AS theta) GROUP BY theta""",
    "w12_refactor_share": f"""WITH {HISTORY}, f AS (SELECT DISTINCT file_id FROM cases),
      t AS (SELECT * FROM touches WHERE file_id IN (FROM f)),
      k AS (SELECT edit_kind FROM t WHERE (lane = 'main' AND EXISTS (SELECT 1 FROM t x WHERE x.file_id = t.file_id AND x.slot = t.slot AND x.lane = 'main' AND x.seq < t.seq))
        OR (lane = 'feature' AND EXISTS (SELECT 1 FROM t x WHERE x.file_id = t.file_id AND x.slot = t.slot AND ((x.lane = 'main' AND x.seq <= t.fork) OR (x.lane = 'feature' AND x.block = t.block AND x.seq < t.seq)))))
      SELECT count(*) AS n_compared, count(*) FILTER (WHERE edit_kind = 1) AS n_refactorings, round(count(*) FILTER (WHERE edit_kind = 1) / count(*), 6) AS share FROM k""",
    "w14_claim_audit": f"""WITH {TRUTH} SELECT vuln_id, source_id, pattern, audit, CASE WHEN audit = 'incomplete' AND n_claimed = 1 THEN 'single_version' WHEN audit = 'over_inclusive' AND lo = 1 THEN 'all_before' END AS pattern_found,
      n_missing::INT AS n_missing, n_extra::INT AS n_extra FROM named""",
    "w14_severity": f"""WITH {TRUTH} SELECT audit, CASE WHEN severity >= 9 THEN 'critical' WHEN severity >= 7 THEN 'high' WHEN severity >= 4 THEN 'medium' ELSE 'low' END AS severity_band, count(*) AS n_cases FROM named GROUP BY ALL""",
    "w15_judge_cost": f"WITH {_RUNS} SELECT vuln_id, sum(tokens_in)::BIGINT AS tokens_in, sum(tokens_out)::BIGINT AS tokens_out, round((sum(tokens_in) * 0.30 + sum(tokens_out) * 1.10)::DOUBLE / 1000000, 9) AS cost FROM runs GROUP BY vuln_id",
    "w16_affected_versions": f"""WITH RECURSIVE {TRUTH}, marks AS (
        SELECT vuln_id, repo_id, fix_commit_id AS commit_id, 'fix' AS kind FROM cases
        UNION ALL SELECT o.vuln_id, o.repo_id, c.commit_id, 'origin' FROM origins o JOIN commits c ON c.repo_id = o.repo_id AND c.seq = o.oseq),
      held AS (SELECT vuln_id, kind, commit_id FROM marks UNION SELECT h.vuln_id, h.kind, e.child_id FROM held h JOIN edges e ON e.parent_id = h.commit_id)
      SELECT h.vuln_id, g.repo_id, g.tag_no, g.tag FROM held h JOIN tags g USING (commit_id) WHERE kind = 'origin'
        AND NOT EXISTS (SELECT 1 FROM held f WHERE f.vuln_id = h.vuln_id AND f.kind = 'fix' AND f.commit_id = h.commit_id)""",
    "w16_ranges": f"WITH {TRUTH} SELECT vuln_id, min(tag_no) AS lo, max(tag_no) + 1 AS hi FROM (SELECT *, tag_no - row_number() OVER (PARTITION BY vuln_id ORDER BY tag_no) AS i FROM truth) GROUP BY vuln_id, i",
    "w17_signature_hits": "SELECT DISTINCT d.doc_id, b.item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)",
    "w18_digest_clones": "SELECT md5(text) AS digest, count(*) AS n_docs, min(doc_id) AS first_doc FROM documents GROUP BY md5(text) HAVING count(*) > 1",
    "w20_label_scores": """WITH x AS (SELECT source, length(regexp_replace(coalesce(text, ''), '[^#*$%&|<>!]', '', 'g')) * 200 <= length(coalesce(text, '')) AS p, quality = 1 AS t FROM documents JOIN labels USING (doc_id))
      SELECT source, count(*) FILTER (WHERE p AND t) AS tp, count(*) FILTER (WHERE p AND NOT t) AS fp, count(*) FILTER (WHERE NOT p AND t) AS fn FROM x GROUP BY source""",
    "w21_transcripts": "SELECT conv_id, count(*) AS n_turns, string_agg(role || ': ' || text, chr(10) ORDER BY turn, role, text) AS prompt FROM conversations GROUP BY conv_id",
    "w22_stream_windows": "SELECT date_trunc('day', ts) AS window_start, event_type, count(*) AS n_events, round(sum(value), 4) AS value FROM events GROUP BY ALL",
    "w01_cube": f"""WITH {HISTORY} SELECT r_name AS domain, patch_class, count(*) AS n_fixes, sum(added + deleted)::BIGINT AS changed, grouping(r_name, patch_class)::INT AS level
      FROM cases JOIN nation ON n_nationkey = repo_id JOIN region ON r_regionkey = n_regionkey GROUP BY CUBE (r_name, patch_class)""",
    "w04_project_ranks": f"""WITH {HISTORY}, n AS (SELECT repo_id, r_name AS domain, count(*) AS n_cases FROM cases JOIN nation ON n_nationkey = repo_id JOIN region ON r_regionkey = n_regionkey GROUP BY ALL)
      SELECT *, (rank() OVER w)::INT AS place, (dense_rank() OVER w)::INT AS dense_place, (ntile(2) OVER (PARTITION BY domain ORDER BY n_cases DESC, repo_id))::INT AS half,
        round(percent_rank() OVER w, 6) AS percent_place, round(cume_dist() OVER w, 6) AS share_up_to FROM n WINDOW w AS (PARTITION BY domain ORDER BY n_cases DESC)""",
    "w14_long_lived": f"""WITH {TRUTH}, n AS (SELECT vuln_id, repo_id, count(*) AS n_versions FROM truth GROUP BY vuln_id, repo_id)
      SELECT vuln_id, repo_id, n_versions FROM n JOIN (SELECT repo_id, avg(n_versions) AS mean FROM n GROUP BY repo_id) USING (repo_id)
      WHERE n_versions > mean AND vuln_id IN (SELECT vuln_id FROM claims WHERE pattern <> 'exact') AND vuln_id IN (SELECT vuln_id FROM cases WHERE severity >= 4)""",
    "w22_stream_projects": "SELECT c_nationkey::INT AS repo_id, event_type, count(*) AS n_events FROM events LEFT JOIN customer ON c_custkey = user_id GROUP BY ALL",
    "w14_audit_rollup": f"WITH {TRUTH} SELECT r_name AS domain, audit, count(*) AS n_cases, grouping(r_name, audit)::INT AS level FROM named JOIN nation ON n_nationkey = repo_id JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, audit)",
    "w14_audit_pivot": f"WITH {TRUTH} SELECT source_id, " + ", ".join(f"count(*) FILTER (WHERE audit = '{k}') AS {k}" for k in ("correct", "incomplete", "over_inclusive", "mixed", "missing")) + " FROM named GROUP BY source_id",
    "w22_stream_votes": f"WITH {_RUNS} SELECT vuln_id, stmt FROM runs GROUP BY ALL HAVING count(DISTINCT run_no) >= 6",
}

_STATES = f"{TRUTH}, {twin.STATES}, {twin.STATEMENTS}"
#: Origins by method: CTEs that end with ``found`` (vuln_id, repo_id, oseq).
_ORIGINS = {
    "two_level": twin.engine("found"),
    "first_parent": twin.engine("found", merges=False),
    "line_only": twin.engine("found", lost=twin.by_line(900)),
    "unweighted": twin.engine("found", weight="1.0"),
    "blame_basic": twin.blamed("found", "content", "TRUE"),
    "blame_annotated": twin.blamed("found", "pairs", "pred0 IS NULL OR a <> b"),
    "blame_tracked": twin.blamed("found", "pairs", twin.by_line(750)),
    "per_commit": f"""held AS (SELECT s.vuln_id, s.repo_id, t.seq, sum(CASE WHEN {twin.BOTH_LEVELS} THEN CASE WHEN sensitive THEN 2.0 ELSE 1.0 END ELSE 0.0 END) AS gone
        FROM stmts s JOIN pairs t ON t.file_id = s.file_id AND t.slot = s.slot AND t.lane = 'main' AND t.seq < s.fix_seq GROUP BY ALL),
      total AS (SELECT vuln_id, sum(CASE WHEN sensitive THEN 2.0 ELSE 1.0 END) AS total FROM stmts GROUP BY vuln_id),
      found AS (SELECT vuln_id, any_value(repo_id) AS repo_id, coalesce(max(seq) FILTER (WHERE round((1 - gone / total) * 1000) < 700), min(seq)) AS oseq FROM held JOIN total USING (vuln_id) GROUP BY vuln_id)""",
}
_BLAME = ("blame_basic", "blame_annotated", "blame_tracked")


def _method(name: str) -> str:
    return f"WITH {_STATES}, {_ORIGINS[name]}, {twin.affected('hits', 'found')}"


def _macro(by: str, rows: str) -> str:
    """Macro scores by some columns from rows of (by, repo_id, tp, fp, fn)."""
    return f"""per AS (SELECT *, CASE WHEN tp + fp > 0 THEN tp::DOUBLE / (tp + fp) END AS precision, CASE WHEN tp + fn > 0 THEN tp::DOUBLE / (tp + fn) END AS recall FROM ({rows})),
      means AS (SELECT {by}avg(precision) AS p, avg(recall) AS r, count(*) AS n_projects, count(*) FILTER (WHERE precision IS NULL) AS undefined_precision,
        count(*) FILTER (WHERE precision > 0.9) AS high_precision, count(*) FILTER (WHERE recall = 1) AS full_recall FROM per GROUP BY ALL),
      macro AS (SELECT {by}round(p, 6) AS precision, round(r, 6) AS recall, n_projects, undefined_precision, high_precision, full_recall, CASE WHEN p + r > 0 THEN 2 * p * r / (p + r) END AS f1 FROM means)"""


def _met(hits: str, truth: str, key: str = "") -> str:
    """Counts by ``key`` and repository of pairs found and true."""
    using = f"USING ({key}vuln_id, repo_id, tag_no)"
    return f"""SELECT {key}repo_id, count(*) FILTER (WHERE h AND t) AS tp, count(*) FILTER (WHERE h AND t IS NULL) AS fp, count(*) FILTER (WHERE t AND h IS NULL) AS fn
      FROM (SELECT *, TRUE AS h FROM {hits}) FULL JOIN (SELECT *, TRUE AS t FROM {truth}) {using} GROUP BY ALL"""


_TRUE = "(SELECT vuln_id, repo_id, tag_no FROM truth)"
_TRUE_DELETED = "(SELECT vuln_id, repo_id, tag_no FROM truth WHERE vuln_id IN (SELECT vuln_id FROM stmts WHERE flag = 'R'))"
SQL |= {f"method_{n}": f"{_method(n)} SELECT * FROM hits" for n in _ORIGINS}
SQL["method_claims"] = f"WITH {_CLAIMED} SELECT vuln_id, repo_id, tag_no FROM claimed"
SQL["w03_engine"] = f"{_method('two_level')} SELECT f.vuln_id, commit_id AS origin_commit_id, oseq AS origin_seq, round(score, 6) AS score FROM found f JOIN commits c ON c.repo_id = f.repo_id AND c.seq = f.oseq"
SQL["w04_per_project"] = f"{_method('two_level')} SELECT 'two_level' AS method, *, {_RATES} FROM ({_met('hits', _TRUE)})"
SQL["w05_merge_subset"] = f"""WITH {_STATES}, {_ORIGINS['two_level']}, {twin.engine('straight', merges=False)}, hard AS (SELECT DISTINCT vuln_id FROM found_met), {twin.affected('hits', 'found')}, {twin.affected('other', 'straight')},
  counted AS (SELECT 'two_level' AS method, * FROM ({_met('(SELECT * FROM hits WHERE vuln_id IN (FROM hard))', '(SELECT vuln_id, repo_id, tag_no FROM truth WHERE vuln_id IN (FROM hard))')})
    UNION ALL SELECT 'first_parent', * FROM ({_met('(SELECT * FROM other WHERE vuln_id IN (FROM hard))', '(SELECT vuln_id, repo_id, tag_no FROM truth WHERE vuln_id IN (FROM hard))')})),
  {_macro('method, ', 'SELECT * FROM counted')} SELECT * REPLACE (round(f1, 6) AS f1) FROM macro"""
_COUNTED = " UNION ALL ".join(f"SELECT '{n}' AS method, * FROM ({_met(f'hits_{n}', _TRUE_DELETED if n in _BLAME else _TRUE)})" for n in ("two_level", *_BLAME))
_FOUND = ", ".join(f"{_ORIGINS[n].replace('found', f'found_{n}')}, {twin.affected(f'hits_{n}', f'found_{n}')}" for n in ("two_level", *_BLAME))
SQL["w03_gains"] = f"""WITH {_STATES}, claimed AS (SELECT b.vuln_id, b.repo_id, g.tag_no FROM bounds b JOIN tags g ON g.repo_id = b.repo_id AND g.tag_no BETWEEN lo AND hi), {_FOUND},
  counted AS ({_COUNTED} UNION ALL SELECT 'claims', * FROM ({_met('claimed', _TRUE)})), {_macro('method, ', 'SELECT * FROM counted')}
  SELECT method, round(CASE WHEN f1 > 0 THEN ((SELECT f1 FROM macro WHERE method = 'two_level') - f1) / f1 END, 6) AS gain FROM macro WHERE method <> 'two_level'"""
SQL["w10_weight_sweep"] = f"""WITH {_STATES}, params AS (SELECT unnest([1.0, 2.0, 3.0, 4.0, 5.0])::DOUBLE AS ratio), {twin.engine('found', weight='CASE WHEN sensitive THEN ratio ELSE 1.0 END', params='ratio')},
  {twin.affected('hits', 'found', 'o.ratio, ')}, {_macro('ratio, ', _met('hits', '(SELECT ratio, vuln_id, repo_id, tag_no FROM truth CROSS JOIN params)', 'ratio, '))}
  SELECT ratio, precision, recall, round(f1, 6) AS f1 FROM macro"""


def _detector(name: str, similarity: str) -> str:
    return f"""WITH {_STATES}, changes AS (SELECT pre, text AS post, a, b, sim, repo_id, edit_kind <> 2 AS same, count(*) AS n FROM pairs WHERE pred0 IS NOT NULL GROUP BY ALL),
      scored AS (SELECT *, {similarity} AS similarity FROM changes),
      points AS (SELECT repo_id % 2 = 1 AS odd, theta, sum(n) FILTER (WHERE hit AND same) AS tp, sum(n) FILTER (WHERE hit AND NOT same) AS fp, sum(n) FILTER (WHERE NOT hit AND same) AS fn
        FROM (SELECT *, round(similarity, 6) >= theta AS hit FROM scored CROSS JOIN (SELECT unnest([0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9, 1.0])::DOUBLE AS theta)) GROUP BY ALL),
      whole AS (SELECT odd, theta, coalesce(tp, 0)::BIGINT AS tp, coalesce(fp, 0)::BIGINT AS fp, coalesce(fn, 0)::BIGINT AS fn FROM points),
      rated AS (SELECT *, CASE WHEN tp + fp > 0 THEN tp::DOUBLE / (tp + fp) END AS p, CASE WHEN tp + fn > 0 THEN tp::DOUBLE / (tp + fn) END AS r FROM whole),
      full_rates AS (SELECT *, CASE WHEN p + r > 0 THEN 2 * p * r / (p + r) END AS f FROM rated)
      SELECT '{name}' AS detector, o.theta, o.tp, o.fp, o.fn, round(o.p, 6) AS precision, round(o.r, 6) AS recall, round(o.f, 6) AS f1,
        o.theta = (SELECT theta FROM full_rates WHERE NOT odd ORDER BY f DESC NULLS LAST, theta LIMIT 1) AS best FROM full_rates o WHERE odd"""


SQL["w11_statement_edit"] = _detector("edit", "sim")
_PARTS = "list_transform(list_filter(string_split_regex({}, '[;{{}}]'), lambda x: trim(x) <> ''), lambda x: trim(x))"
SQL["w11_statement_md5"] = _detector("md5", f"len(list_distinct(list_intersect({_PARTS.format('a')}, {_PARTS.format('b')})))::DOUBLE / greatest(len(list_distinct(list_concat({_PARTS.format('a')}, {_PARTS.format('b')}))), 1)")
_SNAPS = f"WITH {_STATES}, {twin.SNAPSHOTS}"
_SHARE = "len(list_distinct(list_intersect(held, {0})))::DOUBLE / len(list_distinct({0}))"
SQL["method_patch_presence"] = f"""{_SNAPS} SELECT vuln_id, repo_id, tag_no FROM versions JOIN changed USING (vuln_id)
  WHERE coalesce(CASE WHEN len(deleted) > 0 THEN {_SHARE.format('deleted')} END, 1.0) >= 1.0 AND coalesce(CASE WHEN len(added) > 0 THEN {_SHARE.format('added')} END, 0.0) <= 0.9"""
SQL["method_hybrid"] = f"""{_SNAPS}, claimed AS (SELECT b.vuln_id, b.repo_id, g.tag_no FROM bounds b JOIN tags g ON g.repo_id = b.repo_id AND g.tag_no BETWEEN lo AND hi)
  SELECT v.vuln_id, v.repo_id, v.tag_no FROM versions v JOIN claimed USING (vuln_id, tag_no) JOIN bodies USING (vuln_id)
  WHERE len(list_distinct(list_intersect(held, body))) >= 0.5 * len(list_distinct(list_concat(held, body)))"""
_RUNS_OF = "CASE WHEN len({0}) >= 4 THEN list_transform(range(1, len({0}) - 2), lambda i: array_to_string({0}[i:i + 3], chr(10))) ELSE [array_to_string({0}, chr(10))] END"
SQL["method_window_match"] = f"""{_SNAPS}, cut AS (SELECT vuln_id, repo_id, tag_no, {_RUNS_OF.format('held')} AS h, {_RUNS_OF.format('body')} AS w FROM versions JOIN bodies USING (vuln_id))
  SELECT vuln_id, repo_id, tag_no FROM cut WHERE len(list_distinct(list_intersect(w, h))) >= 0.5 * len(list_distinct(w))"""
_WALKED = f"WITH RECURSIVE {_STATES}, {twin.WALKS}"
SQL["method_all_paths"] = f"{_WALKED}, {twin.scored('found', 'walked')}, {twin.affected('hits', 'found')} SELECT * FROM hits"
SQL["w05_path_check"] = f"""{_WALKED}, {twin.engine('found')}
  SELECT count(*) AS n_statements, count(*) FILTER (WHERE a.stop IS NOT DISTINCT FROM b.stop) AS n_same, count(*) FILTER (WHERE a.stop IS NOT NULL AND vuln_id IN (SELECT vuln_id FROM found_met)) AS n_met_merge
  FROM found_stops a FULL JOIN walked b USING (vuln_id, slot)"""
SQL["w12_walk_counts"] = f"""{_WALKED}, made AS (SELECT vuln_id, count(*) AS n FROM (SELECT DISTINCT vuln_id, slot, commit_id, pred FROM steps WHERE later = 1) GROUP BY vuln_id)
  SELECT count(*) AS n_fixes, sum(coalesce(n, 0))::BIGINT AS n_comparisons, round(avg(coalesce(n, 0)), 6) AS mean_comparisons, count(*) FILTER (WHERE coalesce(n, 0) = 0) AS n_direct FROM (SELECT DISTINCT vuln_id FROM stmts) LEFT JOIN made USING (vuln_id)"""
SQL["w16_closure_check"] = f"""WITH RECURSIVE {TRUTH}, asked AS (SELECT fix_commit_id AS commit_id FROM cases UNION SELECT c.commit_id FROM origins o JOIN commits c ON c.repo_id = o.repo_id AND c.seq = o.oseq),
  held AS (SELECT commit_id AS src, commit_id FROM asked UNION SELECT h.src, e.child_id FROM held h JOIN edges e ON e.parent_id = h.commit_id),
  labelled AS (SELECT a.commit_id AS src, b.commit_id FROM commits a JOIN commits b ON {twin.holds('b', 'a')} WHERE a.commit_id IN (FROM asked))
  SELECT count(*) AS n_pairs, count(*) FILTER (WHERE x IS NULL OR y IS NULL) AS n_differ FROM (SELECT *, 1 AS x FROM held) FULL JOIN (SELECT *, 1 AS y FROM labelled) USING (src, commit_id)"""
SQL["method_touched_only"] = f"""WITH {_STATES}, held AS (SELECT s.vuln_id, s.repo_id, t.seq, sum(CASE WHEN {twin.BOTH_LEVELS} THEN CASE WHEN sensitive THEN 2.0 ELSE 1.0 END ELSE 0.0 END) AS gone,
    sum(CASE WHEN sensitive THEN 2.0 ELSE 1.0 END) AS total FROM stmts s JOIN pairs t ON t.file_id = s.file_id AND t.slot = s.slot AND t.lane = 'main' AND t.seq < s.fix_seq GROUP BY ALL),
  found AS (SELECT vuln_id, any_value(repo_id) AS repo_id, coalesce(max(seq) FILTER (WHERE round((1 - gone / total) * 1000) < 700), min(seq)) AS oseq FROM held GROUP BY vuln_id),
  {twin.affected('hits', 'found')} SELECT * FROM hits"""
SQL["w16_set_difference"] = SQL["w16_affected_versions"]
