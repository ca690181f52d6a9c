"""Column types of the history corpus, enforced by name and type wherever it is read or written."""

from __future__ import annotations

COMMIT = "repo_id int, commit_id bigint, committed_at timestamp, seq int, block int, lane string, file_id int, fork int, mseq int"
COMMIT_EDGE = "repo_id int, child_id bigint, parent_id bigint, parent_no int"
VERSION_TAG = "repo_id int, tag string, tag_no int, commit_id bigint, seq int"
FIX_CASE = "vuln_id bigint, repo_id int, fix_commit_id bigint, fix_seq int, file_id int, patch_class string, vuln_type int"
TOUCH = "repo_id int, file_id int, slot int, commit_id bigint, seq int, block int, lane string, fork int, mseq int, op string, edit_kind int"
CLAIM = "vuln_id bigint, source_id bigint, pattern string, lo int, hi int"
JUDGE_RUN = "vuln_id bigint, run_no int, stmt string, tokens int"
FLOW = "func_id string, line_no int, text string, direction string, reason string"

ORDERS = "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string"
EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"
