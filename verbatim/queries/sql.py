"""Pieces of DuckDB SQL that the oracles share."""

from __future__ import annotations


def h32(seed: str, key: str) -> str:
    return f"('0x' || substr(md5('{seed}:' || {key}), 1, 8))::BIGINT"


def toks(text: str) -> str:
    return f"list_filter(string_split_regex(lower({text}), '\\s+'), lambda x: x <> '')"


#: Documents with tokens, and the seen half of them.
TOK = f"tok AS MATERIALIZED (SELECT doc_id, lang, source, text, {toks('text')} AS tk FROM documents)"
SEEN = TOK + f", seen AS MATERIALIZED (SELECT * FROM tok WHERE {h32('split', 'doc_id')} % 2 = 0)"
#: Counts of the language model over the seen half, best successors and totals.
NG = (
    SEEN
    + """, ng AS MATERIALIZED (SELECT o AS ord, array_to_string(tk[i - o:i - 1], ' ') AS ctx, tk[i] AS tok, count(*)::BIGINT AS cnt
  FROM (SELECT tk, unnest(range(1, len(tk) + 1)) AS i FROM seen), range(4) AS r(o) WHERE o < i GROUP BY ALL),
tot AS MATERIALIZED (SELECT ord, ctx, sum(cnt)::BIGINT AS total, count(*)::BIGINT AS n_next FROM ng GROUP BY ALL)"""
)
BEST = NG + ", best AS MATERIALIZED (SELECT ord, ctx, tok, cnt FROM ng QUALIFY row_number() OVER (PARTITION BY ord, ctx ORDER BY cnt DESC, tok) = 1)"


def heads(name: str, n: int, m: int, src: str = "tok") -> str:
    """Head segments (seg_id, doc_id, prefix, reference)."""
    return f"{name} AS MATERIALIZED (SELECT doc_id || '-0' AS seg_id, doc_id, source, tk[1:{n}] AS prefix, tk[{n + 1}:{n + m}] AS reference FROM {src} WHERE len(tk) >= {n + m})"


def decoded(name: str, src: str, steps: int) -> str:
    """Greedy continuations (seg_id, generated) of src(seg_id, prefix); needs BEST and WITH RECURSIVE."""
    return f"""{name}_r AS (
  SELECT seg_id, 0 AS step, prefix[greatest(len(prefix) - 2, 1):] AS tail, []::VARCHAR[] AS generated FROM {src}
  UNION ALL
  SELECT seg_id, step + 1, list_append(tail, nx)[greatest(len(tail) - 1, 1):], list_append(generated, nx) FROM (
    SELECT d.*, coalesce(b3.tok, b2.tok, b1.tok, b0.tok) AS nx FROM {name}_r d
    LEFT JOIN best b3 ON len(d.tail) >= 3 AND b3.ord = 3 AND b3.ctx = array_to_string(d.tail[-3:], ' ')
    LEFT JOIN best b2 ON len(d.tail) >= 2 AND b2.ord = 2 AND b2.ctx = array_to_string(d.tail[-2:], ' ')
    LEFT JOIN best b1 ON len(d.tail) >= 1 AND b1.ord = 1 AND b1.ctx = d.tail[-1]
    LEFT JOIN best b0 ON b0.ord = 0) WHERE step < {steps}),
{name} AS MATERIALIZED (SELECT seg_id, generated FROM {name}_r WHERE step = {steps})"""


def lcs(name: str, src: str) -> str:
    """LCS lengths (id, lcs) of src(id, a, b); needs WITH RECURSIVE."""
    return f"""{name}_s AS MATERIALIZED (SELECT id, a, b FROM {src}),
{name}_r AS (
  SELECT id, 0 AS i, list_transform(range(len(b)), lambda q: 0::BIGINT) AS rw FROM {name}_s
  UNION ALL
  SELECT id, i + 1, list_transform(range(1, len(c) + 1), lambda j: list_max(c[1:j])) FROM (
    SELECT r.id, r.i, list_transform(range(1, len(s.b) + 1), lambda j: greatest(r.rw[j], CASE WHEN s.b[j] = s.a[r.i + 1] THEN coalesce(CASE WHEN j > 1 THEN r.rw[j - 1] END, 0) + 1 ELSE 0 END)) AS c
    FROM {name}_r r JOIN {name}_s s ON r.id = s.id WHERE r.i < len(s.a))),
{name} AS MATERIALIZED (SELECT r.id, coalesce(list_max(r.rw), 0)::INT AS lcs FROM {name}_r r JOIN {name}_s s ON r.id = s.id WHERE r.i = len(s.a))"""


def nll(name: str, src: str, mix=(0.1, 0.2, 0.3, 0.4)) -> str:
    """(id, n_tokens, nll) of src(id, given, txt); needs NG."""
    w = ", ".join(map(str, mix))
    return f"""{name}_p AS MATERIALIZED (SELECT id, i - len(given) AS pos, o AS ord, array_to_string(al[i - o:i - 1], ' ') AS ctx, al[i] AS tok
  FROM (SELECT id, given, list_concat(given, txt) AS al, unnest(range(len(given) + 1, len(given) + len(txt) + 1)) AS i FROM {src}), range({len(mix)}) AS r(o) WHERE o < i),
{name}_m AS (SELECT p.id, p.pos, sum([{w}][p.ord + 1]::DOUBLE * coalesce(n.cnt / t.total, 0)) AS pr FROM {name}_p p
  LEFT JOIN ng n ON n.ord = p.ord AND n.ctx = p.ctx AND n.tok = p.tok LEFT JOIN tot t ON t.ord = p.ord AND t.ctx = p.ctx GROUP BY ALL),
{name} AS MATERIALIZED (SELECT id, count(*) AS n_tokens, sum(-ln(greatest(pr, 1e-6))) AS nll FROM {name}_m GROUP BY id)"""


#: Recorded outputs (output_id, task, text, tk): assistant turns, their conversation dealt over three tasks.
TURNS = f"turns AS MATERIALIZED (SELECT conv_id || '-' || turn AS output_id, ['story', 'poem', 'speech'][({h32('task', 'conv_id')} % 3 + 1)::BIGINT] AS task, text, {toks('text')} AS tk FROM conversations WHERE role = 'assistant')"
#: Those, and what the model itself writes after the heads of all documents; needs BEST and WITH RECURSIVE.
OUT = TURNS + f", {heads('oseg', 64, 32)}, {decoded('odec', 'oseg', 32)}, outs AS MATERIALIZED (SELECT output_id, task, tk FROM turns UNION ALL SELECT seg_id, ['story', 'poem', 'speech'][({h32('task', 'doc_id')} % 3 + 1)::BIGINT], generated FROM odec JOIN oseg USING (seg_id))"


def gram(tk: str, n: int) -> str:
    return f"list_transform(range(1, greatest(len({tk}) - {n - 1}, 0) + 1), lambda i: array_to_string({tk}[i:i + {n - 1}], ' '))"


def hits(name: str, outs: str, corpus: str, n: int) -> str:
    """(output_id, task, pos, hit) of each n-gram position."""
    return f"""{name}_c AS MATERIALIZED (SELECT DISTINCT unnest({gram('tk', n)}) AS g FROM {corpus}),
{name}_o AS (SELECT output_id, task, unnest({gram('tk', n)}) AS g, unnest(range(greatest(len(tk) - {n - 1}, 0))) AS pos FROM {outs}),
{name} AS MATERIALIZED (SELECT output_id, task, pos, c.g IS NOT NULL AS hit FROM {name}_o o LEFT JOIN {name}_c c ON c.g = o.g)"""
