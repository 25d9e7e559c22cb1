"""DuckDB SQL built from shared parts: characters, extensions, factors, greedy walks."""

from __future__ import annotations

BENCHMARK = "SELECT CAST(item_id AS VARCHAR) AS string_id, text FROM benchmark"
PART_NAMES = "SELECT CAST(p_partkey AS VARCHAR) AS string_id, p_name AS text FROM part"
CUSTOMER_STATUS = "SELECT CAST(o_custkey AS VARCHAR) AS string_id, string_agg(o_orderstatus, '' ORDER BY o_orderdate, o_orderkey) AS text FROM orders GROUP BY 1"
USER_EVENTS = (
    "SELECT CAST(user_id AS VARCHAR) AS string_id, string_agg(CASE event_type WHEN 'signup' THEN 's' WHEN 'view' THEN 'v' WHEN 'error' THEN 'e' "
    "WHEN 'click' THEN 'c' WHEN 'purchase' THEN 'p' ELSE '?' END, '' ORDER BY ts, event_id) AS text FROM events GROUP BY 1"
)
LETTER = (
    "CASE event_type WHEN 'signup' THEN 's' WHEN 'view' THEN 'v' WHEN 'error' THEN 'e' WHEN 'click' THEN 'c' WHEN 'purchase' THEN 'p' ELSE '?' END"
)
DAY_EVENTS = f"SELECT strftime(ts, '%Y-%m-%d') AS string_id, string_agg({LETTER}, '' ORDER BY ts, event_id) AS text FROM events GROUP BY 1"
PART_FLAGS = (
    "SELECT CAST(l_partkey AS VARCHAR) AS string_id, string_agg(CASE WHEN l_linestatus = 'F' THEN upper(translate(substr(l_returnflag, 1, 1), 'ANR', 'anr')) "
    "ELSE translate(substr(l_returnflag, 1, 1), 'ANR', 'anr') END, '' ORDER BY l_orderkey, l_linenumber, l_suppkey, l_quantity, l_extendedprice) AS text FROM lineitem GROUP BY 1"
)


def factors(strings: str, with_both: bool = False) -> str:
    """CTEs: s, ch, ext (i < j, lce), fac (pos, prev_len, next_len) of a strings query."""
    return f"""s AS ({strings}),
ch AS (SELECT string_id, CAST(p AS BIGINT) AS pos, substr(text, CAST(p AS BIGINT), 1) AS c, length(text) AS n
       FROM s, unnest(range(1, length(text) + 1)) AS t(p)),
pair AS (SELECT a.string_id, a.pos AS i, b.pos AS j, b.pos - a.pos AS gap, a.n, a.c = b.c AS same
         FROM ch a JOIN ch b ON a.string_id = b.string_id AND a.pos < b.pos),
ext AS (SELECT string_id, i, j, n,
               coalesce(min(CASE WHEN NOT same THEN i END) OVER (PARTITION BY string_id, gap ORDER BY i DESC ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), n - gap + 1) - i AS lce
        FROM pair),
fac AS (SELECT ch.string_id, ch.pos, ch.n, coalesce(p.m, 0) AS prev_len, coalesce(q.m, 0) AS next_len
        FROM ch LEFT JOIN (SELECT string_id, j AS pos, max(lce) AS m FROM ext GROUP BY ALL) p USING (string_id, pos)
                LEFT JOIN (SELECT string_id, i AS pos, max(lce) AS m FROM ext GROUP BY ALL) q USING (string_id, pos))"""


def suffixes(strings: str) -> str:
    """CTEs of :func:`factors` and suf (rank, pos, lcp)."""
    return f"""{factors(strings)},
ranked AS (SELECT ch.string_id, ch.pos, row_number() OVER (PARTITION BY ch.string_id ORDER BY substr(text, CAST(pos AS BIGINT))) AS rank FROM ch JOIN s USING (string_id)),
suf AS (SELECT a.string_id, a.rank, a.pos, coalesce(e.lce, 0) AS lcp
        FROM ranked a LEFT JOIN ranked b ON a.string_id = b.string_id AND b.rank = a.rank - 1
        LEFT JOIN ext e ON e.string_id = a.string_id AND e.i = least(a.pos, b.pos) AND e.j = greatest(a.pos, b.pos))"""


def walk(ctes: str, jump: str, source: str = "fac") -> str:
    """A recursive walk over jump lengths: w (string_id, pos, size), size 0 for a literal."""
    return f"""WITH RECURSIVE {ctes},
jumps AS (SELECT string_id, pos, {jump} AS size FROM {source}),
w(string_id, pos, size) AS (
  SELECT string_id, pos, size FROM jumps WHERE pos = 1
  UNION ALL
  SELECT w.string_id, j.pos, j.size FROM w JOIN jumps j ON j.string_id = w.string_id AND j.pos = w.pos + greatest(w.size, 1)
)"""


def starts(strings: str, jump: str) -> str:
    """Start and length of each phrase of a greedy walk."""
    ctes, source = (suffixes(strings), "suf") if jump == "lcp" else (factors(strings), "fac")
    return f"{walk(ctes, jump, source)} SELECT string_id, pos AS start, CAST(greatest(size, 1) AS BIGINT) AS length, size = 0 AS is_literal FROM w"


def phrase_counts(strings: str, jump: str) -> str:
    ctes, source = (suffixes(strings), "suf") if jump == "lcp" else (factors(strings), "fac")
    return f"{walk(ctes, jump, source)} SELECT string_id, count(*) AS phrases FROM w GROUP BY 1"


def truths(source: str, key: str, text: str, flags: list[str]) -> str:
    """(string_id, n, flags all true) for every row of a table."""
    return f"SELECT CAST({key} AS VARCHAR) AS string_id, CAST(length({text}) AS BIGINT) AS n, {', '.join(f'true AS {f}' for f in flags)} FROM {source}"


#: Which of the references with one extension and one LCE a tie rule takes, as a number to be maximised.
TIE_SCORES = {"rightmost": "j", "leftmost": "-j", "nearest_right": "CAST(j > i AS INT) - 2 * abs(j - i)", "nearest_left": "CAST(j < i AS INT) - 2 * abs(j - i)"}

#: Whether all positions end in a literal: references ``tried`` are followed as many times as there are characters.
ENDS = "list_sum(list_reduce(list_prepend(tried, list_transform(range(n), lambda z: tried)), lambda a, b: list_transform(a, lambda x: CASE WHEN x = 0 THEN 0 ELSE tried[x] END))) = 0"


def two_way(strings: str, tie: str = "rightmost") -> str:
    """Phrases (string_id, start, length, ref or 0) of the two-way parse of strings of a few dozen characters, by trying all.

    At each step every reference and every length is tried, and a copy counts only if all positions
    end in a literal once the rest is filled up with literals: references are followed as many
    times as the string has characters. Independent of the kernels: no suffix order, no classes.
    """
    return f"""WITH RECURSIVE s AS ({strings}),
w(string_id, text, n, i, refs, size, ref) AS (
  SELECT string_id, text, CAST(length(text) AS INT), 1, list_transform(range(length(text)), lambda x: CAST(0 AS INT)), 0, 0 FROM s WHERE text <> ''
  UNION ALL
  SELECT string_id, text, n, i + greatest(best, 1), list_transform(refs, lambda r, p: CASE WHEN p >= i AND p < i + best THEN j + p - i ELSE r END), best, CASE WHEN best > 0 THEN j ELSE 0 END
  FROM (
    SELECT string_id, any_value(text) AS text, any_value(n) AS n, any_value(i) AS i, any_value(refs) AS refs, max(ext) AS best, arg_max(j, ext * 100000000 + lce * 10000 + {TIE_SCORES[tie]}) AS j
    FROM (
      SELECT string_id, text, n, i, refs, j, max(l) AS lce,
             max(CASE WHEN {ENDS} THEN l ELSE 0 END) AS ext
      FROM (
        SELECT *, list_transform(refs, lambda r, p: CASE WHEN p >= i AND p < i + l THEN j + p - i ELSE r END) AS tried
        FROM (
          SELECT w.string_id, w.text, w.n, w.i, w.refs, CAST(t.j AS INT) AS j, CAST(u.l AS INT) AS l
          FROM w, unnest(range(1, n + 1)) t(j), unnest(range(0, n + 1)) u(l)
          WHERE w.i <= w.n AND (t.j <> w.i OR u.l = 0) AND greatest(t.j, w.i) + u.l <= n + 1 AND substr(text, w.i, u.l) = substr(text, t.j, u.l)
        )
      ) GROUP BY ALL
    ) GROUP BY string_id
  )
)
SELECT string_id, CAST(i - greatest(size, 1) AS BIGINT) AS start, CAST(greatest(size, 1) AS BIGINT) AS length, CAST(ref AS BIGINT) AS ref FROM w WHERE i > 1"""


def profile(strings: str, phrases: str) -> str:
    """Longest valid copy (string_id, j, length) of every place j behind given first phrases, by trying all lengths."""
    return f"""WITH s AS ({strings}), p AS ({phrases}),
refs AS (SELECT string_id, start + k AS pos, ref + k AS target FROM p, unnest(range(length)) t(k) WHERE ref > 0),
w AS (
  SELECT string_id, any_value(text) AS text, any_value(CAST(length(text) AS INT)) AS n, list(CAST(coalesce(target, 0) AS INT) ORDER BY pos) AS refs
  FROM (SELECT string_id, text, p AS pos FROM s, unnest(range(1, length(text) + 1)) t(p)) LEFT JOIN refs USING (string_id, pos) GROUP BY 1
),
ends AS (SELECT string_id, CAST(max(start + length) AS INT) AS i FROM p GROUP BY 1),
tried AS (
  SELECT string_id, n, j, l, list_transform(refs, lambda r, p: CASE WHEN p >= i AND p < i + l THEN j + p - i ELSE r END) AS tried
  FROM (
    SELECT w.string_id, n, coalesce(i, 1) AS i, refs, CAST(t.j AS INT) AS j, CAST(u.l AS INT) AS l
    FROM w LEFT JOIN ends USING (string_id), unnest(range(1, n + 1)) t(j), unnest(range(0, n + 1)) u(l)
    WHERE coalesce(i, 1) <= n AND (t.j <> coalesce(i, 1) OR u.l = 0) AND greatest(t.j, coalesce(i, 1)) + u.l <= n + 1 AND substr(text, coalesce(i, 1), u.l) = substr(text, t.j, u.l)
  )
)
SELECT string_id, CAST(j AS BIGINT) AS j, CAST(max(CASE WHEN {ENDS} THEN l ELSE 0 END) AS BIGINT) AS length FROM tried GROUP BY ALL"""


def reversed_text(strings: str) -> str:
    return f"SELECT string_id, reverse(text) AS text FROM ({strings})"


def table(strings: str) -> str:
    """Best counts of three methods over both directions, and ratios to the left parse, all by brute force."""
    parts = []
    for name, query in (("lz77", lambda s: phrase_counts(s, "prev_len")), ("lex", lambda s: phrase_counts(s, "lcp")), ("two_way", lambda s: f"SELECT string_id, count(*) AS phrases FROM ({two_way(s)}) GROUP BY 1")):
        parts += [f"{name}_f AS ({query(strings)})", f"{name}_r AS ({query(reversed_text(strings))})"]
    best = {m: f"least({m}_f.phrases, {m}_r.phrases)" for m in ("lz77", "lex", "two_way")}
    joins = " ".join(f"JOIN {m}_{d} USING (string_id)" for m in best for d in "fr" if (m, d) != ("lz77", "f"))
    columns = ", ".join(f"{v} AS {m}" for m, v in best.items())
    ratios = ", ".join(f"round({best[m]} / {best['lz77']}, 6) AS {m}_ratio" for m in ("lex", "two_way"))
    return f"WITH {', '.join(parts)}, t AS ({strings}) SELECT string_id, CAST(length(t.text) AS BIGINT) AS n, {columns}, {ratios} FROM lz77_f {joins} JOIN t USING (string_id)"
