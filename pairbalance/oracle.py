"""SQL that finds the results of the methods from the keys alone: pairs by comparing keys, numbers by counting rows.

It repeats none of the engine's arithmetic, so that agreement means something.
"""

from __future__ import annotations

TITLE = "regexp_extract(html, '<title>([^<]*)</title>', 1)"
DOCUMENTS = """SELECT doc_id AS entity_id, text AS attr, lower(left(trim(text), 3)) AS block_key,
  CASE WHEN CAST(substr(source, 4) AS INT) < 10 THEN 'R' ELSE 'S' END AS source FROM documents"""
PAGES = f"""SELECT page_id AS entity_id, {TITLE} AS attr, lower(left(trim({TITLE}), 3)) AS block_key,
  CASE WHEN starts_with(url, 'https://') THEN 'R' ELSE 'S' END AS source FROM pages"""
CONVERSATIONS = "SELECT conv_id * 1000 + turn AS entity_id, text AS attr, lower(left(trim(text), 3)) AS block_key FROM conversations"
PART = "SELECT p_partkey AS entity_id, p_name AS attr, lower(left(trim(p_name), 3)) AS block_key FROM part"


def strict(entities: str) -> str:
    return f"SELECT entity_id, attr, source, CASE WHEN regexp_full_match(block_key, '[a-z]{{3}}') THEN block_key END AS block_key FROM ({entities})"


STRICT = strict(PAGES)
SORTED = "CAST((row_number() OVER (ORDER BY block_key, entity_id) - 1) * {m} // count(*) OVER () AS INT)"
MOD = "CAST(entity_id % {m} AS INT)"


def base(entities: str = DOCUMENTS, m: int = 8, part: str = MOD) -> str:
    """Common tables e (records), k (keys), cells, profile and total."""
    return f"""e AS (SELECT *, {part.format(m=m)} AS part_ix FROM ({entities})),
k AS (SELECT block_key, row_number() OVER (ORDER BY block_key) - 1 AS block_ix FROM (SELECT DISTINCT block_key FROM e WHERE block_key IS NOT NULL)),
cells AS (SELECT block_key, block_ix, part_ix, count(*) AS n FROM e JOIN k USING (block_key) GROUP BY ALL),
sizes AS (SELECT block_key, block_ix, CAST(sum(n) AS BIGINT) AS n FROM cells GROUP BY ALL),
profile AS (SELECT *, n * (n - 1) // 2 AS pairs, CAST(coalesce(sum(n * (n - 1) // 2) OVER (ORDER BY block_ix ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS first_pair FROM sizes),
total AS (SELECT CAST(sum(pairs) AS BIGINT) AS total FROM profile)"""


def tasks(r: int) -> str:
    """Common table tasks, on top of base()."""
    return f"""heavy AS (SELECT block_ix FROM profile, total WHERE pairs * {r} > total),
hc AS (SELECT block_ix, part_ix, n FROM cells WHERE block_ix IN (FROM heavy)),
tasks AS (
  SELECT block_ix, -1 AS hi, -1 AS lo, pairs FROM profile WHERE pairs > 0 AND block_ix NOT IN (FROM heavy)
  UNION ALL SELECT block_ix, part_ix, part_ix, n * (n - 1) // 2 FROM hc WHERE n > 1
  UNION ALL SELECT a.block_ix, a.part_ix, b.part_ix, a.n * b.n FROM hc a JOIN hc b ON a.block_ix = b.block_ix AND a.part_ix > b.part_ix)"""


def placement(r: int, source: str = "tasks") -> str:
    """Common table placed: the least loaded reduce task, one task after another, by a recursive query over the loads."""
    zeros = ", ".join(["CAST(0 AS BIGINT)"] * r)
    return f"""o AS (SELECT *, row_number() OVER (ORDER BY pairs DESC, block_ix, hi, lo) AS step FROM {source}),
w AS (
  SELECT CAST(0 AS BIGINT) AS step, [{zeros}] AS loads, -1 AS reduce_ix
  UNION ALL
  SELECT o.step, list_transform(range({r}), lambda i: w.loads[i + 1] + CASE WHEN i = list_position(w.loads, list_min(w.loads)) - 1 THEN o.pairs ELSE 0 END),
         CAST(list_position(w.loads, list_min(w.loads)) - 1 AS INT)
  FROM w JOIN o ON o.step = w.step + 1),
placed AS (SELECT block_ix, hi, lo, pairs, w.reduce_ix FROM o JOIN w USING (step))"""


PLACES = """x AS (SELECT e.*, k.block_ix, row_number() OVER (PARTITION BY block_key ORDER BY part_ix, entity_id) - 1 AS place FROM e JOIN k USING (block_key)),
numbered AS (
  SELECT a.entity_id AS i, b.entity_id AS j, a.block_ix, row_number() OVER (ORDER BY a.block_ix, a.place, b.place) - 1 AS p
  FROM x a JOIN x b ON a.block_key = b.block_key AND a.place < b.place)"""


def interval(p: str, r: int, cut: str = "proportional") -> str:
    """The interval of a pair number, given the table total."""
    if cut == "proportional":
        return f"CAST({p} * {r} // (SELECT total FROM total) AS INT)"
    return f"CAST({p} // (((SELECT total FROM total) + {r} - 1) // {r}) AS INT)"


def pairs(entities: str = DOCUMENTS, test: str = "a.block_key = b.block_key AND a.entity_id < b.entity_id", columns: str = "a.entity_id AS left_id, b.entity_id AS right_id") -> str:
    return f"WITH e AS ({entities}) SELECT {columns} FROM e a JOIN e b ON {test}"


MATCH_COLUMNS = """a.entity_id AS left_id, b.entity_id AS right_id, CAST(levenshtein(a.attr, b.attr) AS INT) AS distance,
  CASE WHEN greatest(length(a.attr), length(b.attr)) = 0 THEN 1.0::DOUBLE ELSE 1 - levenshtein(a.attr, b.attr) / greatest(length(a.attr), length(b.attr)) END AS similarity"""
SIMILAR = "5 * levenshtein(a.attr, b.attr) <= greatest(length(a.attr), length(b.attr))"


def one_byte(entities: str) -> str:
    """Common table e: the whole attribute with each letter beyond ASCII as an ASCII one that the table does not use.

    DuckDB counts edits of bytes; with one byte for each letter they are edits of letters.
    """
    return f"""t AS ({entities}), letters AS (SELECT DISTINCT unnest(string_split(attr, '')) AS ch FROM t),
wide AS (SELECT ch, row_number() OVER (ORDER BY ch) AS i FROM letters WHERE unicode(ch) > 127),
free AS (SELECT chr(CAST(x.range AS INT)) AS ch, row_number() OVER (ORDER BY x.range) AS i FROM range(1, 128) x WHERE chr(CAST(x.range AS INT)) NOT IN (SELECT ch FROM letters)),
codes AS (SELECT coalesce(string_agg(wide.ch, '' ORDER BY i), '') AS wide, coalesce(string_agg(free.ch, '' ORDER BY i), '') AS free FROM wide JOIN free USING (i)),
e AS (SELECT t.* REPLACE (translate(attr, wide, free) AS attr) FROM t, codes)"""


def matches(test: str, entities: str = PAGES, similar: str = SIMILAR, columns: str = MATCH_COLUMNS) -> str:
    return f"WITH {one_byte(entities)} SELECT {columns} FROM e a JOIN e b ON {test} AND {similar}"


def loads(cells: str, r: int) -> str:
    """A query of the loads of all r reduce tasks after greedy placement of sub-block tasks, on top of cells given as the
    common tables of base()."""
    return f"""WITH RECURSIVE {cells}, {tasks(r)}, {placement(r)}
SELECT CAST(x.range AS INT) AS reduce_ix, CAST(coalesce(sum(placed.pairs), 0) AS BIGINT) AS pairs FROM range({r}) x LEFT JOIN placed ON placed.reduce_ix = x.range GROUP BY 1"""


def whole_loads(cells: str, r: int) -> str:
    """The same for whole blocks."""
    return f"""WITH {cells}, h AS (SELECT {home('block_key', r)} AS reduce_ix, pairs FROM profile)
SELECT CAST(x.range AS INT) AS reduce_ix, CAST(coalesce(sum(h.pairs), 0) AS BIGINT) AS pairs FROM range({r}) x LEFT JOIN h ON h.reduce_ix = x.range GROUP BY 1"""


def even_loads(cells: str, r: int) -> str:
    """The same for intervals of pair numbers: how many of the numbers fall into each."""
    return f"""WITH {cells}, g AS (SELECT {interval('p.range', r)} AS k, count(*) AS pairs FROM range((SELECT total FROM total)) p GROUP BY 1)
SELECT CAST(x.range AS INT) AS reduce_ix, coalesce(g.pairs, 0) AS pairs FROM range({r}) x LEFT JOIN g ON g.k = x.range"""


def home(key: str, r: int) -> str:
    """The reduce task of a whole block."""
    return f"CAST(('0x' || substr(md5({key}), 1, 8))::BIGINT % {r} AS INT)"


IMBALANCE = "max(pairs) AS largest, max(pairs) * count(*) / sum(pairs) AS over_average"
