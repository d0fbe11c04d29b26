"""Hand-made SQL for the queries, independent of automata: graphs, walks and closures as common table expressions."""

from __future__ import annotations

import re

GRAPHS = {
    "timeline": """g AS (SELECT DISTINCT src, label, dst FROM (
  SELECT lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS src, event_type AS label, event_id AS dst FROM events) WHERE src IS NOT NULL)""",
    "hop": """g AS (SELECT DISTINCT src, label, dst FROM (
  SELECT lag(k) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS src, event_type AS label, k AS dst, value
  FROM (SELECT *, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events)) WHERE src IS NOT NULL AND value >= 95)""",
    "talk": """g AS (SELECT DISTINCT src, label, dst FROM (
  SELECT lag(conv_id * 1000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS src, role AS label, conv_id * 1000 + turn AS dst FROM conversations) WHERE src IS NOT NULL)""",
    "supply": """g AS (
  SELECT DISTINCT 'C' || o_custkey AS src, 'placed' AS label, 'O' || o_orderkey AS dst FROM orders
  UNION SELECT 'O' || l_orderkey, 'contains_' || l_returnflag, 'P' || l_partkey FROM lineitem
  UNION SELECT 'P' || l_partkey, 'supplied_by', 'S' || l_suppkey FROM lineitem
  UNION SELECT 'C' || c_custkey, 'c_in', 'N' || c_nationkey FROM customer
  UNION SELECT 'S' || s_suppkey, 's_in', 'N' || s_nationkey FROM supplier
  UNION SELECT 'N' || n_nationkey, 'part_of', 'R' || n_regionkey FROM nation)""",
    "web": """g AS (
  SELECT DISTINCT 'p' || page_id AS src, 'links' AS label, unnest(regexp_extract_all(html, '<a[^>]*href="([^"]*)"', 1)) AS dst FROM pages
  UNION SELECT 'p' || page_id, 'on_host', 'h:' || regexp_extract(url, '^[a-z]+://([^/:?#]*)', 1) FROM pages)""",
    "docs": """g AS (
  SELECT DISTINCT 'd' || doc_id AS src, 'in_lang' AS label, 'l:' || lang AS dst FROM documents
  UNION SELECT 'd' || doc_id, 'from_source', 's:' || source FROM documents
  UNION SELECT 'd' || doc_id, 'has_text', 't:' || md5(text) FROM documents
  UNION SELECT 'd' || doc_id, 'rated', 'q:' || quality FROM labels WHERE quality IS NOT NULL
  UNION SELECT 'd' || doc_id, 'quotes', 'b' || item_id FROM documents, benchmark WHERE contains(documents.text, benchmark.text))""",
    "near": """g AS (SELECT src, label, dst FROM (
  SELECT a.vec_id AS src, CASE WHEN a.label = b.label THEN 'same' ELSE 'diff' END AS label, b.vec_id AS dst,
    row_number() OVER (PARTITION BY a.vec_id ORDER BY list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) DESC, b.vec_id) AS r
  FROM embeddings a, embeddings b WHERE a.vec_id <> b.vec_id) WHERE r <= 5)""",
}
VERTICES = "n AS (SELECT src AS v FROM g UNION SELECT dst FROM g)"


def labels(*names: str) -> str:
    return "TRUE" if not names else "label IN (" + ", ".join(f"'{n}'" for n in names) + ")"


def edge(*names: str, back: bool = False) -> str:
    """(x, y) of edges with these labels, any label without one."""
    return f"SELECT DISTINCT {'dst' if back else 'src'} AS x, {'src' if back else 'dst'} AS y FROM g WHERE {labels(*names)}"


def closure(name: str, *names: str) -> str:
    """A recursive table of walks of any length over these labels, none included."""
    return f"{name}(x, y) AS (SELECT v, v FROM n UNION SELECT c.x, e.dst FROM {name} c JOIN g e ON c.y = e.src WHERE {labels(*names).replace('label', 'e.label')})"


def then(*tables: str) -> str:
    """(x, y) of walks through tables of pairs, one after the other."""
    joins = f"FROM {tables[0]} t0" + "".join(f" JOIN {t} t{i} ON t{i - 1}.y = t{i}.x" for i, t in enumerate(tables[1:], 1))
    return f"SELECT DISTINCT t0.x, t{len(tables) - 1}.y {joins}"


def query(graph: str, body: str, *tables: tuple[str, str] | str) -> str:
    """A statement over a graph; tables: (name, select) or whole definitions."""
    left = [t if isinstance(t, str) else f"{t[0]} AS ({t[1]})" for t in tables]
    made = [GRAPHS[graph], VERTICES]
    while left:  # a table stands behind those that it reads
        names = {t: re.match(r"\w+", t)[0] for t in left}
        ready = [t for t in left if not any(n != names[t] and re.search(rf"(?:FROM|JOIN|,) {n}\b(?!\.)", t) for n in names.values())]
        made += ready
        left = [t for t in left if t not in ready]
        if not ready:
            raise ValueError(f"tables read each other: {left}")
    return "WITH RECURSIVE " + ",\n".join(made) + "\n" + body


def conjunction(head: list[str], atoms: list[tuple[str, str, str]]) -> str:
    """Distinct head of atoms (table, x variable, y variable) joined on equal variables."""
    seen: dict[str, str] = {}
    froms, wheres = [], []
    for i, (t, x, y) in enumerate(atoms):
        froms.append(f"{t} a{i}")
        for v, column in ((x, f"a{i}.x"), (y, f"a{i}.y")):
            if v in seen:
                wheres.append(f"{seen[v]} = {column}")
            else:
                seen[v] = column
    where = " WHERE " + " AND ".join(wheres) if wheres else ""
    return f"SELECT DISTINCT {', '.join(f'{seen[v]} AS {v}' for v in head)} FROM {', '.join(froms)}{where}"
