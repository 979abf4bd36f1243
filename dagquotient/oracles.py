"""DuckDB SQL that tells the same results from the definitions alone: recursive signatures, no ranks, no sweeps."""

from __future__ import annotations

from dagquotient.sources import fixtures
from dagquotient.sources.tables import TABLES

_NAMES = {t: t for t in TABLES}


def ctes(name: str) -> str:
    """``n`` (node_id, label) and ``e`` (parent, child) of a graph."""
    if name == "pages":
        return page_ctes() + ", n AS (SELECT node_id, label FROM t), e AS (SELECT parent, node_id AS child FROM t WHERE parent IS NOT NULL)"
    nodes, edges = (x.format(**_NAMES) for x in fixtures.GRAPHS[name])
    return f"WITH RECURSIVE n AS ({nodes}), e AS (SELECT DISTINCT parent, child FROM ({edges}))"


def literal_ctes(*parts: tuple[list, list]) -> str:
    nodes = ", ".join(f"({i}, '{label}')" for p in parts for i, label in p[0])
    edges = ", ".join(f"({a}, {b})" for p in parts for a, b in p[1])
    return f"WITH RECURSIVE n(node_id, label) AS (VALUES {nodes}), e(parent, child) AS (VALUES {edges})"


def page_ctes() -> str:
    """``t``: node_id, parent, label, depth of the elements of all pages, by a stack that is carried along the tags."""
    void = ", ".join(f"'{x}'" for x in sorted(fixtures.tree.VOID))
    return f"""WITH RECURSIVE raw AS (
      SELECT page_id AS doc, regexp_extract_all(regexp_replace(regexp_replace(html, '(?s)<!--.*?-->', '', 'g'), '(?is)(<(?:script|style)\\b[^>]*>).*?(</(?:script|style))', '\\1\\2', 'g'), '</?[a-zA-Z][a-zA-Z0-9]*') AS tags FROM pages),
    tok AS (SELECT doc, i, tags[i][2] <> '/' AS is_start, lower(replace(replace(tags[i], '<', ''), '/', '')) AS name FROM (SELECT doc, tags, unnest(range(1, len(tags) + 1)) AS i FROM raw)),
    st(doc, i, labels, ids, seen, node, parent, label, depth) AS (
      SELECT doc, 0::BIGINT, []::VARCHAR[], []::BIGINT[], 0::BIGINT, NULL::BIGINT, NULL::BIGINT, NULL::VARCHAR, NULL::BIGINT FROM raw
      UNION ALL
      SELECT s.doc, k.i,
        CASE WHEN k.is_start THEN CASE WHEN k.name IN ({void}) THEN s.labels ELSE list_append(s.labels, k.name) END
             WHEN list_contains(s.labels, k.name) THEN s.labels[1 : len(s.labels) - list_position(list_reverse(s.labels), k.name)] ELSE s.labels END,
        CASE WHEN k.is_start THEN CASE WHEN k.name IN ({void}) THEN s.ids ELSE list_append(s.ids, s.seen) END
             WHEN list_contains(s.labels, k.name) THEN s.ids[1 : len(s.labels) - list_position(list_reverse(s.labels), k.name)] ELSE s.ids END,
        s.seen + k.is_start::INT, CASE WHEN k.is_start THEN s.seen END, CASE WHEN k.is_start THEN s.ids[len(s.ids)] END, k.name, len(s.labels)
      FROM st s JOIN tok k ON k.doc = s.doc AND k.i = s.i + 1),
    t AS (SELECT doc, doc * {fixtures.tree.STRIDE} + node AS node_id, doc * {fixtures.tree.STRIDE} + parent AS parent, label, depth FROM st WHERE node IS NOT NULL)"""


def signatures(out: str, rounds: int, back: bool = False, start: str = "label", source: str = "n", keep: bool = False) -> str:
    """CTE ``out`` (id, sig): after ``rounds`` rounds, hashes of what every node reaches. ``keep``: with its last one."""
    near, far = ("child", "parent") if back else ("parent", "child")
    own = "p.sig" if keep else "p.l"
    return f"""{out}_all(i, id, l, sig) AS (
      SELECT 0, node_id, {start}, md5({start}) FROM {source}
      UNION ALL
      SELECT p.i + 1, p.id, p.l, md5({own} || ':' || coalesce(string_agg(DISTINCT c.sig, ',' ORDER BY c.sig), ''))
      FROM {out}_all p LEFT JOIN e ON e.{near} = p.id LEFT JOIN {out}_all c ON c.id = e.{far}
      WHERE p.i < {rounds} GROUP BY p.i, p.id, p.l, p.sig),
    {out} AS (SELECT id, sig FROM {out}_all WHERE i = {rounds})"""


def blocks(sig: str = "s", key: str = "sig") -> str:
    return f"SELECT id AS node_id, min(id) OVER (PARTITION BY {key}) AS block_id FROM {sig}"


def forward(head: str, rounds: int) -> str:
    return f"{head}, {signatures('s', rounds)} {blocks()}"


def backward(head: str, rounds: int) -> str:
    return f"{head}, {signatures('s', rounds, back=True)} {blocks()}"


def k_backward(head: str, k: int) -> str:
    return f"{head}, {signatures('s', k, back=True, keep=True)} {blocks()}"


def k_forward(head: str, k: int) -> str:
    return f"{head}, {signatures('s', k, keep=True)} {blocks()}"


def both_ways(head: str, rounds: int, stable: bool) -> str:
    if not stable:
        return f"{head}, {signatures('f', rounds)}, {signatures('b', rounds, back=True)}, s AS (SELECT f.id, f.sig || b.sig AS sig FROM f JOIN b ON f.id = b.id) {blocks()}"
    return f"{head}, {signatures('f', rounds)}, m AS (SELECT id AS node_id, sig AS label FROM f), {signatures('s', rounds, back=True, source='m')} {blocks()}"


def rank(head: str) -> str:
    """Path lengths as a set, the largest of each node."""
    return f"""{head}, w(id, steps) AS (SELECT node_id, 0 FROM n UNION SELECT e.parent, w.steps + 1 FROM w JOIN e ON e.child = w.id)
    SELECT id AS node_id, max(steps)::INT AS rank FROM w GROUP BY id"""


def quotient_edges(partition: str) -> str:
    """Over ``head, ... SELECT node_id, block_id``: the edges between blocks."""
    at = partition.rindex("SELECT id AS node_id")
    return f"{partition[:at]}, q AS ({partition[at:]}) SELECT DISTINCT a.block_id AS parent_block, b.block_id AS child_block FROM e JOIN q a ON a.node_id = e.parent JOIN q b ON b.node_id = e.child"


def quotient_nodes(partition: str) -> str:
    at = partition.rindex("SELECT id AS node_id")
    return f"{partition[:at]}, q AS ({partition[at:]}) SELECT block_id, min(label) AS label, count(*) AS n_members FROM q JOIN n USING (node_id) GROUP BY block_id"


def path(head: str, labels: list[str], anchored: bool = False) -> str:
    """Nodes at the end of a label path, by joins over the graph."""
    joins = " ".join(f"JOIN e e{k} ON e{k}.parent = n{k - 1}.node_id JOIN n n{k} ON n{k}.node_id = e{k}.child AND n{k}.label = '{x}'" for k, x in enumerate(labels) if k)
    root = " AND NOT EXISTS (SELECT 1 FROM e WHERE e.child = n0.node_id)" if anchored else ""
    return f"{head} SELECT DISTINCT n{len(labels) - 1}.node_id FROM n n0 {joins} WHERE n0.label = '{labels[0]}'{root}"


#: Blocks of documents by the sets of their lines, lines by the sets of their words.
DOCUMENT_WORDS = r"""WITH l AS (SELECT DISTINCT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents),
w AS (SELECT line, unnest(string_split_regex(line, '[ \t\r\f\x0b]+')) AS word FROM (SELECT DISTINCT line FROM l)),
s AS (SELECT line, md5(coalesce(string_agg(DISTINCT word, ' ' ORDER BY word) FILTER (word <> ''), '')) AS sig FROM w GROUP BY line),
x AS (SELECT o.doc_id, md5(coalesce(string_agg(DISTINCT s.sig, ',' ORDER BY s.sig), '')) AS sig FROM documents o LEFT JOIN l USING (doc_id) LEFT JOIN s USING (line) GROUP BY o.doc_id)
SELECT doc_id AS node_id, min(doc_id) OVER (PARTITION BY sig) AS block_id FROM x"""
