"""DuckDB SQL of the methods over any link query (src, dst), by k-cliques, faces and least labels."""

from __future__ import annotations


def _k(k: int, sep: str = ", ", fmt: str = "m{}") -> str:
    return sep.join(fmt.format(i) for i in range(1, k + 1))


def cliques(edges: str, k: int, by: str = "", keep: str = "true") -> str:
    """CTEs e and cl (by, m1..mk, id): k-cliques for which keep holds, numbered in the order of their members."""
    b = f"{by}, " if by else ""
    p = f"p.{by}, " if by else ""
    # One step a member: planners misjudge one join of all pairs at once.
    steps = [f"c2 AS MATERIALIZED (SELECT {b}src AS m1, dst AS m2 FROM e)"]
    for j in range(3, k + 1):
        same = f" AND x.{by} = p.{by}" if by else ""
        # Links to the earlier members are tested, not joined, or planners may join them with each other first.
        linked = "".join(f" AND ({p}p.m{i}, x.dst) IN (SELECT ({b}src, dst) FROM e)" for i in range(1, j - 1))
        steps.append(f"c{j} AS MATERIALIZED (SELECT {p}{_k(j - 1, fmt='p.m{}')}, x.dst AS m{j} FROM c{j - 1} p JOIN e x ON x.src = p.m{j - 1}{same} WHERE true{linked})")
    return f"e AS MATERIALIZED ({edges}), {', '.join(steps)}, cl AS (SELECT *, row_number() OVER (ORDER BY {b}{_k(k)}) AS id FROM c{k} WHERE {keep})"


def cover(edges: str, k: int, by: str = "", keep: str = "true") -> str:
    """CTEs up to lab (by, id, lab, m1..mk) and mem (by, community_key, vid)."""
    b = f"{by}, " if by else ""
    part = f"CAST({by} AS VARCHAR) || '|' || " if by else ""
    faces = " UNION ALL ".join(f"SELECT id, {part}concat_ws('-', {', '.join(f'm{j}' for j in range(1, k + 1) if j != i)}) AS face FROM cl" for i in range(1, k + 1))
    return (
        f"{cliques(edges, k, by, keep)}, f AS ({faces}), s AS (SELECT face, min(id) AS m FROM f GROUP BY face), l0 AS (SELECT DISTINCT f.id AS a, s.m AS b FROM f JOIN s USING (face) WHERE f.id <> s.m), "
        "l AS (SELECT a, b FROM l0 UNION SELECT b, a FROM l0), "
        "cc(id, lab) USING KEY (id) AS (SELECT id, id AS lab FROM cl UNION (SELECT l.b AS id, min(c.lab) AS lab FROM cc c JOIN l ON l.a = c.id JOIN recurring.cc r ON r.id = l.b WHERE c.lab < r.lab GROUP BY l.b)), "
        f"lab AS (SELECT cl.*, cc.lab FROM cl JOIN cc USING (id)), keys AS (SELECT id AS lab, concat_ws('-', {_k(k)}) AS community_key FROM cl), "
        f"mem AS (SELECT DISTINCT {b}community_key, vid FROM (SELECT {b}lab, unnest([{_k(k)}]) AS vid FROM lab) JOIN keys USING (lab))"
    )


def communities(edges: str, k: int, by: str = "", shown_k: int | None = None, keep: str = "true") -> str:
    b = f"{by}, " if by else ""
    return f"WITH RECURSIVE {cover(edges, k, by, keep)} SELECT {b}CAST({shown_k or k} AS BIGINT) AS k, community_key, count(*) AS size FROM mem GROUP BY ALL"


def over(edges: str, k: int, select: str, by: str = "") -> str:
    """A query over e, cl, lab, keys and mem of a cover."""
    return f"WITH RECURSIVE {cover(edges, k, by)} {select}"
