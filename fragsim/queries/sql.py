"""Common table expressions of the SQL twins, assembled by need."""

from __future__ import annotations

W = r"[\p{L}\p{N}_]+"

CTES: dict[str, tuple[tuple[str, ...], str]] = {
    "doc": ((), f"SELECT doc_id AS id, coalesce(text, '') AS text, lang, source, regexp_extract_all(lower(coalesce(text, '')), '{W}') AS w FROM documents"),
    "frag": (("doc",), "SELECT *, CAST(len(w) AS BIGINT) AS n FROM doc WHERE len(w) >= 15"),
    "act": (("frag",), "SELECT id, u AS action, CAST(count(*) AS BIGINT) AS f FROM (SELECT id, unnest(w) AS u FROM frag) WHERE length(u) >= 6 GROUP BY ALL"),
    "tot": (("frag", "act"), "SELECT frag.id, n, CAST(coalesce(sum(f), 0) AS BIGINT) AS total FROM frag LEFT JOIN act ON act.id = frag.id GROUP BY ALL"),
    "edge": (("frag",), "SELECT 0 AS i, 15 AS lo UNION ALL SELECT i + 1, lo * 10000 // 3600 + 1 FROM edge WHERE lo <= (SELECT max(n) FROM frag)"),
    "band": (("edge",), "SELECT a.i AS band, a.lo, b.lo - 1 AS hi, (a.lo * 60 + 99) // 100 AS cand_lo, (b.lo - 1) * 100 // 60 AS cand_hi FROM edge a JOIN edge b ON b.i = a.i + 1"),
    "home": (("frag", "band"), "SELECT id, n, band FROM frag JOIN band ON n BETWEEN lo AND hi"),
    "cand": (("frag", "band"), "SELECT id, n, band FROM frag JOIN band ON n BETWEEN cand_lo AND cand_hi"),
    "share": (("act",), "SELECT a.id AS l, b.id AS r, CAST(sum(least(a.f, b.f)) AS BIGINT) AS ov, CAST(count(*) AS BIGINT) AS common, CAST(sum(CASE WHEN a.f = b.f THEN 1 ELSE 0 END) AS BIGINT) AS eq FROM act a JOIN act b ON a.action = b.action AND a.id < b.id GROUP BY ALL"),
    "pair": (("share", "tot"), "SELECT s.*, a.total AS lt, b.total AS rt, a.n AS ln, b.n AS rn FROM share s JOIN tot a ON a.id = s.l JOIN tot b ON b.id = s.r"),
    "meet": (("pair", "home", "cand"), """SELECT * FROM pair p WHERE EXISTS (SELECT 1 FROM home h JOIN cand c ON h.band = c.band WHERE h.id = p.l AND c.id = p.r)
        OR EXISTS (SELECT 1 FROM home h JOIN cand c ON h.band = c.band WHERE h.id = p.r AND c.id = p.l)"""),
}


def with_(select: str, *names: str, **extra: tuple[tuple[str, ...], str]) -> str:
    """A statement with the named expressions and what they need, in order."""
    known, order = CTES | extra, []

    def need(name: str) -> None:
        if name not in order:
            for d in known[name][0]:
                need(d)
            order.append(name)

    for n in names:
        need(n)
    return "WITH RECURSIVE " + ", ".join(f"{n} AS ({known[n][1]})" for n in order) + " " + select
