"""Pieces of the oracle SQL: collections, postings, code lengths, greedy packing."""

from __future__ import annotations

CUT = "flatten(list_transform(regexp_extract_all(lower({t}), '{p}'), lambda w: regexp_extract_all(w, '.{{1,20}}')))"


def _tok(ids: str, text: str, source: str, pattern: str = "[a-z]+") -> str:
    words = CUT.format(t=text, p=pattern)
    return f"(SELECT d, unnest(ts) AS term, generate_subscripts(ts, 1)::BIGINT AS w FROM (SELECT {ids} AS d, {words} AS ts FROM {source}))"


_BASKET = (
    "(SELECT d, term, (row_number() OVER (PARTITION BY d ORDER BY l_linenumber, text, i))::BIGINT AS w FROM (SELECT d, l_linenumber, text, unnest(ts) AS term, generate_subscripts(ts, 1) AS i FROM (SELECT l_orderkey + 1 AS d, l_linenumber, lower(text) AS text, string_split(lower(text), ' ') AS ts FROM "
    "(SELECT l_orderkey, l_linenumber, concat_ws(' ', p_name, p_brand, p_type, l_returnflag, l_linestatus, 'q' || l_quantity::INT::VARCHAR, 's' || p_size::VARCHAR) AS text FROM lineitem JOIN part ON l_partkey = p_partkey))))")
TOK = {
    "docs": _tok("doc_id + 1", "text", "documents"),
    "pages": _tok("page_id + 1", "html", "pages"),
    "turns": _tok("d", "text", "(SELECT row_number() OVER (ORDER BY conv_id, turn) AS d, text FROM conversations)"),
    "baskets": _BASKET,
}
TOK_UNICODE = _tok("doc_id + 1", "text", "documents", "\\p{L}+")
N_DOCS = {"docs": "(SELECT count(*) FROM documents)", "pages": "(SELECT count(*) FROM pages)", "turns": "(SELECT count(*) FROM conversations)"}


def counts(coll: str) -> str:
    return f"(SELECT term, d, count(*) AS f FROM {TOK[coll]} GROUP BY term, d)"


def post(coll: str) -> str:
    return f"(SELECT term, d, f, d - lag(d, 1, 0) OVER (PARTITION BY term ORDER BY d) AS g FROM {counts(coll)})"


def word(coll: str) -> str:
    return (f"(SELECT term, d, w, d - pd + 1 AS g1, CASE WHEN pd = d THEN w - pw ELSE w END AS wg FROM "
            f"(SELECT term, d, w, lag(d, 1, 0) OVER t AS pd, lag(w) OVER t AS pw FROM {TOK[coll]} WINDOW t AS (PARTITION BY term ORDER BY d, w)))")


def vlen(x: str) -> str:
    steps = " ".join(f"WHEN ({x}) < {1 << (7 * k)} THEN {k}" for k in range(1, 9))
    return f"(CASE {steps} ELSE 9 END)"


def plen(a: str, b: str, f: str | int) -> str:
    return f"(CASE WHEN ({b}) < {f} THEN {vlen(f'(({a}) - 1) * {f} + ({b})')} ELSE {vlen(f'({a}) * {f}')} + {vlen(f'({b}) - {f} + 1')} END)"


def packed(coll: str, level: str = "doc", unit: str = "64", f: int | None = None, h: int = 4, head: int = 18, caps: str | None = None, groups: str = "") -> str:
    """CTEs that end in pk(term, rn, blk, nx, first_d, base, d, x, l): greedy packing, one posting of each list a step.

    unit: block size, or a column of `groups` (a CTE of parameter rows) to pack once for each. caps: name of a CTE
    (blk, size) of the sizes, whose first is unit."""
    f = f or (4 if level == "doc" else 3)
    source = post(coll) if level == "doc" else word(coll)
    pick = "term, d, f AS x, g AS gap" if level == "doc" else "term, d, wg AS x, g1 - 1 AS gap"
    order = "d" if level == "doc" else "d, w"
    length = (lambda g: plen(g, "p.x", f)) if level == "doc" else (lambda g: plen("p.x", f"({g}) + 1", f))
    caps_join = f" JOIN {caps} c ON c.blk = k.blk" if caps else ""
    extra, g_join, g_from = ("", "", "") if not groups else (f", {groups}", f", k.{groups}", f", g.{groups} AS {groups}")
    params = "" if not groups else f" CROSS JOIN params g"
    fits0 = f"{head} + strlen(p.term) + {length('p.gap')} <= {unit if not groups else 'g.' + groups}"
    limit = "c.size" if caps else (unit if not groups else "k." + groups)
    fits = f"k.nx + {length('p.gap')} <= {limit}"
    return f"""src AS MATERIALIZED (SELECT {pick}, row_number() OVER (PARTITION BY term ORDER BY {order}) AS rn FROM {source}),
pk AS (
  SELECT p.term, p.rn, CASE WHEN {fits0} THEN 1 ELSE 2 END AS blk, CASE WHEN {fits0} THEN {head} + strlen(p.term) + {length('p.gap')} ELSE {h} + {length('p.d')} END AS nx, p.d AS first_d, 0::BIGINT AS base, p.d, p.x, {length('p.d')} AS l{g_from}
  FROM src p{params} WHERE p.rn = 1
  UNION ALL
  SELECT p.term, p.rn, CASE WHEN {fits} THEN k.blk ELSE k.blk + 1 END, CASE WHEN {fits} THEN k.nx + {length('p.gap')} ELSE {h} + {length('p.d - k.first_d')} END,
    CASE WHEN {fits} THEN k.first_d ELSE p.d END, CASE WHEN {fits} THEN k.base ELSE k.first_d END, p.d, p.x, CASE WHEN {fits} THEN {length('p.gap')} ELSE {length('p.d - k.first_d')} END{g_join}
  FROM pk k JOIN src p ON p.term = k.term AND p.rn = k.rn + 1{caps_join})"""


def blocks(unit: str = "64", head: int = 18, h: int = 4) -> str:
    """CTE blk of pk: one row a block that holds postings (empty heads have none), and lists(term, z)."""
    return f"""blk AS (SELECT term, blk AS block_no, min(d) AS first_d, max(d) AS last_d, count(*) AS n, sum(l)::BIGINT AS used, max(x) AS most FROM pk GROUP BY term, blk),
lists AS (SELECT term, max(block_no) AS z FROM blk GROUP BY term),
tab AS (SELECT l.term, s.block_no, CASE WHEN s.block_no = 1 THEN 'head' WHEN s.block_no = l.z THEN 'tail' ELSE 'full' END AS kind, {unit} - CASE WHEN s.block_no = 1 THEN {head} + strlen(l.term) ELSE {h} END AS cap,
  coalesce(b.first_d, 0) AS first_d, coalesce(b.last_d, 0) AS last_d, coalesce(b.n, 0) AS n, coalesce(b.used, 0) AS used
  FROM lists l JOIN (SELECT term, unnest(range(1, z + 1)) AS block_no FROM lists) s ON s.term = l.term LEFT JOIN blk b ON b.term = s.term AND b.block_no = s.block_no)"""


def folded(coll: str, level: str, unit: int, sizes: list[int] | None = None, head: int = 18, h: int = 4, f: int | None = None) -> str:
    """(term, n, z): postings and blocks of each list by a fold over it, one posting a step. For long lists.

    sizes: those of the first blocks, if they grow. State: z, bytes of the open block with its overhead, its first
    document (0 while it is empty)."""
    f = f or (4 if level == "doc" else 3)
    source = post(coll) if level == "doc" else word(coll)
    pick, order = ("d, f AS x, g AS gap", "d") if level == "doc" else ("d, wg AS x, g1 - 1 AS gap", "d, w")
    length = (lambda g: plen(g, "p.x", f)) if level == "doc" else (lambda g: plen("p.x", f"({g}) + 1", f))
    limit = str(unit) if sizes is None else f"list_extract({sizes}, s.z)"
    fits = f"s.u + {length('p.gap')} <= {limit}"
    step = (f"struct_pack(d := p.d, x := p.x, gap := p.gap, z := CASE WHEN {fits} THEN s.z ELSE s.z + 1 END, u := CASE WHEN {fits} THEN s.u + {length('p.gap')} ELSE {h} + {length('p.d - s.fd')} END, "
            f"fd := CASE WHEN {fits} AND s.fd > 0 THEN s.fd ELSE p.d END)")
    first = f"struct_pack(d := 0::BIGINT, x := 0::BIGINT, gap := 0::BIGINT, z := 1::BIGINT, u := ({head} + strlen(term))::BIGINT, fd := 0::BIGINT)"
    item = "struct_pack(d := d::BIGINT, x := x::BIGINT, gap := gap::BIGINT, z := 0::BIGINT, u := 0::BIGINT, fd := 0::BIGINT)"
    return (f"(SELECT term, n, list_reduce(list_prepend({first}, l), lambda s, p: {step}).z AS z FROM "
            f"(SELECT term, count(*) AS n, list({item} ORDER BY {order}) AS l FROM (SELECT term, {pick}{'' if level == 'doc' else ', w'} FROM {source}) GROUP BY term))")
