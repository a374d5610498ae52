"""SQL twins of the catalogue for DuckDB: written from the definitions (joins with all features, recursion over whole
images), not from the plans of the operators."""

from __future__ import annotations

from .functions.lut import dual, numbers, simple

RE = """re AS MATERIALIZED (SELECT (vec_id // 64)::BIGINT AS image_id, (vec_id % 64)::INT AS row, (i - 1)::INT AS col, embedding[i] > 0 AS obj,
  least(greatest(floor((embedding[i]::DOUBLE + 1) * 127.5), 0), 255)::INT AS level FROM embeddings, (SELECT unnest(range(1, 65)) AS i))"""
RO = """ro AS MATERIALIZED (SELECT 0::BIGINT AS image_id, floor(round(o_totalprice * 100)::BIGINT * 200 / 50000000)::INT AS row,
  floor(date_diff('day', DATE '1995-01-01', o_orderdate::DATE) * 200 / 2405)::INT AS col, count(*) AS n FROM orders GROUP BY ALL)"""
RV = """rv AS MATERIALIZED (SELECT 0::BIGINT AS image_id, (user_id % 168)::INT AS row, ((hour(ts) * 60 + minute(ts)) // 5)::INT AS col, count(*) AS n FROM events GROUP BY ALL)"""
RL = """rl AS MATERIALIZED (SELECT 0::BIGINT AS image_id, floor(round(l_extendedprice * 100)::BIGINT * 512 / 10500000)::INT AS row,
  floor(date_diff('day', DATE '1995-01-02', l_shipdate::DATE) * 512 / 2499)::INT AS col, count(*) AS n FROM lineitem GROUP BY ALL)"""
NEAR = """near AS (SELECT * FROM (VALUES (0, -1, 0), (1, -1, 1), (2, 0, 1), (3, 1, 1), (4, 1, 0), (5, 1, -1), (6, 0, -1), (7, -1, -1)) AS v(k, dr, dc))"""


def padded(margin: int, name: str = "rp") -> str:
    """RE with a margin of background."""
    return f"""{name} AS MATERIALIZED (SELECT f.image_id, r::INT AS row, c::INT AS col, coalesce(obj, false) AS obj
  FROM (SELECT image_id, max(row) AS h FROM re GROUP BY 1) f, (SELECT unnest(range(-{margin}, {64 + margin})) AS c) x, (SELECT unnest(range(-{margin}, {64 + margin})) AS r) y
  LEFT JOIN re ON re.image_id = f.image_id AND re.row = r AND re.col = c WHERE r <= h + {margin})"""


def mask(source: str, name: str = "mask") -> str:
    return f"""{name} AS MATERIALIZED (SELECT p.image_id, p.row, p.col, bool_or(p.obj) AS obj, coalesce(sum(CASE WHEN q.obj THEN 1 << k END), 0)::INT AS mask
  FROM {source} p CROSS JOIN near LEFT JOIN {source} q ON q.image_id = p.image_id AND q.row = p.row + dr AND q.col = p.col + dc GROUP BY 1, 2, 3)"""


def table_of(conn: str, name: str = "lut") -> str:
    t, b = numbers(conn)
    return f"{name} AS MATERIALIZED (SELECT unnest(range(256))::INT AS mask, unnest({t}) AS t, unnest({b}) AS tb)"


def nearest(source: str, want: str, name: str) -> str:
    """The definition of the distance transform: the least squared distance to any feature of the image."""
    return f"""{name} AS MATERIALIZED (SELECT p.image_id, p.row, p.col, min((p.row - q.row) * (p.row - q.row) + (p.col - q.col) * (p.col - q.col))::BIGINT AS d2
  FROM {source} p LEFT JOIN {source} q ON q.image_id = p.image_id AND {want.replace('$', 'q.obj')} GROUP BY 1, 2, 3)"""


def within(source: str, want: str, r: int, name: str) -> str:
    """Cells with a feature within distance r, and how far it is."""
    return f"""{name} AS MATERIALIZED (SELECT p.image_id, p.row, p.col, min(CASE WHEN {want.replace('$', 'q.obj')} THEN dr * dr + dc * dc END)::BIGINT AS d2
  FROM {source} p CROSS JOIN (SELECT * FROM (SELECT unnest(range(-{r}, {r + 1}))::INT AS dr), (SELECT unnest(range(-{r}, {r + 1}))::INT AS dc) WHERE dr * dr + dc * dc <= {r * r}) b
  LEFT JOIN {source} q ON q.image_id = p.image_id AND q.row = p.row + dr AND q.col = p.col + dc GROUP BY 1, 2, 3)"""


def eroded(source: str, r: int, name: str) -> str:
    return within(source, "NOT $", r, f"{name}_d") + f", {name} AS MATERIALIZED (SELECT image_id, row, col, d2 IS NULL AS obj FROM {name}_d)"


def dilated(source: str, r: int, name: str) -> str:
    return within(source, "$", r, f"{name}_d") + f", {name} AS MATERIALIZED (SELECT image_id, row, col, d2 IS NOT NULL AS obj FROM {name}_d)"


def with_(*parts: str) -> str:
    return "WITH " + ",\n".join(parts) + "\n"


# ---- whole images as lists, for the order-dependent operators ----

SIDE, PAD = 68, 2
CELLS = SIDE * SIDE


def lists(source: str = "re", name: str = "im") -> str:
    """One row an image: b, the cells of the frame of SIDE x SIDE row by row."""
    return f"""{name} AS MATERIALIZED (SELECT g.image_id, list(coalesce(s.obj, false) ORDER BY x.i) AS b
  FROM (SELECT DISTINCT image_id FROM re) g CROSS JOIN (SELECT unnest(range({CELLS}))::INT AS i) x
  LEFT JOIN {source} s ON s.image_id = g.image_id AND s.row = x.i // {SIDE} - {PAD} AND s.col = x.i % {SIDE} - {PAD} GROUP BY 1)"""


def constants(conn: str) -> str:
    """con: p, the parity subfield of each cell; f, whether a cell is inside the frame's ring; the tables of both pairs."""
    lut = lambda c: "[" + ",".join("true" if v else "false" for v in simple(c)) + "]"
    return f"""con AS MATERIALIZED (SELECT list((((i // {SIDE}) - {PAD}) & 1) * 2 + (((i % {SIDE}) - {PAD}) & 1) ORDER BY i) AS p,
  list(i // {SIDE} BETWEEN 1 AND {SIDE - 2} AND i % {SIDE} BETWEEN 1 AND {SIDE - 2} ORDER BY i) AS f, {lut(conn)} AS own, {lut(dual(conn))} AS other
  FROM (SELECT unnest(range({CELLS}))::INT AS i))"""


def _ball(r: int) -> str:
    return "[" + ",".join(f"{{'o': {dr * SIDE + dc}, 'd': {dr * dr + dc * dc}}}" for dr in range(-r, r + 1) for dc in range(-r, r + 1) if dr * dr + dc * dc <= r * r) + "]"


def reach(bits: str, want: str, r: int) -> str:
    """A list: the squared distance to the nearest wanted cell within r, else null."""
    return f"list_transform(range(1, {CELLS + 1}), lambda i: list_min(list_transform({_ball(r)}, lambda o: CASE WHEN i + o.o > 0 AND {want.replace('$', f'{bits}[i + o.o]')} THEN o.d END)))"


def _mask(b: str = "b") -> str:
    shifts = (-SIDE, -SIDE + 1, 1, SIDE + 1, SIDE, SIDE - 1, -1, -SIDE - 1)
    return " + ".join(f"CASE WHEN {b}[i + ({s})] THEN {1 << k} ELSE 0 END" for k, s in enumerate(shifts))


def thinning(name: str, source: str, bits: str, priority: str, keep: str, table: str, most: int | None = None, joins: str = "") -> str:
    """Canonical thinning of ``bits`` of the rows of ``source``: name(image_id, b). ``priority`` and ``keep`` are list expressions."""
    stop = f" AND step < {4 * most}" if most is not None else ""
    return f"""{name}_p AS MATERIALIZED (SELECT s.image_id, {bits} AS b, {priority} AS d, {keep} AS k, {table} AS l, p, f FROM {source} s {joins}, con),
{name} AS MATERIALIZED (WITH RECURSIVE t AS (
  SELECT image_id, b, d, list_transform(range(1, {CELLS + 1}), lambda i: f[i] AND NOT k[i]) AS free, l, p, 0 AS step, NULL::INT AS lev FROM {name}_p
  UNION ALL
  SELECT image_id, list_transform(range(1, {CELLS + 1}), lambda i: b[i] AND NOT (free[i] AND d[i] = now AND p[i] = step % 4 AND CASE WHEN free[i] AND d[i] = now AND p[i] = step % 4 THEN l[{_mask()} + 1] ELSE false END)),
    d, free, l, p, step + 1, now
  FROM (SELECT *, CASE WHEN step % 4 = 0 THEN list_min(list_transform(range(1, {CELLS + 1}), lambda i: CASE WHEN b[i] AND free[i] THEN CASE WHEN l[{_mask()} + 1] THEN d[i] END END)) ELSE lev END AS now FROM t) u
  WHERE now IS NOT NULL{stop})
SELECT image_id, arg_max(b, step) AS b FROM t GROUP BY 1)"""


def _map(expression: str) -> str:
    return f"list_transform(range(1, {CELLS + 1}), lambda i: {expression})"


def cutting(name: str, source: str, r: int, c: str | None = None) -> str:
    """Homotopic cutting of source(image_id, b): erosion and C are kept, then the dilation of the rest grows back inside."""
    keep = "list_transform(range(1, {n}), lambda i: s.d[i] IS NULL{c})".format(n=CELLS + 1, c=f" OR {c}.b[i]" if c else "")
    joins = f"JOIN {c} ON {c}.image_id = s.image_id" if c else ""
    return ",\n".join((
        f"{name}_d AS MATERIALIZED (SELECT image_id, b, {reach('b', 'NOT $', r)} AS d FROM {source})",
        thinning(f"{name}_y", f"{name}_d", "s.b", "s.d", keep, "own", joins=joins),
        f"{name}_e AS MATERIALIZED (SELECT y.image_id, x.b AS x, y.b AS y, {reach('y.b', '$', r)} AS d FROM {name}_y y JOIN {source} x USING (image_id))",
        thinning(f"{name}_z", f"{name}_e", _map("NOT s.y[i]"), "s.d", _map("NOT (s.d[i] IS NOT NULL AND s.x[i] AND NOT s.y[i])"), "other"),
        f"{name} AS MATERIALIZED (SELECT image_id, {_map('NOT b[i]')} AS b FROM {name}_z)",
    ))


def filling(name: str, source: str, r: int, d: str | None = None) -> str:
    joins = f"JOIN {d} ON {d}.image_id = s.image_id" if d else ""
    return ",\n".join((
        f"{name}_d AS MATERIALIZED (SELECT image_id, b, {reach('b', '$', r)} AS d FROM {source})",
        thinning(f"{name}_w", f"{name}_d", _map("NOT s.b[i]"), "s.d", _map(f"NOT (s.d[i] IS NOT NULL AND NOT s.b[i]{f' AND NOT {d}.b[i]' if d else ''})"), "other", joins=joins),
        f"{name}_z AS MATERIALIZED (SELECT image_id, {_map('NOT b[i]')} AS b FROM {name}_w)",
        f"{name}_e AS MATERIALIZED (SELECT z.image_id, x.b AS x, z.b AS b, {reach('z.b', 'NOT $', r)} AS d FROM {name}_z z JOIN {source} x USING (image_id))",
        thinning(name, f"{name}_e", "s.b", "s.d", _map("s.d[i] IS NULL OR s.x[i]"), "own"),
    ))


def filtered(n: int, c: str | None = None, d: str | None = None, source: str = "im") -> tuple[str, str]:
    """The CTEs of the smoothing filter of radius n, and the name of the last."""
    parts = []
    for r in range(1, n + 1):
        parts += [cutting(f"c{r}", source, r, c), filling(f"f{r}", f"c{r}", r, d)]
        source = f"f{r}"
    return ",\n".join(parts), source


def cells_of(name: str) -> str:
    """SELECT of the object cells of name(image_id, b)."""
    return f"""SELECT image_id, ((i - 1) // {SIDE} - {PAD})::INT AS row, ((i - 1) % {SIDE} - {PAD})::INT AS col FROM {name}, (SELECT unnest(range(1, {CELLS + 1})) AS i) x WHERE b[i]"""


def labelled(name: str, source: str, n: int) -> str:
    """Component labels (least index) of source(image_id, b) by repeated minima: name(image_id, m list)."""
    shifts = (-SIDE, 1, SIDE, -1) if n == 4 else (-SIDE, -SIDE + 1, 1, SIDE + 1, SIDE, SIDE - 1, -1, -SIDE - 1)
    low = ", ".join(f"m[i + ({s})]" for s in shifts)
    edge = f"(i - 1) % {SIDE} BETWEEN 1 AND {SIDE - 2} AND i > {SIDE} AND i <= {CELLS - SIDE}"
    border = f"list_min(list_transform([{', '.join(f'{{{chr(39)}s{chr(39)}: {s}, {chr(39)}c{chr(39)}: {((s + SIDE + 1) % SIDE) - 1 if abs(s) > 1 else s}}}' for s in shifts)}], lambda o: CASE WHEN i + o.s BETWEEN 1 AND {CELLS} AND (i - 1) % {SIDE} + o.c BETWEEN 0 AND {SIDE - 1} THEN m[i + o.s] END))"
    return f"""{name} AS MATERIALIZED (WITH RECURSIVE t AS (
  SELECT image_id, {_map('CASE WHEN b[i] THEN i END')} AS m, 0 AS step, true AS more FROM {source}
  UNION ALL
  SELECT image_id, w, step + 1, w IS DISTINCT FROM m FROM (SELECT image_id, m, step, {_map(f"CASE WHEN m[i] IS NOT NULL THEN least(m[i], CASE WHEN {edge} THEN least({low}) ELSE {border} END) END")} AS w FROM t WHERE more) u)
SELECT image_id, arg_max(m, step) AS m FROM t GROUP BY 1)"""


def signed(source: str, conn: str, name: str = "sig") -> str:
    """name(image_id, n_object, n_background) of source(image_id, b)."""
    n, m = (8, 4) if conn == "8/4" else (4, 8)
    count = "len(list_distinct(list_filter(m, lambda v: v IS NOT NULL)))::BIGINT"
    return ",\n".join((
        labelled(f"{name}_o", source, n),
        f"{name}_n AS MATERIALIZED (SELECT image_id, {_map('NOT b[i]')} AS b FROM {source})",
        labelled(f"{name}_b", f"{name}_n", m),
        f"{name} AS MATERIALIZED (SELECT image_id, {count.replace('(m,', '(o.m,')} AS n_object, {count.replace('(m,', '(g.m,')} AS n_background FROM {name}_o o JOIN {name}_b g USING (image_id))",
    ))
