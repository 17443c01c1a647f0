"""DuckDB text for the exact bits of every codec.

``FORMS[name]`` is a FROM item (term, block, bits) over the CTEs that ``measured``
names: ``rows`` (one value a row), ``quad`` (four values a row) and ``blk`` (a block's
values as a list).
"""

from __future__ import annotations

from quadpost.codecs import words
from quadpost.codecs.frames import ZETA
from quadpost.codecs.quad_selector import SELECTORS
from quadpost.operators.corpus import BLOCK
from quadpost.plans import sql

BLK = f"blk AS (SELECT term, pos // {BLOCK} AS block, count(*) AS n, list({{values}} ORDER BY pos) AS v FROM {{source}} GROUP BY ALL)"
_WIDTHS = "(SELECT unnest(range(1, 33)) AS b)"
_KEY = "term, block, frame"


def _walk(patterns, need: str, word: int) -> str:
    return f"(WITH RECURSIVE {sql.walk(patterns, need)} SELECT term, block, {word} * count(*) AS bits FROM steps GROUP BY ALL)"


def _mixed_walk() -> str:
    """A greedy walk whose patterns have a width for each place."""
    rows = ", ".join(f"({s}, {len(w)}, {w})" for s, w in enumerate([b for n, b in runs for _ in range(n)] for runs in words.SIXTEEN))
    fits = lambda at: f"(SELECT min(sel) FROM pat WHERE list_max(list_transform(list_zip(c[{at} + 1:{at} + num], w[1:len(c) - {at}]), lambda z: z[1] - z[2])) <= 0)"
    return f"""(WITH RECURSIVE pat(sel, num, w) AS (VALUES {rows}), cells AS (SELECT term, block, {sql.VALUE_NEED} AS c FROM blk),
      steps(term, block, c, ofs, sel) AS (
        SELECT term, block, c, 0, {fits(0)} FROM cells WHERE len(c) > 0
        UNION ALL
        SELECT term, block, c, ofs, {fits("ofs")} FROM (SELECT term, block, c, ofs + p.num AS ofs FROM steps JOIN pat p USING (sel)) WHERE ofs < len(c))
      SELECT term, block, 32 * count(*) AS bits FROM steps GROUP BY ALL)"""


def _cells(laned: bool, frame: int) -> str:
    """What a width is chosen from: values, or quads by their maxima."""
    what, each = ("quad", f"q // {frame // 4}") if laned else ("rows", f"i // {frame}")
    return f"cell AS (SELECT {_KEY}, w, count(*) AS c FROM (SELECT term, block, {each} AS frame, {sql.bits_of('m' if laned else 'x')} AS w FROM {what}) GROUP BY ALL)"


def _data(laned: bool) -> str:
    return "128 * ceil(sum(c * b) / 32)" if laned else "sum(c * b)"


def threshold_form(laned: bool, frame: int = 128, zeta: float = ZETA) -> str:
    """Patched frames with a share of exceptions below ``zeta``: heads, slots, and exceptions with those that the chain forces."""
    head = 24 if frame <= 256 else 40
    return f"""(WITH {_cells(laned, frame)},
      cand AS (SELECT {_KEY}, b, coalesce(sum(c) FILTER (WHERE w > b), 0) AS over, sum(c) AS c FROM cell, {_WIDTHS} GROUP BY ALL),
      fw AS (SELECT {_KEY}, min(b) AS b, max(c) AS c FROM cand WHERE over < cast({zeta} AS DOUBLE) * c GROUP BY ALL),
      far AS (SELECT {_KEY}, {sql.bits_of('x')} AS w, b, i - lag(i) OVER (PARTITION BY {_KEY} ORDER BY i) AS step FROM (SELECT *, i // {frame} AS frame FROM rows) JOIN fw USING ({_KEY}) WHERE {sql.bits_of('x')} > b),
      exc AS (SELECT {_KEY}, (count(*) + coalesce(sum((step - 1) // (1 << least(b, 16))), 0)) * CASE WHEN max(w) <= 8 THEN 8 WHEN max(w) <= 16 THEN 16 ELSE 32 END AS e FROM far GROUP BY ALL)
      SELECT term, block, {head} * count(*) + {_data(laned)} + sum(coalesce(e, 0)) AS bits FROM fw LEFT JOIN exc USING ({_KEY}) GROUP BY ALL)"""


def cost_form(laned: bool, frame: int = 512) -> str:
    """Patched frames of the cheapest width, high parts apart."""
    place, units = 8 if frame <= 256 else 16, frame // 4 if laned else frame
    return f"""(WITH {_cells(laned, frame)},
      cand AS (SELECT {_KEY}, b, coalesce(sum(c) FILTER (WHERE w > b), 0) AS over, sum(c) AS c, max(w) AS top FROM cell, {_WIDTHS} GROUP BY ALL),
      fw AS (SELECT {_KEY}, min({{'cost': c * b + over * (greatest(top - b, 0) + {8 if units <= 256 else 16}), 'b': b}}).b AS b, max(c) AS c, max(top) AS top FROM cand GROUP BY ALL),
      exc AS (SELECT {_KEY}, count(*) AS e FROM (SELECT *, i // {frame} AS frame FROM rows) JOIN fw USING ({_KEY}) WHERE {sql.bits_of('x')} > b GROUP BY ALL)
      SELECT term, block, sum(32 + coalesce(e, 0) * ({place} + top - b)) + {_data(laned)} AS bits FROM fw LEFT JOIN exc USING ({_KEY}) GROUP BY ALL)"""


def _plain_plan(sizes: tuple[int, ...]) -> str:
    return f"(WITH RECURSIVE {sql.frames(sql.VALUE_NEED, sizes[0], sizes, 1)} SELECT term, block, best[1] AS bits FROM plan WHERE done = len(c))"


def lane_plan_form(sizes: tuple[int, ...]) -> str:
    """The least cost of frames over quads, with how many frames there are: lanes fill up to whole vectors only at the end."""
    cell = sizes[0] // 4
    options = ", ".join(
        f"CASE WHEN done + 1 >= {s // sizes[0]} THEN {{'cost': cast(8 + {s} * list_max(c[len(c) - done:len(c) - done + {s // sizes[0] - 1}]) + best[{s // sizes[0]}].cost AS BIGINT), 'shorter': {-s}, 'frames': best[{s // sizes[0]}].frames + 1}} END"
        for s in sizes
    )
    return f"""(WITH RECURSIVE needs AS (SELECT term, block, {sql.QUAD_NEED} AS u FROM blk),
      cells AS (SELECT term, block, list_transform(range(0, cast(ceil(len(u) / {cell}) AS BIGINT)), lambda k: list_max(u[k * {cell} + 1:k * {cell} + {cell}])) AS c FROM needs),
      plan(term, block, c, done, best) AS (
        SELECT term, block, c, 0, [{{'cost': 0::BIGINT, 'shorter': 0, 'frames': 0}}] FROM cells
        UNION ALL
        SELECT term, block, c, done + 1, list_prepend(list_min([x FOR x IN [{options}] IF x IS NOT NULL]), best) FROM plan WHERE done < len(c))
      SELECT term, block, 8 * best[1].frames + 128 * ceil((best[1].cost - 8 * best[1].frames) / 128) AS bits FROM plan WHERE done = len(c))"""


def lane_frame_form(frame: int) -> str:
    return f"(SELECT term, block, 128 * ceil(sum(ceil(c / 4) * w) / 32) + 8 * count(*) AS bits FROM (SELECT term, block, i // {frame} AS f, count(*) AS c, {sql.bits_of('max(x)')} AS w FROM rows GROUP BY ALL) GROUP BY ALL)"


def _filled(need: str, cg: int, bits: str) -> str:
    unit = f"list_transform({need}, lambda b: cast(ceil(b / {cg}) AS BIGINT))"
    return f"(WITH RECURSIVE {sql.fill(unit, 8)} SELECT term, block, {bits} AS bits FROM fills GROUP BY ALL)"


FORMS = {n: sql.sizes_of(n) for n in sql.CLOSED} | {
    "rice_best": f"(SELECT term, block, min(bits) AS bits FROM (SELECT term, block, b, 8 + sum((x - 1) >> b) + count(*) * (1 + b) AS bits FROM rows, (SELECT unnest(range(0, 32)) AS b) GROUP BY term, block, b HAVING b >= {sql.bits_of('max(x)')} - 16) GROUP BY ALL)",
    "quad_selector": _walk([(n, b) for _, n, b in SELECTORS], sql.QUAD_NEED, 132),
    "simple9": _walk(list(words.NINE), sql.VALUE_NEED, 32),
    "simple16": _mixed_walk(),
    "simple8b": _walk(list(words.EIGHT_B), sql.ONES_NEED, 64),
    "g8iu": _filled(sql.VALUE_NEED, 8, "72 * max(groups)"),
    **{f"ql_{cg}_iu": _filled(sql.QUAD_NEED, cg, f"8 * max(groups) + 128 * cast(ceil({cg} * max(list_sum(c)) / 32) AS BIGINT)") for cg in (4, 8)},
    "afor": _plain_plan((8, 16, 32)),
    "vsencoding": _plain_plan((4, 8, 16, 32, 64)),
    "quad_afor": lane_plan_form((32, 64, 128)),
    "quad_vse": lane_plan_form((16, 32, 64, 128, 256)),
    "quad_packed": lane_frame_form(512),
    "pfor": threshold_form(False),
    "quad_pfor": threshold_form(True),
    "fastpfor": cost_form(False),
    "quad_fastpfor": cost_form(True),
}


def measured(forms: dict[str, str], values: str = "gap", collection: str = "documents") -> str:
    """WITH clause up to `sizes` (codec, term, block, n, bits) over the long lists."""
    union = " UNION ALL ".join(f"SELECT '{n}' AS codec, term, block, cast(bits AS BIGINT) AS bits FROM {form}" for n, form in forms.items())
    sizes = f"sizes AS (SELECT codec, term, block, n, bits FROM ({union}) JOIN (SELECT term, block, n FROM blk) USING (term, block))"
    return sql.gaps(collection, BLK.format(values=values, source="gaps"), sql.ROWS.format(values=values), sql.QUADS, sizes)
