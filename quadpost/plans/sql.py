"""DuckDB text shared by the oracles. All of it computes from the raw tables."""

from __future__ import annotations

from quadpost.operators.corpus import BLOCK, SHORT_LIST, TOKEN_BREAK
from quadpost.operators.search import B, K, K1, STOP_SHARE

TOKENS = f"tok AS (SELECT doc_id, term FROM (SELECT doc_id, unnest(string_split_regex(lower(text), '{TOKEN_BREAK}')) AS term FROM col) WHERE term <> '')"
POSTINGS = "tf AS (SELECT term, doc_id, count(*) AS tf FROM tok GROUP BY ALL)"
DICTIONARY = f"dict AS (SELECT term, count(*) AS df, cast(sum(tf) AS BIGINT) AS cf, cast(ceil(count(*) / {BLOCK}) AS BIGINT) AS n_blocks FROM tf GROUP BY term)"
LENGTHS = "lens AS (SELECT doc_id, count(*) AS len FROM tok GROUP BY doc_id)"
GAPS = "gaps AS (SELECT term, doc_id, tf, row_number() OVER w - 1 AS pos, doc_id - lag(doc_id, 1, -1) OVER w AS gap FROM {source} WINDOW w AS (PARTITION BY term ORDER BY doc_id))"
LONG = f"long AS (SELECT tf.* FROM tf JOIN (SELECT term FROM tf GROUP BY term HAVING count(*) >= {SHORT_LIST}) USING (term))"

COLLECTIONS = {
    "documents": "SELECT doc_id, text FROM documents",
    "quality": "SELECT doc_id, text FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)",
    "conversations": "SELECT conv_id AS doc_id, string_agg(text, ' ' ORDER BY turn) AS text FROM conversations GROUP BY conv_id",
}


def _tidied(column: str) -> str:
    for name, mark in (("&quot;", '"'), ("&lt;", "<"), ("&gt;", ">"), ("&copy;", "©"), ("&middot;", "·"), ("&amp;", "&")):
        column = f"replace({column}, '{name}', '{mark}')"
    return f"trim(regexp_replace({column}, '[ \\t\\r\\n]+', ' ', 'g'))"


PAGE_FIELDS = f"""SELECT page_id AS doc_id, {_tidied("regexp_extract(html, '(?is)<title[^>]*>(.*?)</title>', 1)")} AS title,
  {_tidied("regexp_replace(regexp_replace(html, '(?is)<head[^>]*>.*?</head>|<script[^>]*>.*?</script>|<style[^>]*>.*?</style>|<!--.*?-->', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g')")} AS body FROM pages"""
COLLECTIONS["pages"] = f"SELECT doc_id, concat_ws(' ', title, body) AS text FROM ({PAGE_FIELDS})"


def postings(collection: str = "documents", *more: str) -> str:
    """A WITH clause up to tf and whatever else is named."""
    return "WITH RECURSIVE " + ", ".join([f"col AS ({COLLECTIONS[collection]})", TOKENS, POSTINGS, *more])


def gaps(collection: str = "documents", *more: str, source: str = "long") -> str:
    return postings(collection, LONG, GAPS.format(source=source), *more)


#: Blocks of gaps (or tfs) of the long lists: term, block, n, v (the values in order).
def blocks(values: str = "gap", collection: str = "documents", *more: str, source: str = "long") -> str:
    return gaps(collection, f"blk AS (SELECT term, pos // {BLOCK} AS block, count(*) AS n, list({values} ORDER BY pos) AS v FROM gaps GROUP BY ALL)", *more, source=source)


def bits_of(x: str) -> str:
    return f"length(bin({x}))"


ROWS = f"rows AS (SELECT term, pos // {BLOCK} AS block, pos % {BLOCK} AS i, {{values}} AS x FROM gaps)"
QUADS = "quad AS (SELECT term, block, i // 4 AS q, max(x) AS m, bit_or(x) AS o, count(*) AS members FROM rows GROUP BY ALL)"

#: Bits of a block by codec: an aggregate over `rows` (x = value) or `quad` (m = maximum).
BY_ROW = {
    "uncompressed": "32 * count(*)",
    "gamma": f"sum(2 * {bits_of('x')} - 1)",
    "vbyte": f"sum(8 * ceil({bits_of('x')} / 7))",
    "gvb": f"8 * ceil(count(*) / 4) + sum(8 * ceil({bits_of('x')} / 8))",
    "g8cu": f"72 * ceil(sum(ceil({bits_of('x')} / 8)) / 8)",
}
_UNIT = {1: ("16", 3), 2: ("8", 2), 4: ("8", 2), 8: ("8", 4)}
BY_QUAD = {}
for _cg in (1, 2, 4, 8):
    _ld = f"ceil({bits_of('m')} / {_cg})"
    BY_QUAD[f"ql_{_cg}_b"] = f"{_UNIT[_cg][0]} * ceil(count(*) / {_UNIT[_cg][1]}) + 128 * ceil(sum({_cg} * {_ld}) / 32)"
    BY_QUAD[f"ql_{_cg}_cu"] = f"8 * ceil(sum({_ld}) / 8) + 128 * ceil(sum({_cg} * {_ld}) / 32)"
BY_FRAME = {
    "packed_binary": "(SELECT term, block, sum(8 + c * w) AS bits FROM (SELECT term, block, i // 512 AS f, count(*) AS c, length(bin(max(x))) AS w FROM rows GROUP BY ALL) GROUP BY ALL)",
    "quad_bp128": "(SELECT term, block, 128 * ceil(sum(ceil(c / 4) * w) / 32) + 8 * count(*) AS bits FROM (SELECT term, block, i // 128 AS f, count(*) AS c, length(bin(max(x))) AS w FROM rows GROUP BY ALL) GROUP BY ALL)",
    "rice": """(SELECT term, block, sum((x - 1) // (1 << b) + 1 + b) + 8 AS bits FROM (SELECT rows.*, b FROM rows JOIN
      (SELECT term, block, CASE WHEN s > 0 THEN length(bin(s)) - 1 ELSE 0 END AS b FROM (SELECT term, block, cast(69 * sum(x) // (100 * count(*)) AS BIGINT) AS s FROM rows GROUP BY ALL)) USING (term, block)) GROUP BY ALL)""",
    "golomb": """(SELECT term, block, 32 + sum((x - 1) // m + 1 + CASE WHEN m = 1 THEN 0 WHEN (x - 1) % m < (1 << length(bin(m - 1))) - m THEN length(bin(m - 1)) - 1 ELSE length(bin(m - 1)) END) AS bits FROM (SELECT rows.*, m FROM rows JOIN
      (SELECT term, block, greatest(1, cast(69 * sum(x) // (100 * count(*)) AS BIGINT)) AS m FROM rows GROUP BY ALL) USING (term, block)) GROUP BY ALL)""",
}
CLOSED = [*BY_ROW, *BY_QUAD, *BY_FRAME]


def sizes_of(name: str) -> str:
    """A FROM item (term, block, bits) over `rows` and `quad`."""
    if name in BY_ROW:
        return f"(SELECT term, block, {BY_ROW[name]} AS bits FROM rows GROUP BY ALL)"
    if name in BY_QUAD:
        return f"(SELECT term, block, {BY_QUAD[name]} AS bits FROM quad GROUP BY ALL)"
    return BY_FRAME[name]


def all_sizes(names: list[str], values: str) -> str:
    """WITH clause up to `sizes` (codec, term, block, n, bits)."""
    union = " UNION ALL ".join(f"SELECT '{n}' AS codec, term, block, cast(bits AS BIGINT) AS bits FROM {sizes_of(n)}" for n in names)
    return gaps("documents", ROWS.format(values=values), QUADS, "ns AS (SELECT term, block, count(*) AS n FROM rows GROUP BY ALL)", f"sizes AS (SELECT * FROM ({union}) JOIN ns USING (term, block))")


# --- sequential codecs: recursive CTEs over lists -------------------------------------------------------------------


def walk(patterns: list[tuple[int, int]], need: str) -> str:
    """WITH clause up to `steps` (term, block, ofs, sel): a greedy walk; ``need`` lists what each cell wants (over blk)."""
    rows = ", ".join(f"({s}, {n}, {b})" for s, (n, b) in enumerate(patterns))
    return ", ".join(
        [
            f"pat(sel, num, bw) AS (VALUES {rows})",
            f"cells AS (SELECT term, block, {need} AS c FROM blk)",
            """steps(term, block, c, ofs, sel, num) AS (
              SELECT term, block, c, 0, (SELECT min(sel) FROM pat WHERE list_max(c[1:num]) <= bw), 0 FROM cells WHERE len(c) > 0
              UNION ALL
              SELECT term, block, c, ofs + taken, (SELECT min(sel) FROM pat WHERE list_max(c[ofs + taken + 1:ofs + taken + pat.num]) <= bw), taken
              FROM (SELECT steps.*, p.num AS taken FROM steps JOIN pat p USING (sel)) WHERE ofs + taken < len(c))""",
        ]
    )


QUAD_NEED = "list_transform(range(0, cast(ceil(len(v) / 4) AS BIGINT)), lambda q: length(bin(list_max(v[q * 4 + 1:q * 4 + 4]))))"
VALUE_NEED = "list_transform(v, lambda x: length(bin(x)))"
ONES_NEED = "list_transform(v, lambda x: CASE WHEN x = 1 THEN 0 ELSE length(bin(x)) END)"


def fill(unit: str, room: int) -> str:
    """WITH clause up to `fills` (term, block, used groups): values of ``unit`` cells fill groups of ``room`` greedily."""
    return ", ".join(
        [
            f"cells AS (SELECT term, block, {unit} AS c FROM blk)",
            f"""fills(term, block, c, ofs, groups, used) AS (
              SELECT term, block, c, 1, 1, c[1] FROM cells WHERE len(c) > 0
              UNION ALL
              SELECT term, block, c, ofs + 1, CASE WHEN used + c[ofs + 1] > {room} THEN groups + 1 ELSE groups END, CASE WHEN used + c[ofs + 1] > {room} THEN c[ofs + 1] ELSE used + c[ofs + 1] END
              FROM fills WHERE ofs < len(c))""",
        ]
    )


def frames(need: str, cell: int, sizes: tuple[int, ...], unit: int) -> str:
    """WITH clause up to `plan` (term, block, cost list from the end): least cost of frames of ``sizes`` (in cells of ``cell`` units)."""
    options = ", ".join(f"CASE WHEN len(c) - done >= {k // cell} THEN 8 + {k * unit} * list_max(c[len(c) - done:len(c) - done + {k // cell - 1}]) + best[{k // cell}] END" for k in sizes)
    # the cells before `done` finished ones; best[k] is the cost k cells further on
    options = options.replace("len(c) - done >=", "done + 1 >=")
    return ", ".join(
        [
            f"needs AS (SELECT term, block, {need} AS u FROM blk)",
            f"cells AS (SELECT term, block, list_transform(range(0, cast(ceil(len(u) / {cell}) AS BIGINT)), lambda k: list_max(u[k * {cell} + 1:k * {cell} + {cell}])) AS c FROM needs)",
            f"""plan(term, block, c, done, best) AS (
              SELECT term, block, c, 0, [0::BIGINT] FROM cells
              UNION ALL
              SELECT term, block, c, done + 1, list_prepend(cast(list_min([x FOR x IN [{options}] IF x IS NOT NULL]) AS BIGINT), best) FROM plan WHERE done < len(c))""",
        ]
    )


# --- search --------------------------------------------------------------------------------------------------------

STATS = "st AS (SELECT count(*) AS n, sum(len) / count(*) AS mean FROM lens)"
ASKED = f"""bt AS (SELECT item_id, list_filter(string_split_regex(lower(text), '{TOKEN_BREAK}'), lambda t: t <> '') AS t FROM benchmark),
  bw AS (SELECT item_id, t, unnest(range(0, greatest(1, len(t) // 3))) AS w FROM bt),
  bq AS (SELECT DISTINCT item_id * 100 + w AS query_id, unnest(t[w * 3 + 1:w * 3 + 2 + w % 3]) AS term FROM bw),
  asked AS (SELECT query_id, term, df FROM bq JOIN dict USING (term) WHERE df <= {STOP_SHARE} * (SELECT n FROM st))"""
PARTS = f"""parts AS (SELECT query_id, doc_id, term, ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * ({K1} + 1) / (tf + {K1} * (1 - {B} + {B} * len / mean)) AS part
  FROM asked JOIN tf USING (term) JOIN lens USING (doc_id), st)"""


def search(*more: str, collection: str = "documents") -> str:
    return postings(collection, DICTIONARY, LENGTHS, STATS, ASKED, PARTS, *more)


AND_SCORES = """need AS (SELECT query_id, count(*) AS need FROM asked GROUP BY query_id),
  scores AS (SELECT query_id, doc_id, sum(part) AS score FROM (SELECT query_id, doc_id, sum(part) AS part, count(*) AS have FROM parts GROUP BY ALL) JOIN need USING (query_id) WHERE have = need GROUP BY ALL)"""
OR_SCORES = "scores AS (SELECT query_id, doc_id, sum(part) AS score FROM parts GROUP BY ALL)"
TOP = f"""SELECT query_id, cast(rank AS INT) AS rank, doc_id, score FROM (SELECT query_id, doc_id, round(score, 6) AS score,
  row_number() OVER (PARTITION BY query_id ORDER BY round(score, 6) DESC, doc_id) AS rank FROM scores) WHERE rank <= {K}"""
