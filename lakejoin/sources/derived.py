"""The derived lake: many small datasets defined over the given tables, each group once, for Spark and for DuckDB.

A group is one SELECT with a ``dataset`` column and string columns; a group may hold many datasets, so that one scan
serves them all. Where the two dialects differ the text has a field in braces.
"""

from __future__ import annotations

from dataclasses import dataclass

_DIALECT = {
    "spark": {
        "explode": "explode",
        "words": "split(lower({0}), '[ \\n]+')",
        "lines": "split({0}, '[\\n]+')",
        "h100": "conv(substring(md5({0}), 1, 15), 16, 10) % 100",
        "day": "day(ts)",
        "values": "(VALUES {0}) AS m(k)",
        "bounds": "(VALUES {0}) AS b(lo, hi)",
    },
    "duckdb": {
        "explode": "unnest",
        "words": "string_split_regex(lower({0}), '[ \\n]+')",
        "lines": "string_split_regex({0}, '[\\n]+')",
        "h100": "('0x' || substr(md5({0}), 1, 15))::BIGINT % 100",
        "day": "day(ts)",
        "values": "(VALUES {0}) AS m(k)",
        "bounds": "(VALUES {0}) AS b(lo, hi)",
    },
}


@dataclass(frozen=True)
class Group:
    """SELECT of one family's datasets; ``domains`` maps its string columns to their provenance."""

    name: str
    family: str
    select: str
    domains: dict[str, str]

    def sql(self, dialect: str) -> str:
        d = _DIALECT[dialect]
        out = self.select
        for key in ("words", "lines", "h100", "values", "bounds"):
            while f"{{{key}:" in out:
                start = out.index(f"{{{key}:")
                end = out.index("}", start)
                out = out[:start] + d[key].format(out[start + len(key) + 2 : end]) + out[end + 1 :]
        return out.replace("{explode}", d["explode"]).replace("{day}", d["day"])


_TRAIN_SLICES = ((0, 100), (0, 60), (30, 90), (50, 70), (10, 18), (0, 35), (65, 100), (20, 30))
#: Small references: a few values of a large domain, whose containment in a large column is high and whose ratio is low.
_TRAIN_PICKS = ((3, 4), (9, 10), (21, 23), (28, 29), (40, 42), (47, 50), (61, 62), (74, 77), (88, 89), (95, 97))
_TEST_PICKS = ((1, 2), (5, 6), (15, 17), (25, 26), (33, 35), (44, 45), (58, 61), (69, 71), (82, 85), (91, 92))
_TEST_SLICES = ((0, 80), (25, 75), (40, 100), (0, 50), (45, 55), (70, 78), (10, 70), (60, 95))


def _bounds(pairs) -> str:
    return "{bounds:" + ", ".join(f"({a}, {b})" for a, b in pairs) + "}"


def _slices(prefix: str, table: str, value: str, pairs) -> str:
    return f"SELECT concat('{prefix}_', lo, '_', hi) AS dataset, v AS entity FROM (SELECT v, {{h100:v}} AS h FROM (SELECT {value} AS v FROM {table}) q) s JOIN {_bounds(pairs)} ON h >= lo AND h < hi"


GROUPS: tuple[Group, ...] = (
    Group("nation_dir", "geo", "SELECT 'nation_dir' AS dataset, n_name AS nation, r_name AS region FROM nation JOIN region ON n_regionkey = r_regionkey", {"nation": "nation", "region": "region"}),
    Group("customer_geo", "geo", "SELECT 'customer_geo' AS dataset, c_name AS client, n_name AS country, r_name AS region, c_mktsegment AS segment FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey", {"client": "customer", "country": "nation", "region": "region", "segment": "segment"}),
    Group("supplier_geo", "geo", "SELECT 'supplier_geo' AS dataset, s_name AS vendor, n_name AS nation_name FROM supplier JOIN nation ON s_nationkey = n_nationkey", {"vendor": "supplier", "nation_name": "nation"}),
    Group("orders_year", "trade", "SELECT concat('orders_', year(o_orderdate)) AS dataset, c_name AS buyer, o_orderstatus AS status, o_orderpriority AS priority FROM orders JOIN customer ON o_custkey = c_custkey", {"buyer": "customer", "status": "status", "priority": "priority"}),
    Group("customer_mod", "trade", "SELECT concat('customer_mod', k) AS dataset, c_name AS customer FROM customer JOIN {values:(2), (3), (4), (8), (10), (12), (16)} ON c_custkey % k = 0", {"customer": "customer"}),
    Group("shipments", "trade", "SELECT 'shipments' AS dataset, s_name AS supplier, p_name AS item, p_brand AS make, l_returnflag AS flag, l_linestatus AS state FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN part ON l_partkey = p_partkey", {"supplier": "supplier", "item": "product", "make": "brand", "flag": "flag", "state": "status"}),
    Group("part_all", "goods", "SELECT 'part_all' AS dataset, p_name, p_brand, p_type FROM part", {"p_name": "product", "p_brand": "brand", "p_type": "type"}),
    Group("part_small", "goods", "SELECT 'part_small' AS dataset, p_name AS title, p_brand AS brand, p_type AS kind FROM part WHERE p_size <= 2", {"title": "product", "brand": "brand", "kind": "type"}),
    Group("docs_words", "text", "SELECT * FROM (SELECT concat('docs_', source) AS dataset, {explode}({words:text}) AS term FROM documents WHERE source IS NOT NULL) q WHERE term <> ''", {"term": "word"}),
    Group("docs_lines", "text", "SELECT * FROM (SELECT concat('docs_', source) AS dataset, {explode}({lines:text}) AS line FROM documents WHERE source IS NOT NULL) q WHERE line <> ''", {"line": "passage"}),
    Group("vocab", "text", "SELECT * FROM (SELECT concat('vocab_', lang) AS dataset, {explode}({words:text}) AS word FROM documents WHERE lang IS NOT NULL) q WHERE word <> ''", {"word": "word"}),
    Group("bench_terms", "text", "SELECT * FROM (SELECT 'bench_terms' AS dataset, {explode}({words:text}) AS token FROM benchmark) q WHERE token <> ''", {"token": "word"}),
    Group("chat_terms", "text", "SELECT * FROM (SELECT 'chat_terms' AS dataset, {explode}({words:text}) AS token FROM conversations) q WHERE token <> ''", {"token": "word"}),
    Group("chat", "text", "SELECT 'chat' AS dataset, role AS speaker FROM conversations", {"speaker": "role"}),
    Group("page_hosts", "web", "SELECT 'page_hosts' AS dataset, regexp_extract(url, '^https?://([^/]+)', 1) AS host FROM pages", {"host": "host"}),
    Group("events_day", "stream", "SELECT concat('events_d', {day}) AS dataset, concat('user_', user_id) AS visitor, event_type AS action, props AS payload FROM events WHERE {day} % 3 = 1 AND {day} <= 28", {"visitor": "user", "action": "action", "payload": "props"}),
    Group("cslice_train", "slice", _slices("cslice", "customer", "c_name", _TRAIN_SLICES), {"entity": "customer"}),
    Group("cslice_test", "slice", _slices("cslice", "customer", "c_name", _TEST_SLICES), {"entity": "customer"}),
    Group("islice_train", "slice", _slices("islice", "part", "concat('item_', p_partkey)", _TRAIN_SLICES), {"entity": "item"}),
    Group("islice_test", "slice", _slices("islice", "part", "concat('item_', p_partkey)", _TEST_SLICES), {"entity": "item"}),
    Group("cpick_train", "pick", _slices("cpick", "customer", "c_name", _TRAIN_PICKS), {"entity": "customer"}),
    Group("cpick_test", "pick", _slices("cpick", "customer", "c_name", _TEST_PICKS), {"entity": "customer"}),
    Group("ipick_train", "pick", _slices("ipick", "part", "concat('item_', p_partkey)", _TRAIN_PICKS), {"entity": "item"}),
    Group("ipick_test", "pick", _slices("ipick", "part", "concat('item_', p_partkey)", _TEST_PICKS), {"entity": "item"}),
    Group("gate", "gate", "SELECT 'keys_as_text' AS dataset, concat('', c_custkey) AS custkey_txt, concat('+34 600 123 ', 100 + c_custkey % 900) AS phone_txt, concat('2001-01-', 10 + c_custkey % 18) AS date_txt, '   ' AS blank_txt, CAST(NULL AS VARCHAR(9)) AS null_txt FROM customer", {c: "gate" for c in ("custkey_txt", "phone_txt", "date_txt", "blank_txt", "null_txt")}),
)

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "pages", "benchmark", "conversations")

_ODD, _EVEN = (1995, 1997, 1999, 2001), (1996, 1998, 2000)


def split_sql(dataset: str) -> str:
    """CASE giving 'train', 'test' or null for a dataset name; both dialects."""
    names = lambda xs: ", ".join(f"'{x}'" for x in xs)
    train = ["nation_dir", "customer_geo", "supplier_geo", *(f"orders_{y}" for y in _ODD), *(f"customer_mod{m}" for m in (2, 4, 10, 16)), *(f"docs_src{i}" for i in range(10)), "vocab_en", "vocab_de", *(f"events_d{d}" for d in (1, 7, 13, 19, 25))]
    train += [f"{p}_{a}_{b}" for p in ("cslice", "islice") for a, b in _TRAIN_SLICES]
    train += [f"{p}_{a}_{b}" for p in ("cpick", "ipick") for a, b in _TRAIN_PICKS]
    test = ["part_all", "part_small", "shipments", *(f"orders_{y}" for y in _EVEN), *(f"customer_mod{m}" for m in (3, 8, 12)), *(f"docs_src{i}" for i in range(10, 20)), "vocab_es", "vocab_fr", "bench_terms", "chat_terms", "chat", "page_hosts", *(f"events_d{d}" for d in (4, 10, 16, 22, 28))]
    test += [f"{p}_{a}_{b}" for p in ("cslice", "islice") for a, b in _TEST_SLICES]
    test += [f"{p}_{a}_{b}" for p in ("cpick", "ipick") for a, b in _TEST_PICKS]
    return f"CASE WHEN {dataset} IN ({names(train)}) THEN 'train' WHEN {dataset} IN ({names(test)}) THEN 'test' END"


def domain_sql(attr: str) -> str:
    """CASE giving the provenance of an attribute by its name (and for ``entity`` by its dataset)."""
    named: dict[str, str] = {}
    for g in GROUPS:
        named |= {a: d for a, d in g.domains.items() if a != "entity"}
    return f"CASE {' '.join(f"WHEN {attr} = '{a}' THEN '{d}'" for a, d in sorted(named.items()))} ELSE 'entity' END"


def chosen(families: tuple[str, ...] | None = None) -> list[Group]:
    return [g for g in GROUPS if families is None or g.family in families]


def duckdb_melted(families: tuple[str, ...] | None = None) -> str:
    """CTEs ``melted(dataset, attr, value)`` and ``freq(dataset, attr, value, cnt)``."""
    parts = [f"SELECT dataset, '{a}' AS attr, CAST({a} AS VARCHAR) AS value FROM g_{g.name}" for g in chosen(families) for a in g.domains]
    views = ",\n".join(f"g_{g.name} AS ({g.sql('duckdb')})" for g in chosen(families))
    return f"WITH {views},\nmelted AS ({' UNION ALL '.join(parts)}),\nfreq AS (SELECT dataset, attr, value, CAST(count(*) AS BIGINT) AS cnt FROM melted GROUP BY ALL)"
