"""DuckDB common table expressions that several oracles share."""

from ..functions.text import FIRST, WIDTH
from ..sources.listings import ADJECTIVES, NOUNS, SELLERS


def _synonym(word: str, table: dict[str, str], bit: int) -> str:
    cases = " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in table.items())
    return f"CASE WHEN (h >> {bit}) % 2 = 1 THEN CASE {word} {cases} ELSE {word} END ELSE {word} END"


OFFERS = f"""
sold AS (SELECT l_partkey, l_suppkey, min(l_extendedprice / l_quantity) AS price FROM lineitem GROUP BY ALL),
raw_offers AS (SELECT *, ('0x' || substr(md5(l_partkey || '|' || l_suppkey), 1, 8))::BIGINT AS h FROM sold JOIN part ON l_partkey = p_partkey),
worded AS (SELECT *, {_synonym("split_part(p_name, ' ', 1)", ADJECTIVES, 4)} AS adj, {_synonym("split_part(p_name, ' ', 2)", NOUNS, 5)} AS noun,
    replace(p_brand, '#', CASE WHEN (h >> 6) % 2 = 1 THEN ' no ' ELSE '' END) AS brand, 'size ' || p_size AS sz FROM raw_offers),
offers AS (SELECT l_partkey * 100000 + l_suppkey AS listing_id, l_partkey AS product_key, l_suppkey AS seller, p_type || '/' || p_brand AS category,
    CASE h % 5 WHEN 0 THEN concat_ws(' ', brand, adj, noun, p_type, sz) WHEN 1 THEN concat_ws(' ', adj, noun, brand, sz, p_type)
        WHEN 2 THEN lower(concat_ws(' - ', concat_ws(' ', adj, noun, p_type), brand, sz)) WHEN 3 THEN concat_ws(' ', 'NEW!', brand, noun, adj, p_type, sz, 'fast shipping')
        ELSE upper(concat_ws(' ', p_type, adj, noun, sz, 'by', brand)) END AS title, price, p_name, p_brand, p_type, p_size, h FROM worded)"""

OFFERS3 = f"""{OFFERS},
offers3 AS (SELECT * FROM offers QUALIFY row_number() OVER (PARTITION BY product_key ORDER BY h, seller) <= {SELLERS})"""


def features(relation: str, key: str, text: str, name: str = "feats", limit: int = FIRST, width: int = WIDTH) -> str:
    """``name``(key, dim, val) and ``name``_norm(key, n2): signed hashed token counts."""
    return rf"""
{name}_tok AS (SELECT {key}, unnest(regexp_extract_all(lower({text}), '[\p{{L}}\p{{N}}]+')[1:{limit}]) AS tok FROM {relation}),
{name}_h AS (SELECT {key}, ('0x' || substr(md5(tok), 1, 8))::BIGINT AS h FROM {name}_tok),
{name} AS (SELECT {key}, h % {width} AS dim, sum(CASE WHEN (h >> 16) % 2 = 1 THEN -1 ELSE 1 END)::BIGINT AS val FROM {name}_h GROUP BY ALL HAVING val <> 0),
{name}_norm AS (SELECT {key}, sum(val * val)::BIGINT AS n2 FROM {name} GROUP BY ALL)"""


def dense(relation: str, key: str, text: str, name: str = "feats", width: int = WIDTH, limit: int = FIRST) -> str:
    """``features`` and ``{name}_vec``(key, v): the same as one list a row, for products in one pass."""
    return f"""{features(relation, key, text, name, limit, width)},
{name}_vec AS (SELECT {key}, list_transform(range({width}), lambda d: coalesce(m[d], 0)::DOUBLE) AS v FROM (SELECT {key}, map_from_entries(list((dim, val))) AS m FROM {name} GROUP BY {key}))"""


def text_lists(relation: str, key: str, asked: str, probes: int, top: int, name: str = "feats") -> str:
    """``lists``, ``member``, ``probe`` and ``candidates``(q, c, score, rank) over ``{name}`` of ``relation``: inverted lists around the texts whose keys have the smallest
    md5, and for the rows where ``asked`` holds the best ``top`` others with a positive product in the ``probes`` closest lists."""
    return f"""
seeded AS (SELECT {key}, row_number() OVER (ORDER BY md5({key}::VARCHAR)) - 1 AS list_id FROM {name}_norm QUALIFY list_id < floor(sqrt((SELECT count(*) FROM {name}_norm)))::BIGINT),
lists AS (SELECT list_id, dim, val FROM {name} JOIN seeded USING ({key})),
list_norm AS (SELECT list_id, sum(val * val)::BIGINT AS m2 FROM lists GROUP BY list_id),
to_list AS (SELECT {key}, list_id, sum(v.val * l.val)::BIGINT AS dot FROM {name} v JOIN lists l USING (dim) GROUP BY ALL),
near_list AS (SELECT {key}, list_id, row_number() OVER (PARTITION BY {key} ORDER BY dot / sqrt((n2 * m2)::DOUBLE) DESC, list_id) AS r FROM to_list JOIN {name}_norm USING ({key}) JOIN list_norm USING (list_id)),
member AS (SELECT {key}, list_id FROM near_list WHERE r = 1),
probe AS (SELECT {key}, list_id FROM near_list WHERE r <= {probes} AND {asked}),
met AS (SELECT p.{key} AS q, m.{key} AS c FROM probe p JOIN member m ON p.list_id = m.list_id AND p.{key} <> m.{key}),
product AS (SELECT q, c, list_dot_product(a.v, b.v) / sqrt((na.n2 * nb.n2)::DOUBLE) AS score FROM met JOIN {name}_vec a ON a.{key} = q JOIN {name}_vec b ON b.{key} = c JOIN {name}_norm na ON na.{key} = q JOIN {name}_norm nb ON nb.{key} = c),
candidates AS (SELECT q, c, score, row_number() OVER (PARTITION BY q ORDER BY score DESC, c)::INT AS rank FROM product WHERE score > 0 QUALIFY rank <= {top})"""


def fixed(relation: str = "embeddings") -> str:
    """``vecs``(id, dim, val) and ``norms``(id, n2)."""
    return f"""
vecs AS (SELECT vec_id AS id, unnest(range(len(embedding))) AS dim, floor(unnest(embedding)::DOUBLE * 4096)::BIGINT AS val FROM {relation}),
norms AS (SELECT id, sum(val * val)::BIGINT AS n2 FROM vecs GROUP BY id)"""


LISTS = "floor(sqrt((SELECT count(*) FROM embeddings)))::BIGINT"


def inverted(probes: int) -> str:
    """``lists``(list_id, dim, val), ``member``(id, list_id), ``probe``(id, list_id) over ``vecs``: seeded lists, closest by cosine."""
    return f"""{fixed()},
seeded AS (SELECT id, row_number() OVER (ORDER BY md5(id::VARCHAR)) - 1 AS list_id FROM norms QUALIFY list_id < {LISTS}),
lists AS (SELECT list_id, dim, val FROM vecs JOIN seeded USING (id)),
list_norm AS (SELECT list_id, sum(val * val)::BIGINT AS m2 FROM lists GROUP BY list_id),
to_list AS (SELECT id, list_id, sum(v.val * l.val)::BIGINT AS dot FROM vecs v JOIN lists l USING (dim) GROUP BY ALL),
near_list AS (SELECT id, list_id, row_number() OVER (PARTITION BY id ORDER BY dot / sqrt((n2 * m2)::DOUBLE) DESC, list_id) AS r FROM to_list JOIN norms USING (id) JOIN list_norm USING (list_id)),
member AS (SELECT id, list_id FROM near_list WHERE r = 1),
probe AS (SELECT id, list_id, r - 1 AS probe FROM near_list WHERE r <= {probes})"""
