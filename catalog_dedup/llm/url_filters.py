"""URL filters: a blocked Bloom filter of listed prefixes and canonical URLs, then an exact hash join.

A rule lists a host (with all its subdomains), a path prefix and a verdict. Besides rules there may be a list of URLs to block: an entry
stands for the page with the same canonical form, and one that is a site's root for all pages of the site and its subdomains. From
each distinct url come the keys that an entry fitting it would have: the suffixes of the host with as many labels as a listed host
has, with the path cut to each length of a listed path, and the canonical form. A blocked Bloom filter (each key sets its bits in
one 256-bit block, so a test touches one block) passes possible hits; a join on the exact key drops false ones; the longest rule
wins (longer host first, then longer path), then the list; what nothing fits gets ``default``.

The canonical form has no scheme, default port (80, 443), trailing dot of the host, or fragment; the host is lower case, an empty
path is ``/``, escapes of letters, digits and ``-._~`` are resolved and the others in upper case; an empty query goes.

The filter is built by Spark and has ``BITS_PER_KEY`` bits a key up to ``FILTER_BITS`` (32 MB); a longer list fills it more
densely, so that more false hits go to the join, which drops them. Urls are judged once each and joined back by url with the hot
ones split by Spark's skew join. Null urls and those without ``://`` have empty host and path and fit nothing. Repeated rows each
get theirs. Entries listed twice count once; of two verdicts for one rule, block wins. Input columns named like a result, in any
case, are replaced; all other names are free. An empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import carried, others, small, stash, unpacked

BITS_PER_KEY, FILTER_BITS = 16, 1 << 28
PROBES = 6
_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: The characters whose escapes say nothing.
_PLAIN = _UPPER + _UPPER.lower() + "0123456789-._~"


def _lower(c: Column) -> Column:
    return F.translate(c, _UPPER, _UPPER.lower())


def host_and_path(url: Column) -> tuple[Column, Column]:
    rest = F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1)
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(rest, r"^[^/?#]*(/[^?#]*)", 1)
    return F.coalesce(_lower(host), F.lit("")), F.coalesce(path, F.lit(""))


def unescaped(text: Column) -> Column:
    """Escapes of plain characters resolved, the others in upper case."""
    plain = F.create_map(*[F.lit(x) for c in _PLAIN for x in (f"{ord(c):02X}", c)])
    parts = F.split(text, "%", -1)
    code = lambda p: F.upper(F.substring(p, 1, 2))
    after = lambda p: F.substring(p, F.lit(3), F.length(p))
    mend = lambda p, i: F.when(i == 0, p).when(F.element_at(plain, code(p)).isNotNull(), F.concat(F.element_at(plain, code(p)), after(p))).otherwise(F.concat(F.lit("%"), F.when(p.rlike("^[0-9A-Fa-f]{2}"), F.concat(code(p), after(p))).otherwise(p)))
    return F.array_join(F.transform(parts, mend), "")


def canonical_host(url: Column) -> Column:
    host, _ = host_and_path(url)
    return F.regexp_replace(F.regexp_replace(host, r":(80|443)?$", ""), r"\.$", "")


def canonical(url: Column) -> Column:
    """host, path and query in canonical form; empty for what is no url."""
    rest = F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^#]*)", 1)
    rest = F.regexp_replace(rest, r"\?$", "")
    rest = F.when(F.substring(rest, 1, 1) == "/", rest).otherwise(F.concat(F.lit("/"), rest))
    host = canonical_host(url)
    return F.when(host != "", F.concat(host, unescaped(rest))).otherwise("")


def _places(hashes: np.ndarray, blocks: int):
    h = hashes.astype(np.int64).view(np.uint64)
    at = (h & np.uint64(blocks - 1)).astype(np.int64)
    mixed = (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    places = [(mixed >> np.uint64(8 * p + 8)) & np.uint64(255) for p in range(PROBES)]
    return at, [(x >> np.uint64(6)).astype(np.int64) for x in places], [np.uint64(1) << (x & np.uint64(63)) for x in places]


def blocks_for(keys: int) -> int:
    """A power of two of 256-bit blocks."""
    return min(FILTER_BITS // 256, 1 << max(int(np.ceil(np.log2(max(keys, 1) * BITS_PER_KEY / 256))), 0))


def blocked_bloom(hashes: np.ndarray, blocks: int | None = None) -> np.ndarray:
    """Blocks of 256 bits (rows of 4 words) with PROBES bits a key, all in the block that the key's hash picks."""
    blocks = blocks or blocks_for(len(hashes))
    table = np.zeros((blocks, 4), np.uint64)
    at, word, bit = _places(hashes, blocks)
    for p in range(PROBES):
        np.bitwise_or.at(table, (at, word[p]), bit[p])
    return table


def built(keys: DataFrame, count: int) -> np.ndarray:
    """The filter of ``keys`` (h): tasks set bits block by block, blocks of several tasks are joined by or."""
    blocks = blocks_for(count)

    def part(batches):
        import pyarrow as pa

        for b in batches:
            h = b.column(0).to_numpy()
            order = np.argsort(h & (blocks - 1))
            at, first = np.unique((h & (blocks - 1))[order], return_inverse=True)
            table = np.zeros((len(at), 4), np.uint64)
            _, word, bit = _places(h[order], blocks)
            for p in range(PROBES):
                np.bitwise_or.at(table, (first, word[p]), bit[p])
            yield pa.RecordBatch.from_arrays([pa.array(at), *[pa.array(np.ascontiguousarray(c).view(np.int64)) for c in table.T]], names=["at", "w0", "w1", "w2", "w3"])

    rows = keys.select("h").mapInArrow(part, "at long, w0 long, w1 long, w2 long, w3 long").groupBy("at").agg(*[F.bit_or(f"w{k}").alias(f"w{k}") for k in range(4)]).toArrow()  # FILTER_BITS / 256 rows at most
    table = np.zeros((blocks, 4), np.uint64)
    for k in range(4):
        table[rows.column("at").to_numpy(), k] = rows.column(f"w{k}").to_numpy().view(np.uint64)
    return table


def possible(table: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    at, word, bit = _places(hashes, len(table))
    hit = np.ones(len(hashes), bool)
    for p in range(PROBES):
        hit &= (table[at, word[p]] & bit[p]) != 0
    return hit


def entries(rules: DataFrame, listed: DataFrame | None) -> DataFrame:
    """key, rule (null for listed urls), verdict, labels (of the host), host_length and path_length of all that is listed."""
    r = rules.select(_lower(F.col("host")).alias("host"), "path", "verdict").filter("host IS NOT NULL AND path IS NOT NULL")
    r = r.groupBy("host", "path").agg(F.max("verdict").alias("verdict"))
    dots = lambda c: F.length(c) - F.length(F.replace(c, F.lit("."), F.lit(""))) + 1
    out = r.select(F.concat("host", "path").alias("key"), F.concat("host", "path").alias("rule"), "verdict", dots(F.col("host")).alias("labels"), F.length("host").alias("host_length"), F.length("path").alias("path_length"))
    if listed is None:
        return out
    urls = listed.select(canonical(F.col("url")).alias("key"), canonical_host(F.col("url")).alias("host")).filter("key != ''").distinct()
    # Ranks below every rule; a root also stands for its site.
    return out.unionByName(urls.select("key", F.lit(None).cast("string").alias("rule"), F.lit("block").alias("verdict"), F.when(F.col("key") == F.concat("host", F.lit("/")), dots(F.col("host"))).alias("labels"), F.lit(-1).alias("host_length"), F.lit(-1).alias("path_length")))


def judge(pages: DataFrame, rules: DataFrame, keep: list[str], default: str = "allow", listed: DataFrame | None = None) -> DataFrame:
    """``keep`` columns, host, path, rule and verdict of every row of ``pages`` (url). ``rules`` has host, path and verdict (allow or
    block), ``listed`` has urls to block."""
    known = stash(entries(rules, listed), "listed")
    count = known.count()
    # Few: numbers of labels and lengths of paths that are listed.
    shapes = sorted((r[0], r[1]) for r in known.filter("rule IS NOT NULL").select("labels", "path_length").distinct().collect())
    roots = sorted(r[0] for r in known.filter("rule IS NULL AND labels IS NOT NULL").select("labels").distinct().collect())
    host, path = host_and_path(F.col("url"))
    urls = pages.select("url").filter("url IS NOT NULL").distinct().select("url", host.alias("host"), path.alias("path")).filter("host != ''")
    keep = others(keep, ["host", "path", "rule", "verdict"])
    if count:
        size = lambda h: F.length(h) - F.length(F.replace(h, F.lit("."), F.lit(""))) + 1
        tail = lambda h, k: F.substring_index(h, ".", -k)
        key = lambda k, h, p: F.struct(k.alias("key"), h.alias("host_length"), p.alias("path_length"))
        keys = [F.when((size(F.col("host")) >= k) & (F.length("path") >= n), key(F.concat(tail(F.col("host"), k), F.substring("path", 1, n)), F.length(tail(F.col("host"), k)), F.lit(n))) for k, n in shapes]
        if listed is not None:
            plain = canonical_host(F.col("url"))
            keys += [key(canonical(F.col("url")), F.lit(-1), F.lit(-1))] + [F.when(size(plain) >= k, key(F.concat(tail(plain, k), F.lit("/")), F.lit(-1), F.lit(-1))) for k in roots]
        each = urls.select("url", F.explode(F.array_distinct(F.array_compact(F.array(*keys)))).alias("k")).select("url", "k.*").withColumn("h", F.xxhash64("key"))
        table = built(known.select(F.xxhash64("key").alias("h")), count)

        def passed(batches):
            import pyarrow as pa

            for b in batches:
                yield b.filter(pa.array(possible(table, b.column("h").to_numpy())))

        each = each.mapInArrow(passed, each.schema).drop("h")
        hits = each.join(small(known.drop("labels")), ["key", "host_length", "path_length"])
        found = hits.groupBy(F.col("url").alias("f_url")).agg(F.max_by(F.struct("rule", "verdict"), F.struct("host_length", "path_length")).alias("hit"))
    else:
        found = urls.select(F.col("url").alias("f_url"), F.lit(None).cast("struct<rule: string, verdict: string>").alias("hit")).limit(0)
    out = pages.select(carried(keep).alias("row"), F.col("url").alias("p_url")).join(found, F.col("p_url") == F.col("f_url"), "left")
    host, path = host_and_path(F.col("p_url"))
    return out.select(*unpacked("row", keep), host.alias("host"), path.alias("path"), F.col("hit.rule").alias("rule"), F.coalesce("hit.verdict", F.lit(default)).alias("verdict"))
