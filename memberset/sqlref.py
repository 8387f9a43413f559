"""DuckDB SQL for filters: an independent reference for lines, lookups and multi-choice insertion."""

from __future__ import annotations

from .geometry import LINE_BITS, WORDS, FilterSpec
from .hashing import constant, sql_hash, sql_mul, sql_premix, sql_reduce
from .kernels import BIT, LINE, SHARD

SIGNED = "CAST(CAST({v} AS HUGEINT) - CASE WHEN {v} >= CAST('9223372036854775808' AS UBIGINT) THEN CAST('18446744073709551616' AS HUGEINT) ELSE 0 END AS BIGINT)"


def _x(key: str, spec: FilterSpec) -> str:
    return sql_premix(key) if spec.premix else f"CAST({key} AS UBIGINT)"


def _bits(spec: FilterSpec) -> str:
    """List of k expressions over x: addresses, or for distinct footprints ranks among the free addresses."""
    edge = [LINE_BITS * i // spec.k for i in range(spec.k + 1)]

    def one(i: int) -> str:
        width = spec.lines * LINE_BITS if spec.kind == "classic" else LINE_BITS - i if spec.bits == "distinct" else edge[i + 1] - edge[i] if spec.bits == "sliced" else LINE_BITS
        h = sql_hash("x", constant(spec.seed, BIT + i), width, spec.u)
        return f"{edge[i]} + {h}" if spec.kind != "classic" and spec.bits == "sliced" else h

    return "[" + ", ".join(map(one, range(spec.k))) + "]"


def _placed(source: str, k: int) -> str:
    """Ranks in ``addresses`` -> addresses: each moves past the taken ones at or below it, in rising order."""
    out = f"SELECT * RENAME (addresses AS ranks), list_slice(addresses, 1, 1) AS taken FROM ({source})"
    for i in range(2, k + 1):
        moved = f"list_reduce(list_prepend(ranks[{i}], list_sort(taken)), lambda v, s: v + CASE WHEN s <= v THEN 1 ELSE 0 END)"
        out = f"SELECT * REPLACE (list_append(taken, {moved}) AS taken) FROM ({out})"
    return f"SELECT * EXCLUDE (ranks) RENAME (taken AS addresses) FROM ({out})"


def hashed(table: str, key: str, spec: FilterSpec) -> str:
    """CTE bodies x -> h: key64, x, shard, l1..lc, addresses, for the distinct keys of a table or subquery."""
    lines = ", ".join(f"{sql_hash('x', constant(spec.seed, LINE + i), spec.lines, spec.u)} AS l{i + 1}" for i in range(spec.choices))
    source = f"""SELECT key64, {sql_hash('x', constant(spec.seed, SHARD), spec.shards, spec.u)} AS shard, {lines}, {_bits(spec)} AS addresses
  FROM (SELECT key64, {_x('key64', spec)} AS x FROM (SELECT DISTINCT {key} AS key64 FROM {table} WHERE {key} IS NOT NULL))"""
    if spec.bits == "distinct" and spec.kind != "classic":
        source = _placed(source, spec.k)
    return f"""h AS (SELECT key64, shard, l1{''.join(f', l{i + 2}' for i in range(spec.choices - 1))}, addresses FROM (
  {source}))"""


def _words(source: str) -> str:
    """shard, line, w, v (unsigned word) -> the line table."""
    columns = ", ".join(f"{SIGNED.format(v=f'max(CASE WHEN w = {i} THEN v ELSE CAST(0 AS UBIGINT) END)')} AS w{i}" for i in range(WORDS))
    return f"SELECT CAST(shard AS INTEGER) AS shard, CAST(line AS INTEGER) AS line, {columns}, CAST(sum(bit_count(CAST(v AS HUGEINT))) AS INTEGER) AS ones FROM ({source}) GROUP BY shard, line"


def _grouped(spec: FilterSpec) -> str:
    line, bit = ("a // 512", "a % 512") if spec.kind == "classic" else ("l1", "a")
    return f"SELECT shard, line, bit >> 6 AS w, bit_or(CAST(power(2, bit & 63) AS UBIGINT)) AS v FROM (SELECT shard, {line} AS line, {bit} AS bit FROM (SELECT shard, l1, unnest(addresses) AS a FROM h)) GROUP BY ALL"


def union_lines(table: str, key: str, spec: FilterSpec) -> str:
    return f"WITH {hashed(table, key, spec)} {_words(_grouped(spec))}"


def window_lines(table: str, key: str, ts: str, spec: FilterSpec) -> str:
    """Lines of one line-local filter a day."""
    columns = ", ".join(f"{SIGNED.format(v=f'max(CASE WHEN w = {i} THEN v ELSE CAST(0 AS UBIGINT) END)')} AS w{i}" for i in range(WORDS))
    return f"""WITH {hashed(table, key, spec)}, days AS (SELECT DISTINCT date_trunc('day', {ts}) AS window_start, {key} AS key64 FROM {table})
SELECT window_start, CAST(shard AS INTEGER) AS shard, CAST(l1 AS INTEGER) AS line, {columns} FROM (
  SELECT window_start, shard, l1, a >> 6 AS w, bit_or(CAST(power(2, a & 63) AS UBIGINT)) AS v
  FROM (SELECT window_start, shard, l1, unnest(addresses) AS a FROM days JOIN h USING (key64)) GROUP BY ALL) GROUP BY window_start, shard, l1"""


def union_probe(table: str, key: str, probes: str, probe_key: str, spec: FilterSpec) -> str:
    """A row per probe row: the key and whether all its bits are set."""
    place = "shard * 1000000000000 + a" if spec.kind == "classic" else "(shard * 1000000000 + l1) * 512 + a"
    return f"""WITH {hashed(table, key, spec)}, seen AS (SELECT DISTINCT {place} AS place FROM (SELECT shard, l1, unnest(addresses) AS a FROM h)),
asked AS ({hashed(probes, probe_key, spec).removeprefix("h AS (").removesuffix(")")}),
said AS (SELECT key64, bool_and(seen.place IS NOT NULL) AS maybe FROM (SELECT key64, {place} AS p FROM (SELECT key64, shard, l1, unnest(addresses) AS a FROM asked)) q LEFT JOIN seen ON seen.place = q.p GROUP BY key64)
SELECT p.{probe_key}, said.maybe FROM {probes} p JOIN said ON said.key64 = p.{probe_key}"""


def _chosen(table: str, key: str, spec: FilterSpec) -> str:
    """Recursive CTE ``st``: lines after every step; in step r each shard inserts its key of rank r."""
    total, added = spec.cost.tables(spec.k)
    place = " ".join(f"WHEN s.line = k.l{i + 1} THEN {i + 1}" for i in range(spec.choices))
    mask = "CAST(list_aggregate(list_transform(range(512), lambda i: CASE WHEN list_contains(addresses, i) THEN '1' ELSE '0' END), 'string_agg', '') AS BIT)"
    return f"""{hashed(table, key, spec)},
keyed AS (SELECT *, row_number() OVER (PARTITION BY shard ORDER BY key64) AS rank, {mask} AS mask FROM h),
st AS (
  SELECT CAST(0 AS BIGINT) AS step, s.shard, l.line, CAST(repeat('0', 512) AS BIT) AS bits, CAST(0 AS BIGINT) AS skip
  FROM (SELECT CAST(range AS BIGINT) AS shard FROM range({spec.shards})) s, (SELECT CAST(range AS BIGINT) AS line FROM range({spec.lines})) l
  UNION ALL
  SELECT step + 1, shard, line, CASE WHEN place IS NOT NULL AND line = best AND low >= 0 THEN bits | mask ELSE bits END, CASE WHEN low = -1 THEN 1 ELSE 0 END
  FROM (
    SELECT *, arg_min(line, price * 8 + place) OVER (PARTITION BY shard) AS best, min(price) OVER (PARTITION BY shard) AS low
    FROM (
      SELECT s.step, s.shard, s.line, s.bits, k.mask, CASE {place} END AS place,
        CASE WHEN CASE {place} END IS NULL THEN NULL WHEN bit_count(s.bits | k.mask) = bit_count(s.bits) THEN CAST(-1 AS HUGEINT)
          ELSE CAST({total.tolist()}[bit_count(s.bits | k.mask) + 1] AS HUGEINT) + {added.tolist()}[bit_count(s.bits | k.mask) - bit_count(s.bits) + 1] END AS price
      FROM st s LEFT JOIN keyed k ON k.shard = s.shard AND k.rank = s.step + 1
      WHERE s.step < (SELECT max(rank) FROM keyed)
    )
  )
)"""


def choice_lines(table: str, key: str, spec: FilterSpec) -> str:
    words = ", ".join(f"CAST(CAST(reverse(substr(CAST(bits AS VARCHAR), {64 * i + 1}, 64)) AS BIT) AS BIGINT) AS w{i}" for i in range(WORDS))
    return f"""WITH RECURSIVE {_chosen(table, key, spec)}
SELECT CAST(shard AS INTEGER) AS shard, CAST(line AS INTEGER) AS line, {words}, CAST(bit_count(bits) AS INTEGER) AS ones
FROM st WHERE step = (SELECT max(step) FROM st) AND bit_count(bits) > 0"""


def choice_probe(table: str, key: str, probes: str, probe_key: str, spec: FilterSpec) -> str:
    places = ", ".join(f"l{i + 1}" for i in range(spec.choices))
    return f"""WITH RECURSIVE {_chosen(table, key, spec)},
final AS (SELECT shard, line, bits FROM st WHERE step = (SELECT max(step) FROM st)),
asked AS ({hashed(probes, probe_key, spec).removeprefix("h AS (").removesuffix(")")}),
said AS (SELECT key64, bool_or(list_aggregate(list_transform(addresses, lambda a: get_bit(bits, CAST(a AS INTEGER))), 'min') = 1) AS maybe
  FROM (SELECT key64, shard, unnest([{places}]) AS line, addresses FROM asked) q JOIN final USING (shard, line) GROUP BY key64)
SELECT p.{probe_key}, said.maybe FROM {probes} p JOIN said ON said.key64 = p.{probe_key}"""


def choice_skips(table: str, key: str, spec: FilterSpec) -> str:
    return f"""WITH RECURSIVE {_chosen(table, key, spec)}
SELECT CAST(k.shard AS INTEGER) AS shard, k.keys, coalesce(s.skipped, 0) AS skipped FROM (SELECT shard, count(*) AS keys FROM keyed GROUP BY shard) k
LEFT JOIN (SELECT shard, CAST(count(DISTINCT step) AS BIGINT) AS skipped FROM st WHERE skip = 1 GROUP BY shard) s USING (shard)"""


def choice_epochs(table: str, key: str, spec: FilterSpec, epochs: int, epoch: int) -> str:
    """Batch insertion, one set of CTEs per epoch; ``epoch`` is the number of the hash that deals the keys."""
    total, added = spec.cost.tables(spec.k)
    mask = "CAST(list_aggregate(list_transform(range(512), lambda i: CASE WHEN list_contains(addresses, i) THEN '1' ELSE '0' END), 'string_agg', '') AS BIT)"
    tries = " UNION ALL ".join(f"SELECT key64, shard, {i + 1} AS choice, l{i + 1} AS line, mask, epoch FROM keyed" for i in range(spec.choices))
    zero = "CAST(repeat('0', 512) AS BIT)"
    out = f"""{hashed(table, key, spec)},
keyed AS (SELECT *, {sql_hash('key64', constant(spec.seed, epoch), epochs)} AS epoch, {mask} AS mask FROM h),
tried AS ({tries}),
s0 AS (SELECT shard, line, mask AS bits FROM tried WHERE false)"""
    for e in range(epochs):
        j, before = f"bit_count(coalesce(s.bits, {zero}) | t.mask)", f"bit_count(coalesce(s.bits, {zero}))"
        out += f""",
p{e} AS (SELECT t.key64, t.shard, t.line, t.mask, t.choice, CASE WHEN {j} = {before} THEN CAST(-1 AS HUGEINT) ELSE CAST({total.tolist()}[{j} + 1] AS HUGEINT) + {added.tolist()}[{j} - {before} + 1] END AS price
  FROM tried t LEFT JOIN s{e} s USING (shard, line) WHERE t.epoch = {e}),
c{e} AS (SELECT shard, arg_min(line, price * 8 + choice) AS line, any_value(mask) AS mask FROM p{e} GROUP BY key64, shard),
s{e + 1} AS (SELECT shard, line, bit_or(bits) AS bits FROM (SELECT shard, line, bits FROM s{e} UNION ALL SELECT shard, line, mask FROM c{e}) GROUP BY shard, line)"""
    words = ", ".join(f"CAST(CAST(reverse(substr(CAST(bits AS VARCHAR), {64 * i + 1}, 64)) AS BIT) AS BIGINT) AS w{i}" for i in range(WORDS))
    return f"WITH {out} SELECT CAST(shard AS INTEGER) AS shard, CAST(line AS INTEGER) AS line, {words}, CAST(bit_count(bits) AS INTEGER) AS ones FROM s{epochs}"


def choice_touches(table: str, key: str, probes: str, probe_key: str, spec: FilterSpec) -> str:
    """Mean lines read per lookup until the first candidate that holds the footprint, by outcome."""
    places = ", ".join(f"l{i + 1}" for i in range(spec.choices))
    return f"""WITH RECURSIVE {_chosen(table, key, spec)},
final AS (SELECT shard, line, bits FROM st WHERE step = (SELECT max(step) FROM st)),
asked AS ({hashed(probes, probe_key, spec).removeprefix("h AS (").removesuffix(")")}),
tried AS (SELECT key64, choice, list_aggregate(list_transform(addresses, lambda a: get_bit(bits, CAST(a AS INTEGER))), 'min') = 1 AS holds
  FROM (SELECT key64, shard, unnest([{places}]) AS line, unnest(range(1, {spec.choices + 1})) AS choice, addresses FROM asked) q JOIN final USING (shard, line)),
said AS (SELECT key64, bool_or(holds) AS maybe, coalesce(min(CASE WHEN holds THEN choice END), {spec.choices}) AS touched FROM tried GROUP BY key64)
SELECT maybe, round(avg(touched), 6) AS mean_touched, count(*) AS probes, {spec.choices} AS eager FROM {probes} p JOIN said ON said.key64 = p.{probe_key} GROUP BY maybe"""


def _products(first: int, n: int) -> str:
    return "[" + ", ".join(sql_mul("x", constant(1, first + i)) for i in range(n)) + "]"


def order_free_grid(keys: str, cells: list[tuple[str, int, float]], shard_keys: int) -> str:
    """Loads and expected FPR of classic and line-local filters (kind, k, relative size) sized for the counted keys of
    the subquery ``keys`` (key64): the moduli are columns."""
    top = max(k for _, k, _ in cells)
    values = ", ".join(f"('{kind}', {k}, {rel!r}::DOUBLE)" for kind, k, rel in cells)
    reduce = sql_reduce
    return f"""WITH u AS (SELECT DISTINCT key64 FROM ({keys}) WHERE key64 IS NOT NULL),
n AS (SELECT count(*) AS n, greatest(1, CAST(ceil(count(*) / {float(shard_keys)!r}::DOUBLE) AS BIGINT)) AS shards FROM u),
cells AS (SELECT kind, k, rel_size, n, shards, CAST(ceil(greatest(1, ceil(CAST(n AS DOUBLE) * k * rel_size / (ln(2.0::DOUBLE) * {LINE_BITS}))) / shards) AS BIGINT) AS lines
  FROM n, (VALUES {values}) t(kind, k, rel_size)),
y AS (SELECT {sql_mul('x', constant(1, SHARD))} AS ys, {sql_mul('x', constant(1, LINE))} AS yl, {_products(BIT, top)} AS yb FROM (SELECT {sql_premix('key64')} AS x FROM u)),
local AS (SELECT DISTINCT k, rel_size, lines, shards, {reduce('ys', 'shards')} AS shard, {reduce('yl', 'lines')} AS line, unnest(list_transform(list_slice(yb, 1, k), lambda v: v >> 55)) AS a
  FROM cells, y WHERE kind = 'linelocal'),
spread AS (SELECT DISTINCT k, rel_size, lines, shards, shard, {reduce('v', '(lines * 512)')} AS a
  FROM (SELECT k, rel_size, lines, shards, {reduce('ys', 'shards')} AS shard, unnest(list_slice(yb, 1, k)) AS v FROM cells, y WHERE kind = 'classic')),
full_lines AS (SELECT 'linelocal' AS kind, k, rel_size, lines, shards, shard, line, count(*) AS ones FROM local GROUP BY ALL
  UNION ALL SELECT 'classic', k, rel_size, lines, shards, shard, a // 512, count(*) FROM spread GROUP BY ALL),
by_shard AS (SELECT kind, k, rel_size, shards, shard, sum(ones) AS ones, max(ones) AS most, any_value(lines) AS lines,
    CASE kind WHEN 'classic' THEN pow(sum(ones) / (any_value(lines) * 512.0::DOUBLE), k) ELSE sum(pow(ones / 512.0::DOUBLE, k)) / any_value(lines) END AS p FROM full_lines GROUP BY kind, k, rel_size, shards, shard)
SELECT kind, k, rel_size, CAST((SELECT n FROM n) AS BIGINT) AS n, round(log2(sum(p) / any_value(shards)), 9) AS log2_fpr,
  round(sum(ones) / (any_value(shards) * any_value(lines))::DOUBLE, 9) AS mean_ones, CAST(max(most) AS BIGINT) AS max_ones FROM by_shard GROUP BY kind, k, rel_size"""


def classic_bits_examined(keys: str, key: str, probes: str, probe_key: str, k: int, shards: int) -> str:
    """Mean place of the first zero among the k bits (k if there is none) in a classic filter sized for the counted keys, by outcome."""
    return f"""WITH u AS (SELECT DISTINCT {key} AS key64 FROM {keys}), a AS (SELECT DISTINCT {probe_key} AS key64 FROM {probes} WHERE {probe_key} IS NOT NULL),
g AS (SELECT 512 * CAST(ceil(greatest(1, ceil(CAST(count(*) AS DOUBLE) * {k} / (ln(2.0::DOUBLE) * {LINE_BITS}))) / {shards}) AS BIGINT) AS b FROM u),
y AS (SELECT *, {sql_hash('x', constant(1, SHARD), shards)} AS shard, {_products(BIT, k)} AS yb FROM (SELECT true AS held, key64, {sql_premix('key64')} AS x FROM u UNION ALL SELECT false, key64, {sql_premix('key64')} FROM a)),
bits AS (SELECT held, key64, shard, i, {sql_reduce('v', 'b')} AS bit FROM (SELECT held, key64, shard, unnest(yb) AS v, unnest(range(1, {k + 1})) AS i FROM y), g),
have AS (SELECT DISTINCT shard, bit, true AS one FROM bits WHERE held),
said AS (SELECT key64, bool_and(one IS NOT NULL) AS maybe, coalesce(min(CASE WHEN one IS NULL THEN i END), {k}) AS read FROM bits LEFT JOIN have USING (shard, bit) WHERE NOT held GROUP BY key64)
SELECT maybe, round(avg(read), 6) AS mean_bits, count(*) AS probes FROM {probes} p JOIN said ON said.key64 = p.{probe_key} GROUP BY maybe"""
