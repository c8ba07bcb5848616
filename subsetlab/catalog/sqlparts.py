"""SQL fragments in DuckDB's dialect. Each is a list of common table expressions, joined by with_()."""

from __future__ import annotations


def with_(*ctes: str, select: str) -> str:
    return "WITH " + ",\n".join(c for c in ctes if c) + "\n" + select


def unit(v: str) -> str:
    return f"list_transform({v}, lambda x: x / sqrt(list_dot_product({v}, {v})))"


def norm_safe(v: str) -> str:
    return f"CASE WHEN list_dot_product({v}, {v}) > 0 THEN {unit(v)} END"


E = "e AS MATERIALIZED (SELECT vec_id AS id, label, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings)"
Z = f"z AS MATERIALIZED (SELECT id, label, v, {unit('v')} AS z FROM e)"
REF = "ref AS MATERIALIZED (SELECT * FROM z WHERE id % 5 < 2)"
POOL = "pool AS MATERIALIZED (SELECT * FROM z WHERE id % 5 >= 2)"


def level_h(name: str, source: str, key: str, level: str) -> str:
    """name(key, h): entropy of the levels in source (one row for each level that occurs in a sample)."""
    return f"""{name} AS MATERIALIZED (SELECT {key}, greatest(0.0, ln(sum(n)) - sum(n * ln(n)) / sum(n)) AS h
FROM (SELECT {key}, {level} AS level, CAST(count(*) AS DOUBLE) AS n FROM {source} GROUP BY ALL) GROUP BY {key})"""


def quantized(v: str, levels: int = 16, lo: str = "-0.5", hi: str = "0.5") -> str:
    return f"list_transform({v}, lambda x: greatest(0, least({levels - 1}, CAST(floor((x - ({lo})) / (({hi}) - ({lo})) * {levels}) AS INTEGER))))"


E_LEVELS = f"elv AS (SELECT id, unnest({quantized('v')}) AS lv FROM e)"
E_H = E_LEVELS + ",\n" + level_h("eh", "elv", "id", "lv")


def byte_h(name: str, table: str, id_: str, text: str) -> str:
    """name(id, h) over UTF-8 bytes; rows without bytes have entropy 0."""
    rows = f"{name}_b AS (SELECT {id_} AS id, unnest(regexp_extract_all(hex(encode({text})), '..')) AS lv FROM {table})"
    part = level_h(f"{name}_p", f"{name}_b", "id", "lv")
    return f"{rows},\n{part},\n{name} AS MATERIALIZED (SELECT {id_} AS id, coalesce(h, 0.0) AS h FROM {table} LEFT JOIN {name}_p ON {name}_p.id = {id_})"


DOC_H = byte_h("dh", "documents", "doc_id", "text")
MD5_8 = "CAST(('0x' || substr(md5({}), 1, 8)) AS BIGINT)"


def hash_order(col: str, seed: int = 42) -> str:
    return f"CAST(('0x' || substr(md5('{seed}:' || CAST({col} AS VARCHAR)), 1, 13)) AS BIGINT)"


TEST = f"""test AS MATERIALIZED (SELECT pool.* FROM pool JOIN eh USING (id) WHERE {MD5_8.format('CAST(id AS VARCHAR)')} % 3 = 0 ORDER BY round(h, 9) DESC, id LIMIT 50)"""
CAND = "cand AS MATERIALIZED (SELECT * FROM pool WHERE id NOT IN (SELECT id FROM test))"


def text_vec(prefix: str, table: str, id_: str, text: str) -> str:
    """prefix_z(id, v, z): hashed tokens of texts, square root of counts, and the unit vector."""
    return f"""{prefix}tok AS (SELECT {id_} AS id, unnest(string_split_regex(lower({text}), '\\s+')) AS t FROM {table}),
{prefix}cnt AS (SELECT id, CAST({MD5_8.format('t')} % 64 AS INTEGER) AS b, sqrt(CAST(count(*) AS DOUBLE)) AS c FROM {prefix}tok WHERE t <> '' GROUP BY ALL),
{prefix}full AS (SELECT i.id, b.b, coalesce(c.c, 0.0) AS c FROM (SELECT DISTINCT id FROM {prefix}cnt) i CROSS JOIN (SELECT unnest(range(64)) AS b) b LEFT JOIN {prefix}cnt c ON c.id = i.id AND c.b = b.b),
{prefix}raw AS (SELECT id, list(c ORDER BY b) AS v FROM {prefix}full GROUP BY id),
{prefix}z AS MATERIALIZED (SELECT id, v, {unit('v')} AS z FROM {prefix}raw)"""


DOC_VEC = text_vec("d", "documents", "doc_id", "text")
D_REF = "dref AS MATERIALIZED (SELECT * FROM dz WHERE id IN (SELECT doc_id FROM labels WHERE quality = 1 AND toxic = 0))"
D_POOL = "dpool AS MATERIALIZED (SELECT * FROM dz WHERE id NOT IN (SELECT doc_id FROM labels))"


def kmeans(prefix: str, source: str, k: int, iters: int, seeds: str | None = None, order: str = "id") -> str:
    """prefix_c(k, z) after iters rounds of spherical k-means over source(id, z), seeded with its first k rows in order, or with seeds(k, z)."""
    first = f"SELECT CAST(row_number() OVER (ORDER BY {order}) - 1 AS INTEGER) AS k, z FROM (SELECT id, z FROM {source} ORDER BY {order} LIMIT {k})"
    out = [f"{prefix}_c0 AS MATERIALIZED ({f'SELECT k, z FROM {seeds}' if seeds else first})"]
    for t in range(1, iters + 1):
        out.append(f"""{prefix}_a{t} AS MATERIALIZED (SELECT r.id, any_value(r.z) AS z, arg_max(c.k, {{'s': round(list_dot_product(r.z, c.z), 9), 'k': -c.k}}) AS k FROM {source} r CROSS JOIN {prefix}_c{t - 1} c GROUP BY r.id),
{prefix}_s{t} AS (SELECT k, list(s ORDER BY pos) AS v FROM (SELECT k, pos, sum(x) AS s FROM (SELECT k, unnest(z) AS x, generate_subscripts(z, 1) AS pos FROM {prefix}_a{t}) GROUP BY k, pos) GROUP BY k),
{prefix}_c{t} AS MATERIALIZED (SELECT c.k, coalesce({norm_safe('s.v')}, c.z) AS z FROM {prefix}_c{t - 1} c LEFT JOIN {prefix}_s{t} s ON s.k = c.k)""")
    out.append(f"{prefix}_c AS (SELECT * FROM {prefix}_c{iters})")
    return ",\n".join(out)


def farthest(name: str, source: str, k: int) -> str:
    """name(k, id, z): the first id, then again and again the row whose largest similarity with the chosen ones is least."""
    out = [f"{name}_0 AS MATERIALIZED (SELECT 0 AS k, id, z FROM {source} ORDER BY id LIMIT 1)"]
    for t in range(1, k):
        far = f"SELECT r.id, any_value(r.z) AS z, max(round(list_dot_product(r.z, s.z), 9)) AS near FROM {source} r CROSS JOIN {name}_{t - 1} s WHERE r.id NOT IN (SELECT id FROM {name}_{t - 1}) GROUP BY r.id"
        out.append(f"{name}_{t} AS MATERIALIZED (SELECT * FROM {name}_{t - 1} UNION ALL SELECT * FROM (SELECT {t} AS k, id, z FROM ({far}) ORDER BY near, id LIMIT 1))")
    out.append(f"{name} AS (SELECT * FROM {name}_{k - 1})")
    return ",\n".join(out)


def projected(name: str, source: str, d_in: int, d_out: int, vec: str = "v") -> str:
    """name(id, z): unit rows of source's vectors in d_out dimensions, by signs from MD5."""
    sign = f"CASE WHEN {MD5_8.format("'42:' || i || ':' || j")} % 2 = 1 THEN 1.0 ELSE -1.0 END / sqrt({d_out}.0)"
    return f"""{name}_m AS MATERIALIZED (SELECT j, list(CAST({sign} AS DOUBLE) ORDER BY i) AS m FROM (SELECT unnest(range({d_in})) AS i) CROSS JOIN (SELECT unnest(range({d_out})) AS j) GROUP BY j),
{name}_p AS MATERIALIZED (SELECT id, list(list_dot_product({vec}, m) ORDER BY j) AS p FROM {source} CROSS JOIN {name}_m GROUP BY id),
{name} AS MATERIALIZED (SELECT id, {unit('p')} AS z FROM {name}_p)"""


def minibatch(prefix: str, source: str, k: int, batches: int, share: int = 10) -> str:
    """prefix_c(k, z) after so many mini-batches of one hash slice in share; a centre moves by the part that a batch has of all rows it saw."""
    out = [f"{prefix}_c0 AS MATERIALIZED (SELECT CAST(row_number() OVER (ORDER BY id) - 1 AS INTEGER) AS k, z, CAST(0 AS DOUBLE) AS seen FROM (SELECT id, z FROM {source} ORDER BY id LIMIT {k}))"]
    for t in range(1, batches + 1):
        slice_ = MD5_8.format(f"'42:{(t - 1) // share}:' || CAST(r.id AS VARCHAR)")
        moved = "list_transform(list_zip(c.z, coalesce(s.v, c.z)), lambda p: (1 - coalesce(s.n, 0) / greatest(c.seen + coalesce(s.n, 0), 1)) * p[1] + coalesce(s.n, 0) / greatest(c.seen + coalesce(s.n, 0), 1) * p[2] / coalesce(s.n, 1))"
        out.append(f"""{prefix}_a{t} AS MATERIALIZED (SELECT r.id, any_value(r.z) AS z, arg_max(c.k, {{'s': round(list_dot_product(r.z, c.z), 9), 'k': -c.k}}) AS k FROM {source} r CROSS JOIN {prefix}_c{t - 1} c WHERE {slice_} % {share} = {(t - 1) % share} GROUP BY r.id),
{prefix}_s{t} AS (SELECT k, list(s ORDER BY pos) AS v, CAST(any_value(n) AS DOUBLE) AS n FROM (SELECT k, pos, sum(x) AS s, count(*) AS n FROM (SELECT k, unnest(z) AS x, generate_subscripts(z, 1) AS pos FROM {prefix}_a{t}) GROUP BY k, pos) GROUP BY k),
{prefix}_m{t} AS (SELECT c.k, c.z, c.seen + coalesce(s.n, 0) AS seen, s.n > 0 AS hit, {moved} AS w FROM {prefix}_c{t - 1} c LEFT JOIN {prefix}_s{t} s ON s.k = c.k),
{prefix}_c{t} AS MATERIALIZED (SELECT k, CASE WHEN hit THEN coalesce({norm_safe('w')}, z) ELSE z END AS z, seen FROM {prefix}_m{t})""")
    out.append(f"{prefix}_c AS (SELECT k, z FROM {prefix}_c{batches})")
    return ",\n".join(out)


def assign(name: str, rows: str, centroids: str, vec: str = "z") -> str:
    """name(id, k, sim)"""
    return f"""{name} AS MATERIALIZED (SELECT r.id, arg_max(c.k, {{'s': round(list_dot_product(r.{vec}, c.z), 9), 'k': -c.k}}) AS k, max(list_dot_product(r.{vec}, c.z)) AS sim
FROM {rows} r CROSS JOIN {centroids} c GROUP BY r.id)"""


def scene(name: str, assigned: str, budget: str, k: int, order: str = "round(sim, 9) DESC, id") -> str:
    """name(id, k, sim, rank_in_cluster, picked_by): quota, then refill by similarity."""
    return f"""{name}_r AS (SELECT *, row_number() OVER (PARTITION BY k ORDER BY {order}) AS rk FROM {assigned}),
{name}_o AS (SELECT *, rk <= ({budget}) // {k} AS quota, row_number() OVER (ORDER BY CASE WHEN rk <= ({budget}) // {k} THEN 0 ELSE 1 END, round(sim, 9) DESC, id) AS place FROM {name}_r),
{name} AS MATERIALIZED (SELECT id, k, sim, CAST(row_number() OVER (PARTITION BY k ORDER BY {order}) AS INTEGER) AS rank_in_cluster, CASE WHEN quota THEN 'quota' ELSE 'refill' END AS picked_by FROM {name}_o WHERE place <= ({budget}))"""


def top_h(name: str, rows: str, keep: str) -> str:
    """name: the keep rows of highest h."""
    return f"{name} AS MATERIALIZED (SELECT * FROM {rows} ORDER BY round(h, 9) DESC, id LIMIT ({keep}))"


def moment(selected: str, test: str, vec: str = "v", by: str = "") -> str:
    """Select of by, moment parts: selected has vec and the by columns."""
    by_ = by + ", " if by else ""
    return f"""SELECT {by_}round(sum((a.mu - b.mu) * (a.mu - b.mu)), 6) AS mean_part, round(sum((a.sd - b.sd) * (a.sd - b.sd)), 6) AS spread_part,
round(sum((a.mu - b.mu) * (a.mu - b.mu)) + sum((a.sd - b.sd) * (a.sd - b.sd)), 6) AS moment
FROM (SELECT {by_}pos, avg(x) AS mu, stddev_pop(x) AS sd FROM (SELECT {by_}unnest({vec}) AS x, generate_subscripts({vec}, 1) AS pos FROM {selected}) GROUP BY ALL) a
JOIN (SELECT pos, avg(x) AS mu, stddev_pop(x) AS sd FROM (SELECT unnest({vec}) AS x, generate_subscripts({vec}, 1) AS pos FROM {test}) GROUP BY ALL) b USING (pos)""" + (f" GROUP BY {by}" if by else "")


OUT = "SELECT id AS sample_id, CAST(k AS INTEGER) AS cluster_id, round(sim, 6) AS sim, rank_in_cluster, picked_by FROM "
