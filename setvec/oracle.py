"""The queries' SQL for DuckDB, put together from named parts. Everything is whole numbers until a last rounding."""

from __future__ import annotations

from setvec.functions.seeds import int12_sql, sign_sql

#: The settings that the compared queries use.
SEED, REPS, BITS, PROJ, FINAL, DIM, SCALE = 42, 4, 3, 8, 16, 64, 1 << 20
CELLS, N_CENTERS, PQ_CODES, PQ_GROUP, LISTS, PROBES, PQ_KEPT = 1 << BITS, 16, 256, 4, 8, 7, 100
TAU = int(0.1 * (1 << 40))
K, CANDIDATES = 10, 20
STAGED_PROBES, STAGED_KEEP, ENC_CODES = 4, 40, 16

_WORDS = "list_filter(regexp_split_to_array(lower({0}), '[^\\p{{L}}\\p{{N}}]+'), lambda w: w <> '')"

#: name: (parts it reads, its text)
PARTS: dict[str, tuple[tuple[str, ...], str]] = {
    "emb": ((), "SELECT vec_id, label, unnest(range(len(embedding)))::INT AS dim, unnest(embedding)::DOUBLE AS e FROM embeddings"),
    "tok": (("emb",), f"SELECT vec_id // 8 AS bag_id, (vec_id % 8)::INT AS pos, dim, floor(e * {SCALE} + 0.5)::BIGINT AS x FROM emb"),
    "q": (
        ("tok",),
        f"SELECT bag_id AS query_id, pos AS qpos, dim, x + 256 * {int12_sql(f"'noise:{SEED}:' || bag_id || ':' || pos || ':' || dim")} AS x FROM tok WHERE pos < 4",
    ),
    "planes": (
        (),
        f"SELECT rep::INT AS rep, bit::INT AS bit, dim::INT AS dim, {int12_sql(f"'plane:{SEED}:' || rep || ':' || bit || ':' || dim")} AS g "
        f"FROM range({REPS}) a(rep), range({BITS}) b(bit), range({DIM}) c(dim)",
    ),
    "inner_signs": (
        (),
        f"SELECT rep::INT AS rep, j::INT AS j, dim::INT AS dim, {sign_sql(f"'inner:{SEED}:' || rep || ':' || j || ':' || dim")} AS sgn "
        f"FROM range({REPS}) a(rep), range({PROJ}) b(j), range({DIM}) c(dim)",
    ),
    "final_signs": (
        (),
        f"SELECT i::INT AS i, j::INT AS j, {sign_sql(f"'final:{SEED}:' || i || ':' || j")} AS sgn FROM range({REPS * CELLS * PROJ}) a(i), range({FINAL}) b(j)",
    ),
    "dcell": (
        ("tok", "planes"),
        "SELECT bag_id, pos, rep, sum(CASE WHEN dot > 0 THEN 1 << bit ELSE 0 END)::INT AS cell FROM (SELECT bag_id, pos, rep, bit, sum(x * g) AS dot "
        "FROM tok JOIN planes USING (dim) GROUP BY ALL) GROUP BY bag_id, pos, rep",
    ),
    "qcell": (
        ("q", "planes"),
        "SELECT query_id, qpos, rep, sum(CASE WHEN dot > 0 THEN 1 << bit ELSE 0 END)::INT AS cell FROM (SELECT query_id, qpos, rep, bit, sum(x * g) AS dot "
        "FROM q JOIN planes USING (dim) GROUP BY ALL) GROUP BY query_id, qpos, rep",
    ),
    "dsum": (("tok", "dcell"), "SELECT bag_id, rep, cell, dim, sum(x)::BIGINT AS s, count(*)::BIGINT AS n FROM tok JOIN dcell USING (bag_id, pos) GROUP BY ALL"),
    "dmean": (("dsum",), "SELECT bag_id, rep, cell, dim, floor(s::DOUBLE / n)::BIGINT AS v FROM dsum"),
    "qblock": (("q", "qcell"), "SELECT query_id, rep, cell, dim, sum(x)::BIGINT AS v FROM q JOIN qcell USING (query_id, qpos) GROUP BY ALL"),
    "holes": (
        ("dcell",),
        f"SELECT bag_id, rep, cell, pos FROM (SELECT bag_id, rep, t.cell::INT AS cell, o.pos, bool_or(o.code = t.cell) OVER w AS own, "
        f"row_number() OVER (w ORDER BY bit_count(xor(o.code, t.cell::INT)), o.pos) AS nth FROM (SELECT bag_id, rep, cell AS code, min(pos) AS pos FROM dcell "
        f"GROUP BY ALL) o, range({CELLS}) t(cell) WINDOW w AS (PARTITION BY bag_id, rep, t.cell)) WHERE nth = 1 AND NOT own",
    ),
    "dfill": (("dmean", "holes", "tok"), "SELECT * FROM dmean UNION ALL SELECT bag_id, rep, cell, dim, x AS v FROM holes JOIN tok USING (bag_id, pos)"),
    "dproj": (("dfill", "inner_signs"), "SELECT bag_id, rep, cell, j, sum(v * sgn)::BIGINT AS v FROM dfill JOIN inner_signs USING (rep, dim) GROUP BY ALL"),
    "qproj": (("qblock", "inner_signs"), "SELECT query_id, rep, cell, j, sum(v * sgn)::BIGINT AS v FROM qblock JOIN inner_signs USING (rep, dim) GROUP BY ALL"),
    "dots": (
        ("q", "tok"),
        "SELECT query_id, qpos, bag_id AS doc_id, pos, sum(q.x * tok.x)::BIGINT AS dot FROM q JOIN tok USING (dim) GROUP BY ALL",
    ),
    "maxsim": (
        ("dots",),
        "SELECT query_id, doc_id, sum(best)::BIGINT AS score FROM (SELECT query_id, qpos, doc_id, max(dot) AS best FROM dots GROUP BY ALL) GROUP BY query_id, doc_id",
    ),
    "exact": (("maxsim",), "SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id)::INT AS rank, doc_id, score FROM maxsim"),
    "encscore": (
        ("qproj", "dproj"),
        "SELECT query_id, bag_id AS doc_id, sum(a.v * b.v)::BIGINT AS score FROM qproj a JOIN dproj b USING (rep, cell, j) GROUP BY query_id, bag_id",
    ),
    "mips": (("encscore",), "SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id)::INT AS rank, doc_id, score FROM encscore"),
    "hits": (
        ("dots",),
        "SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY query_id, qpos ORDER BY dot DESC, doc_id, pos)::INT AS hit_rank FROM dots) WHERE hit_rank <= 5",
    ),
    "tokv": (("tok",), "SELECT bag_id, pos, list(x ORDER BY dim) AS v FROM tok GROUP BY ALL"),
    "qv": (("q",), "SELECT query_id, qpos, list(x ORDER BY dim) AS v FROM q GROUP BY ALL"),
    "centers": (
        ("tok",),
        f"SELECT c - 1 AS c, dim, x FROM (SELECT bag_id, pos, row_number() OVER (ORDER BY md5('center:{SEED}:' || bag_id || ':' || pos), bag_id, pos)::INT AS c "
        f"FROM (SELECT DISTINCT bag_id, pos FROM tok)) JOIN tok USING (bag_id, pos) WHERE c <= {N_CENTERS}",
    ),
    "ccell": (
        ("tok", "centers"),
        "SELECT bag_id, pos, c AS cell FROM (SELECT bag_id, pos, c, row_number() OVER (PARTITION BY bag_id, pos ORDER BY s DESC, c) AS nth FROM (SELECT t.bag_id, t.pos, c, "
        "sum(2 * t.x * k.x - k.x * k.x)::BIGINT AS s FROM tok t JOIN centers k USING (dim) GROUP BY ALL)) WHERE nth = 1",
    ),
    "staged_table": (("q", "centers"), "SELECT query_id, qpos, c, sum(q.x * k.x)::BIGINT AS dot FROM q JOIN centers k USING (dim) GROUP BY ALL"),
    "staged_one": (
        ("staged_table", "ccell"),
        "SELECT DISTINCT p.query_id, t.bag_id AS doc_id FROM (SELECT query_id, c FROM (SELECT *, row_number() OVER (PARTITION BY query_id, qpos ORDER BY dot DESC, c) AS nth FROM staged_table) "
        f"WHERE nth <= {STAGED_PROBES}) p JOIN ccell t ON t.cell = p.c",
    ),
    "staged_two": (
        ("staged_one", "staged_table", "ccell"),
        "SELECT query_id, doc_id FROM (SELECT query_id, doc_id, row_number() OVER (PARTITION BY query_id ORDER BY sum(best) DESC, doc_id) AS nth FROM (SELECT o.query_id, o.doc_id, t.qpos, max(t.held) AS best "
        "FROM staged_one o JOIN (SELECT DISTINCT bag_id, cell FROM ccell) d ON d.bag_id = o.doc_id JOIN (SELECT query_id, qpos, c, CASE WHEN max(dot) OVER (PARTITION BY query_id, c) < 0 THEN "
        "min(dot) OVER (PARTITION BY query_id) ELSE dot END AS held FROM staged_table) t ON t.query_id = o.query_id AND t.c = d.cell GROUP BY ALL) GROUP BY query_id, doc_id) "
        f"WHERE nth <= {STAGED_KEEP}",
    ),
    "staged_three": (
        ("staged_two", "staged_table", "ccell"),
        "SELECT query_id, doc_id FROM (SELECT query_id, doc_id, row_number() OVER (PARTITION BY query_id ORDER BY sum(best) DESC, doc_id) AS nth FROM (SELECT o.query_id, o.doc_id, t.qpos, max(t.dot) AS best "
        "FROM staged_two o JOIN (SELECT DISTINCT bag_id, cell FROM ccell) d ON d.bag_id = o.doc_id JOIN staged_table t ON t.query_id = o.query_id AND t.c = d.cell GROUP BY ALL) GROUP BY query_id, doc_id) "
        f"WHERE nth <= {max(K, STAGED_KEEP // 4)}",
    ),
    "rcenters": (
        ("tok",),
        f"SELECT rep, c - 1 AS c, dim, x FROM (SELECT r.rep::INT AS rep, bag_id, pos, row_number() OVER (PARTITION BY r.rep ORDER BY md5('center:' || r.rep || ':' || bag_id || ':' || pos), bag_id, pos)::INT AS c "
        f"FROM (SELECT DISTINCT bag_id, pos FROM tok), range({REPS}) r(rep)) JOIN tok USING (bag_id, pos) WHERE c <= {N_CENTERS}",
    ),
    "rnear": (("tok", "rcenters"), "SELECT t.bag_id, t.pos, k.rep, k.c, sum(2 * t.x * k.x - k.x * k.x)::BIGINT AS s FROM tok t JOIN rcenters k USING (dim) GROUP BY ALL"),
    "rcell": (("rnear",), "SELECT bag_id, pos, rep, c AS cell FROM (SELECT *, row_number() OVER (PARTITION BY bag_id, pos, rep ORDER BY s DESC, c) AS nth FROM rnear) WHERE nth = 1"),
    "rqcell": (
        ("q", "rcenters"),
        "SELECT query_id, qpos, rep, c AS cell FROM (SELECT *, row_number() OVER (PARTITION BY query_id, qpos, rep ORDER BY s DESC, c) AS nth FROM (SELECT t.query_id, t.qpos, k.rep, k.c, "
        "sum(2 * t.x * k.x - k.x * k.x)::BIGINT AS s FROM q t JOIN rcenters k USING (dim) GROUP BY ALL)) WHERE nth = 1",
    ),
    "rnorm": (("tok",), "SELECT bag_id, pos, sum(x * x)::BIGINT AS n FROM tok GROUP BY ALL"),
    "rlen": (("rcenters",), "SELECT rep, c, sum(x * x)::BIGINT AS n FROM rcenters GROUP BY ALL"),
    "rhole": (
        ("rnear", "rcell", "rnorm", "rlen"),
        "SELECT bag_id, rep, c AS cell, pos FROM (SELECT n.bag_id, n.rep, n.c, n.pos, row_number() OVER (PARTITION BY n.bag_id, n.rep, n.c ORDER BY m.n - n.s - l.n, n.pos) AS nth FROM rnear n JOIN rnorm m "
        "USING (bag_id, pos) JOIN rlen l ON l.rep = n.rep AND l.c = n.c WHERE NOT EXISTS (SELECT 1 FROM rcell o WHERE o.bag_id = n.bag_id AND o.rep = n.rep AND o.cell = n.c)) WHERE nth = 1",
    ),
    "rblock": (
        ("tok", "rcell", "rhole"),
        "SELECT bag_id, rep, cell, dim, floor(sum(x)::DOUBLE / count(*))::BIGINT AS v FROM tok JOIN rcell USING (bag_id, pos) GROUP BY ALL UNION ALL "
        "SELECT bag_id, rep, cell, dim, x AS v FROM tok JOIN rhole USING (bag_id, pos)",
    ),
    "rdproj": (("rblock", "inner_signs"), "SELECT bag_id, rep, cell, j, sum(v * sgn)::BIGINT AS v FROM rblock JOIN inner_signs USING (rep, dim) GROUP BY ALL"),
    "rqproj": (
        ("q", "rqcell", "inner_signs"),
        "SELECT query_id, rep, cell, j, sum(x * sgn)::BIGINT AS v FROM q JOIN rqcell USING (query_id, qpos) JOIN inner_signs USING (rep, dim) GROUP BY ALL",
    ),
    "encbook": (
        ("dproj",),
        f"SELECT rep * {CELLS * PROJ} + cell * {PROJ} + d.j AS place, code, v FROM dproj d JOIN (SELECT bag_id, (row_number() OVER (ORDER BY md5('pqinit:{SEED}:' || bag_id), bag_id) - 1)::INT AS code "
        f"FROM (SELECT DISTINCT bag_id FROM dproj)) b USING (bag_id) WHERE code < {ENC_CODES}",
    ),
    "enccode": (
        ("dproj", "encbook"),
        f"SELECT bag_id, g, code FROM (SELECT *, row_number() OVER (PARTITION BY bag_id, g ORDER BY s DESC, code) AS nth FROM (SELECT d.bag_id, k.place // {PROJ} AS g, k.code, "
        f"sum(2 * d.v * k.v - k.v * k.v) AS s FROM dproj d JOIN encbook k ON k.place = d.rep * {CELLS * PROJ} + d.cell * {PROJ} + d.j GROUP BY ALL)) WHERE nth = 1",
    ),
    "codescore": (
        ("qproj", "enccode", "encbook"),
        f"SELECT query_id, doc_id, score, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id) AS rank FROM (SELECT t.query_id, c.bag_id AS doc_id, sum(part)::BIGINT AS score FROM enccode c "
        f"JOIN (SELECT a.query_id, k.place // {PROJ} AS g, k.code, sum(a.v * k.v) AS part FROM qproj a JOIN encbook k ON k.place = a.rep * {CELLS * PROJ} + a.cell * {PROJ} + a.j GROUP BY ALL) t "
        "ON t.g = c.g AND t.code = c.code GROUP BY t.query_id, c.bag_id)",
    ),
    "chunk_bits": (
        ("doc_words",),
        "SELECT bag_id, ('0x' || substr(md5(word), 1, 16))::UBIGINT AS bits FROM (SELECT doc_id * 10000000 + c AS bag_id, unnest(list_distinct(w[c * 64 + 1 : c * 64 + 128])) AS word FROM "
        "(SELECT doc_id, w, unnest(range(greatest(0, ceil((len(w) - 128) / 64.0)::BIGINT) + 1)) AS c FROM doc_words WHERE len(w) > 0))",
    ),
    "item_words": ((), f"SELECT query_id, word, count(*) AS n FROM (SELECT item_id AS query_id, unnest({_WORDS.format('text')}) AS word FROM benchmark) GROUP BY ALL"),
    "text_best": (
        ("chunk_bits", "item_words"),
        "SELECT bag_id, word, max(64 - 2 * bit_count(xor(c.bits, q.bits))) AS dot FROM chunk_bits c, (SELECT word, ('0x' || substr(md5(word), 1, 16))::UBIGINT AS bits FROM (SELECT DISTINCT word FROM item_words)) q "
        "GROUP BY bag_id, word",
    ),
    "text_scores": (("text_best", "item_words"), "SELECT query_id, bag_id, sum(n * dot)::DOUBLE / 64 AS score FROM text_best JOIN item_words USING (word) GROUP BY ALL"),
    "small": (("emb",), "SELECT vec_id, dim, floor(e * 256 + 0.5)::BIGINT AS x FROM emb"),
    "lowest": (
        (),
        f"SELECT vec_id AS src, (row_number() OVER (ORDER BY md5('pqinit:{SEED}:' || vec_id), vec_id) - 1)::INT AS code FROM embeddings",
    ),
    "pqcode": (
        ("small", "lowest"),
        f"SELECT vec_id, g, code FROM (SELECT vec_id, g, code, row_number() OVER (PARTITION BY vec_id, g ORDER BY s DESC, code) AS nth FROM (SELECT v.vec_id, "
        f"v.dim // {PQ_GROUP} AS g, l.code, sum(2 * v.x * c.x - c.x * c.x) AS s FROM small v JOIN small c USING (dim) JOIN lowest l ON l.src = c.vec_id AND l.code < {PQ_CODES} "
        "GROUP BY ALL)) WHERE nth = 1",
    ),
    "listof": (
        ("small", "lowest"),
        f"SELECT vec_id, code AS list_id FROM (SELECT vec_id, code, row_number() OVER (PARTITION BY vec_id ORDER BY s DESC, code) AS nth FROM (SELECT v.vec_id, l.code, "
        f"sum(2 * v.x * c.x - c.x * c.x) AS s FROM small v JOIN small c USING (dim) JOIN lowest l ON l.src = c.vec_id AND l.code < {LISTS} GROUP BY ALL)) WHERE nth = 1",
    ),
    "carved": (("qv",), "SELECT query_id, list(v ORDER BY qpos) AS vs FROM qv GROUP BY query_id"),
    "doc_words": ((), f"SELECT doc_id, {_WORDS.format('text')} AS w FROM documents WHERE text IS NOT NULL"),
}

_DOT = "list_sum(list_transform(list_zip({0}, {1}), lambda p: p[1]::BIGINT * p[2]::BIGINT))"


def sql(wanted: tuple[str, ...], final: str, recursive: str = "") -> str:
    """``final`` after all the parts that ``wanted`` needs, in order."""
    order: list[str] = []

    def visit(name: str) -> None:
        for before in PARTS[name][0]:
            visit(before)
        if name not in order:
            order.append(name)

    for name in wanted:
        visit(name)
    parts = [f"{n} AS ({PARTS[n][1]})" for n in order] + ([recursive] if recursive else [])
    return f"WITH {'RECURSIVE ' if recursive else ''}{', '.join(parts)} {final}" if parts else final


def _ranked(of: str, k: int) -> str:
    return f"SELECT query_id, rank, doc_id, score FROM {of} WHERE rank <= {k}"


_RERANKED = (
    f"SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id)::INT AS rank, doc_id, score FROM (SELECT m.* FROM maxsim m JOIN "
    f"(SELECT query_id, doc_id FROM mips WHERE rank <= {CANDIDATES}) USING (query_id, doc_id)) QUALIFY rank <= {K}"
)
_CUTS = (1, 5, 10)
_ONE_RECALL = (
    "SELECT n, avg(CASE WHEN rank <= n THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) AS recall FROM (SELECT w.query_id, min(m.rank) AS rank FROM (SELECT query_id, doc_id FROM "
    "(SELECT *, max(score) OVER (PARTITION BY query_id) AS top FROM maxsim) WHERE score = top) w LEFT JOIN {of} m USING (query_id, doc_id) GROUP BY w.query_id), "
    "(VALUES (1), (5), (10)) c(n) GROUP BY n"
)
#: Seeds of each query: a recursive walk over places that keeps the list of seeds so far.
_CARVE = (
    "walk AS (SELECT query_id, 0 AS i, [0] AS seeds FROM carved UNION ALL SELECT w.query_id, w.i + 1, CASE WHEN len(list_filter(w.seeds, lambda j: "
    f"{_DOT.format('c.vs[j + 1]', 'c.vs[w.i + 2]')} >= {TAU})) > 0 THEN w.seeds ELSE list_append(w.seeds, w.i + 1) END FROM walk w JOIN carved c USING (query_id) "
    "WHERE w.i + 1 < len(c.vs)), seedlist AS (SELECT query_id, arg_max(seeds, i) AS seeds FROM walk GROUP BY query_id), "
    "member AS (SELECT c.query_id, t.i::INT AS qpos, list_filter(s.seeds, lambda j: j = t.i OR (j < t.i AND "
    f"{_DOT.format('c.vs[j + 1]', 'c.vs[t.i + 1]')} >= {TAU}))[1] AS seed FROM carved c JOIN seedlist s USING (query_id), range(4) t(i))"
)
_CARVED_SUMS = _CARVE + ", csum AS (SELECT query_id, seed, dim, sum(x)::BIGINT AS x FROM q JOIN member USING (query_id, qpos) GROUP BY ALL)"
_EVENTS = "SELECT event_id, user_id, event_type, ts, epoch_us(ts) AS us FROM events"

SQL: dict[str, str] = {
    "maxsim_pairs": sql(("maxsim",), "SELECT query_id, doc_id, score FROM maxsim"),
    "maxsim_mean": sql(("maxsim",), "SELECT query_id, doc_id, score::DOUBLE / 4 AS score FROM maxsim"),
    "maxsim_topk": sql(("exact",), _ranked("exact", K)),
    "maxsim_relaxed_distance": sql(
        ("q", "tok"),
        "SELECT query_id, rank, doc_id, score FROM (SELECT query_id, doc_id, (-sum(d))::BIGINT AS score, row_number() OVER (PARTITION BY query_id ORDER BY sum(d), doc_id)::INT AS rank "
        "FROM (SELECT query_id, qpos, doc_id, min(d) AS d FROM (SELECT query_id, qpos, bag_id AS doc_id, pos, sum((q.x - tok.x) * (q.x - tok.x))::BIGINT AS d FROM q JOIN tok USING (dim) "
        f"GROUP BY ALL) GROUP BY ALL) GROUP BY query_id, doc_id) WHERE rank <= {K}",
    ),
    "sign_cells": sql(("dcell",), "SELECT bag_id, pos, rep, cell FROM dcell"),
    "query_blocks": sql(("qblock",), "SELECT query_id, rep, cell, dim, v FROM qblock"),
    "doc_blocks": sql(("dsum",), "SELECT bag_id, rep, cell, dim, s, n FROM dsum"),
    "doc_blocks_filled": sql(("dfill",), "SELECT bag_id, rep, cell, dim, v FROM dfill"),
    "doc_blocks_sum_ablation": sql(("dsum",), "SELECT bag_id, rep, cell, dim, s AS v FROM dsum WHERE s <> 0"),
    "inner_projection": sql(("dproj",), "SELECT bag_id, rep, cell, j AS dim, v FROM dproj"),
    "doc_encoding_packed": sql(("dproj",), f"SELECT bag_id, (rep * {CELLS * PROJ} + cell * {PROJ} + j)::INT AS place, v FROM dproj"),
    "query_encoding_packed": sql(("qproj",), f"SELECT query_id AS bag_id, (rep * {CELLS * PROJ} + cell * {PROJ} + j)::INT AS place, v FROM qproj WHERE v <> 0"),
    "final_projection": sql(
        ("dproj", "final_signs"),
        f"SELECT d.bag_id, f.j, sum(d.v * f.sgn)::BIGINT AS v FROM dproj d JOIN final_signs f ON f.i = d.rep * {CELLS * PROJ} + d.cell * {PROJ} + d.j GROUP BY ALL",
    ),
    "final_projection_packed": sql(
        ("dproj", "final_signs"),
        f"SELECT d.bag_id, f.j, sum(d.v * f.sgn)::BIGINT AS v FROM dproj d JOIN final_signs f ON f.i = d.rep * {CELLS * PROJ} + d.cell * {PROJ} + d.j GROUP BY ALL",
    ),
    "encode_width": sql(("dproj",), "SELECT bag_id, count(*)::INT AS width FROM dproj GROUP BY bag_id"),
    "mips_dense_topk": sql(("mips",), _ranked("mips", K)),
    "mips_sparse_topk": sql(("mips",), _ranked("mips", K)),
    "collision_score_identity": sql(
        ("dots", "qcell", "dcell"),
        "SELECT query_id, doc_id, round(sum(mean) / 1099511627776.0, 6) AS score FROM (SELECT query_id, qpos, doc_id, qcell.rep, sum(dot)::DOUBLE / count(*) AS mean FROM dots JOIN qcell USING "
        "(query_id, qpos) JOIN dcell d ON d.bag_id = doc_id AND d.pos = dots.pos AND d.rep = qcell.rep AND d.cell = qcell.cell GROUP BY ALL) GROUP BY query_id, doc_id",
    ),
    "collision_best": sql(
        ("dots", "qcell", "dcell"),
        "SELECT query_id, doc_id, sum(best)::BIGINT AS score FROM (SELECT query_id, qpos, doc_id, qcell.rep, max(dot) AS best FROM dots JOIN qcell USING "
        "(query_id, qpos) JOIN dcell d ON d.bag_id = doc_id AND d.pos = dots.pos AND d.rep = qcell.rep AND d.cell = qcell.cell GROUP BY ALL) GROUP BY query_id, doc_id",
    ),
    "encoding_estimate_error": sql(
        ("encscore", "maxsim"),
        f"SELECT round(avg(abs(e)), 6) AS mean_error, round(avg(e), 6) AS mean_signed, round(max(abs(e)), 6) AS max_error, avg(CASE WHEN abs(e) <= 0.1 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) AS within "
        f"FROM (SELECT (s.score / {PROJ}.0 / {REPS}.0 - m.score) / 4.0 / 1099511627776.0 AS e FROM encscore s JOIN maxsim m USING (query_id, doc_id))",
    ),
    "retrieve_rerank": sql(("maxsim", "mips"), _RERANKED),
    "random_center_cells": sql(("ccell",), "SELECT bag_id, pos, cell FROM ccell"),
    "token_hit_raw": sql(("hits",), "SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY hit_rank, qpos)::INT AS rank, doc_id FROM hits"),
    "token_hit_dedup": sql(
        ("hits",),
        "SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY h, p)::INT AS rank, doc_id FROM (SELECT query_id, doc_id, min((hit_rank, qpos)) AS hp, hp[1] AS h, hp[2] AS p "
        "FROM hits GROUP BY query_id, doc_id)",
    ),
    "token_hit_rerank": sql(
        ("maxsim", "hits"),
        "SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id)::INT AS rank, doc_id, score FROM maxsim JOIN (SELECT DISTINCT query_id, doc_id FROM hits) "
        f"USING (query_id, doc_id) QUALIFY rank <= {K}",
    ),
    "pooled_topk": sql(
        ("q", "tok"),
        "SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id)::INT AS rank, doc_id, score FROM (SELECT query_id, bag_id AS doc_id, sum(a.v * b.v)::BIGINT AS score "
        "FROM (SELECT query_id, dim, sum(x)::BIGINT AS v FROM q GROUP BY ALL) a JOIN (SELECT bag_id, dim, floor(sum(x)::DOUBLE / count(*))::BIGINT AS v FROM tok GROUP BY ALL) b USING (dim) "
        f"GROUP BY query_id, bag_id) QUALIFY rank <= {K}",
    ),
    "carve_clusters": sql(
        ("carved",), "SELECT query_id, count(DISTINCT seed)::INT AS groups, count(*)::INT AS vectors FROM member GROUP BY query_id", _CARVE
    ),
    "carved_rerank": sql(
        ("mips", "tok", "q", "carved"),
        "SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id)::INT AS rank, doc_id, score FROM (SELECT query_id, doc_id, sum(best)::BIGINT AS score FROM "
        "(SELECT query_id, seed, doc_id, max(dot) AS best FROM (SELECT c.query_id, c.seed, t.bag_id AS doc_id, t.pos, sum(c.x * t.x)::BIGINT AS dot FROM csum c JOIN tok t USING (dim) GROUP BY ALL) "
        f"GROUP BY ALL) JOIN (SELECT query_id, doc_id FROM mips WHERE rank <= {CANDIDATES}) USING (query_id, doc_id) GROUP BY query_id, doc_id) QUALIFY rank <= {K}",
        _CARVED_SUMS,
    ),
    "pq_codes": sql(("pqcode",), "SELECT vec_id, g::INT AS g, code FROM pqcode"),
    "pq_search": sql(
        ("pqcode", "small", "lowest"),
        f"SELECT query_id, rank, doc_id, score FROM (SELECT p.query_id, p.doc_id, sum(q.x * d.x)::DOUBLE AS score, row_number() OVER (PARTITION BY p.query_id ORDER BY sum(q.x * d.x) DESC, p.doc_id)::INT AS rank "
        f"FROM (SELECT * FROM (SELECT q.vec_id AS query_id, p.vec_id AS doc_id, row_number() OVER (PARTITION BY q.vec_id ORDER BY sum(q.part) DESC, p.vec_id) AS nth FROM (SELECT q.vec_id, q.dim // {PQ_GROUP} AS g, "
        f"l.code, sum(q.x * c.x) AS part FROM small q JOIN small c USING (dim) JOIN lowest l ON l.src = c.vec_id AND l.code < {PQ_CODES} WHERE q.vec_id % 10 = 0 GROUP BY ALL) q JOIN pqcode p ON p.g = q.g AND "
        f"p.code = q.code GROUP BY q.vec_id, p.vec_id) WHERE nth <= {PQ_KEPT}) p JOIN small q ON q.vec_id = p.query_id JOIN small d ON d.vec_id = p.doc_id AND d.dim = q.dim GROUP BY p.query_id, p.doc_id) "
        f"WHERE rank <= {K}",
    ),
    "ivf_topk": sql(
        ("listof", "small", "lowest"),
        f"SELECT query_id, rank, doc_id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id)::INT AS rank FROM (SELECT q.vec_id AS query_id, d.vec_id AS doc_id, "
        f"sum(q.x * d.x)::DOUBLE AS score FROM (SELECT vec_id, code FROM (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY s DESC, code) AS nth FROM (SELECT q.vec_id, l.code, sum(q.x * c.x) AS s "
        f"FROM small q JOIN small c USING (dim) JOIN lowest l ON l.src = c.vec_id AND l.code < {LISTS} WHERE q.vec_id % 10 = 0 GROUP BY q.vec_id, l.code)) WHERE nth <= {PROBES}) n JOIN listof o ON "
        f"o.list_id = n.code JOIN small q ON q.vec_id = n.vec_id JOIN small d ON d.vec_id = o.vec_id AND d.dim = q.dim GROUP BY q.vec_id, d.vec_id)) WHERE rank <= {K}",
    ),
    "staged_prune_whole": sql(("exact",), _ranked("exact", K)),
    "one_recall": sql(("maxsim", "mips"), _ONE_RECALL.format(of="mips")),
    "one_recall_token_hit": sql(
        ("maxsim", "hits"),
        _ONE_RECALL.format(
            of="(SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY hp)::INT AS rank, doc_id FROM (SELECT query_id, doc_id, min((hit_rank, qpos)) AS hp FROM hits GROUP BY query_id, doc_id))"
        ),
    ),
    "recall_labelled": sql(
        ("mips",),
        "SELECT n, avg(CASE WHEN rank <= n THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) AS recall FROM (SELECT query_id, min(CASE WHEN doc_id = query_id THEN rank END) AS rank FROM mips GROUP BY query_id), "
        "(VALUES (1), (5), (10)) c(n) GROUP BY n",
    ),
    "recall_pivot": sql(
        ("mips",),
        "SELECT avg(CASE WHEN rank <= 1 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) AS r1, avg(CASE WHEN rank <= 5 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) AS r5, avg(CASE WHEN rank <= 10 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) "
        "AS r10 FROM (SELECT query_id, min(CASE WHEN doc_id = query_id THEN rank END) AS rank FROM mips GROUP BY query_id)",
    ),
    "regret": sql(
        ("maxsim", "mips"),
        "SELECT query_id, (top - m.score)::BIGINT AS regret FROM (SELECT query_id, max(score) AS top FROM maxsim GROUP BY query_id) JOIN maxsim m USING (query_id) JOIN mips p ON p.query_id = m.query_id AND "
        "p.doc_id = m.doc_id WHERE p.rank = 1",
    ),
    "candidate_overlap": sql(
        ("mips", "hits"),
        f"SELECT a.query_id, count(*)::BIGINT AS n_both FROM (SELECT query_id, doc_id FROM mips WHERE rank <= {K} INTERSECT SELECT query_id, doc_id FROM hits) a GROUP BY a.query_id",
    ),
    "collision_rate": sql(
        ("dots", "qcell", "dcell"),
        "SELECT q.rep, avg(CASE WHEN q.cell = d.cell THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) AS rate FROM (SELECT *, row_number() OVER (PARTITION BY query_id, qpos ORDER BY dot DESC, doc_id, pos) AS nth FROM dots) b "
        "JOIN qcell q USING (query_id, qpos) JOIN dcell d ON d.bag_id = b.doc_id AND d.pos = b.pos AND d.rep = q.rep WHERE nth = 1 GROUP BY q.rep",
    ),
    "cell_purity": sql(
        ("dots", "qcell", "dcell"),
        f"SELECT rep, avg(pure) AS purity FROM (SELECT query_id, qpos, doc_id, q.rep, CASE WHEN min(dot) >= max(top) - {1 << 38} THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END AS pure FROM (SELECT *, max(dot) OVER (PARTITION BY "
        "query_id, qpos, doc_id) AS top FROM dots) b JOIN qcell q USING (query_id, qpos) JOIN dcell d ON d.bag_id = b.doc_id AND d.pos = b.pos AND d.rep = q.rep AND d.cell = q.cell GROUP BY ALL) GROUP BY rep",
    ),
    "floats_scanned": sql(
        ("tok",),
        f"SELECT n::BIGINT AS n, n::BIGINT * {REPS * CELLS * PROJ} AS encoding, round(4.0 * {DIM} * m_avg * n, 3) AS token_hit, round(4.0 * {DIM} * m_avg, 3) AS equal_width FROM (SELECT count(*) AS n, avg(c) AS m_avg "
        "FROM (SELECT bag_id, count(DISTINCT pos) AS c FROM tok GROUP BY bag_id))",
    ),
    "word_tokens": sql(("doc_words",), "SELECT doc_id, len(w)::INT AS n_words, len(list_distinct(w))::INT AS n_distinct FROM doc_words"),
    "chunks": sql(
        ("doc_words",),
        "SELECT doc_id, c::INT AS chunk_no, len(d)::INT AS n, md5(array_to_string(list_sort(d), ' ')) AS words_md5 FROM (SELECT doc_id, c, list_distinct(w[c * 64 + 1 : c * 64 + 128]) AS d FROM (SELECT doc_id, w, "
        "unnest(range(greatest(0, ceil((len(w) - 128) / 64.0)::BIGINT) + 1)) AS c FROM doc_words WHERE len(w) > 0))",
    ),
    "text_floats_scanned": sql(
        ("doc_words",),
        f"SELECT n, n * 10240 AS encoding, round(32.0 * {DIM} * m * n, 3) AS token_hit, round(32.0 * {DIM} * m, 3) AS equal_width, {32 * DIM}::INT AS free_search_width FROM (SELECT count(*)::BIGINT AS n, avg(d) AS m "
        "FROM (SELECT len(list_distinct(w[c * 64 + 1 : c * 64 + 128])) AS d FROM (SELECT w, unnest(range(greatest(0, ceil((len(w) - 128) / 64.0)::BIGINT) + 1)) AS c FROM doc_words WHERE len(w) > 0)))",
    ),
    "rank_fusion": sql(
        ("mips", "hits"),
        f"SELECT query_id, doc_id, ra, rb, round(coalesce(1.0::DOUBLE / (ra + 60), 0) + coalesce(1.0::DOUBLE / (rb + 60), 0), 9) AS score FROM (SELECT query_id, doc_id, rank AS ra FROM mips WHERE rank <= {K}) a FULL JOIN "
        "(SELECT query_id, doc_id, row_number() OVER (PARTITION BY query_id ORDER BY hp)::INT AS rb FROM (SELECT query_id, doc_id, min((hit_rank, qpos)) AS hp FROM hits GROUP BY query_id, doc_id) QUALIFY rb <= 10) b "
        "USING (query_id, doc_id)",
    ),
    "new_owner_curve": sql(
        ("hits",),
        "SELECT query_id, rank, sum(fresh) OVER (PARTITION BY query_id ORDER BY rank ROWS UNBOUNDED PRECEDING)::BIGINT AS owners FROM (SELECT query_id, rank, (row_number() OVER (PARTITION BY query_id, doc_id ORDER BY rank) = 1)::INT AS fresh "
        "FROM (SELECT query_id, doc_id, row_number() OVER (PARTITION BY query_id ORDER BY hit_rank, qpos)::INT AS rank FROM hits))",
    ),
    "containment_truth": "SELECT b.item_id AS query_id, d.doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)",
    "html_tokens": (
        "SELECT page_id, len(list_filter(regexp_split_to_array(lower(regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g')), "
        "'[^\\p{L}\\p{N}]+'), lambda w: w <> ''))::INT AS n_words FROM pages"
    ),
    "filtered_documents": "SELECT doc_id, n_chars FROM documents SEMI JOIN (SELECT doc_id FROM labels WHERE quality = 1 AND toxic = 0) l USING (doc_id)",
    "unseen_documents": "SELECT doc_id FROM documents ANTI JOIN labels USING (doc_id)",
    "asof_event": (
        f"SELECT e.event_id, p.event_id AS last_view FROM ({_EVENTS}) e ASOF LEFT JOIN (SELECT user_id, us, max(event_id) AS event_id FROM ({_EVENTS}) WHERE event_type = 'view' GROUP BY ALL) p "
        "ON e.user_id = p.user_id AND e.us > p.us"
    ),
    "interval_events": (
        f"SELECT v.user_id, v.event_id AS view_id, p.event_id AS purchase_id FROM ({_EVENTS}) v JOIN ({_EVENTS}) p ON v.user_id = p.user_id AND p.us > v.us AND p.us <= v.us + 3600000000 "
        "WHERE v.event_type = 'view' AND p.event_type = 'purchase'"
    ),
    "range_window_events": (
        f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY us // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW)::BIGINT AS past_hour FROM ({_EVENTS})"
    ),
    "session_bags": (
        f"SELECT user_id, min(us) AS began, count(*)::BIGINT AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY us, event_id) AS session FROM (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY user_id "
        f"ORDER BY us, event_id) < 1800000000 THEN 0 ELSE 1 END AS fresh FROM ({_EVENTS}))) GROUP BY user_id, session"
    ),
    "corpus_cube": "SELECT lang, source, count(*)::BIGINT AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY CUBE (lang, source)",
    "order_basket_similarity": (
        "WITH brands AS (SELECT p_brand, (row_number() OVER (ORDER BY p_brand) - 1)::INT AS bit FROM (SELECT DISTINCT p_brand FROM part)), masks AS (SELECT l_orderkey AS o, bit_or(1::BIGINT << bit) AS m FROM lineitem "
        "JOIN part ON p_partkey = l_partkey JOIN brands USING (p_brand) GROUP BY l_orderkey), sets AS (SELECT m, count(*)::BIGINT AS n, bit_count(m) AS s FROM masks GROUP BY m), linked AS (SELECT a.m, "
        "sum(b.n)::BIGINT AS n FROM sets a JOIN sets b ON 5 * least(a.s, b.s) >= 4 * greatest(a.s, b.s) AND 5 * bit_count(a.m & b.m) >= 4 * (a.s + b.s - bit_count(a.m & b.m)) GROUP BY a.m) "
        "SELECT o, min(o) OVER (PARTITION BY m) AS set_id, s.n AS n_copies, l.n - 1 AS n_links FROM masks JOIN sets s USING (m) JOIN linked l USING (m)"
    ),
    "staged_prune": sql(
        ("staged_three", "maxsim"),
        "SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id)::INT AS rank, doc_id, score FROM maxsim JOIN staged_three USING (query_id, doc_id) "
        f"QUALIFY rank <= {K}",
    ),
    "center_encodings": sql(
        ("rdproj", "rqproj"),
        "SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id)::INT AS rank, doc_id, score FROM (SELECT query_id, bag_id AS doc_id, sum(a.v * b.v)::BIGINT AS score FROM rqproj a "
        f"JOIN rdproj b USING (rep, cell, j) GROUP BY ALL) QUALIFY rank <= {K}",
    ),
    "graph_encodings_topk": sql(("mips",), _ranked("mips", K)),
    "graph_pq_topk": sql(
        ("codescore", "maxsim"),
        "SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY m.score DESC, doc_id)::INT AS rank, doc_id, m.score FROM maxsim m JOIN (SELECT query_id, doc_id FROM codescore WHERE "
        f"rank <= {CANDIDATES}) USING (query_id, doc_id) QUALIFY rank <= {K}",
    ),
    "text_exact_topk": sql(
        ("text_scores",),
        f"SELECT query_id, rank, bag_id AS doc_id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, bag_id)::INT AS rank FROM text_scores) WHERE rank <= {K}",
    ),
    "corpus_rollup": "SELECT lang, source, count(*)::BIGINT AS n, max(n_chars) AS longest, grouping_id(lang, source)::BIGINT AS level FROM documents GROUP BY ROLLUP (lang, source)",
    "corpus_grouping_sets": "SELECT lang, source, count(DISTINCT n_chars)::BIGINT AS lengths FROM documents GROUP BY GROUPING SETS ((lang), (source), ())",
    "event_places": (
        f"SELECT event_id, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 9) AS part, round(cume_dist() OVER w, 9) AS down, lead(event_id) OVER w AS next, nth_value(event_id, 2) OVER "
        f"(PARTITION BY user_id ORDER BY us, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second, rank() OVER (PARTITION BY user_id ORDER BY event_type) AS type_rank, "
        f"dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS type_place FROM ({_EVENTS}) WINDOW w AS (PARTITION BY user_id ORDER BY us, event_id)"
    ),
    "event_statistics": "SELECT event_type, round(median(value), 6) AS middle, round(corr(value, event_id), 6) AS trend, round(stddev_samp(value), 6) AS sd, round(quantile_cont(value, 0.9), 6) AS high FROM events GROUP BY event_type",
    "event_distinct": "SELECT event_type, count(DISTINCT user_id)::BIGINT AS users, true AS near FROM events GROUP BY event_type",
    "event_props": "SELECT event_type, sum(json_extract(props, '$.k')::BIGINT)::BIGINT AS total, count(*)::BIGINT AS n FROM events WHERE json_extract(props, '$.k')::BIGINT >= 50 GROUP BY event_type",
    "viewers_except_buyers": "SELECT user_id FROM events WHERE event_type = 'view' EXCEPT ALL SELECT user_id FROM events WHERE event_type = 'purchase'",
    "brand_distances": "SELECT DISTINCT a.p_brand AS a, b.p_brand AS b, levenshtein(a.p_brand, b.p_brand)::INT AS apart FROM (SELECT DISTINCT p_brand FROM part) a JOIN (SELECT DISTINCT p_brand FROM part) b ON a.p_brand < b.p_brand",
    "lateral_topk": (
        "SELECT c_custkey, o_orderkey, o_totalprice FROM (SELECT c_custkey, o_orderkey, o_totalprice, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS nth FROM customer JOIN orders ON "
        "o_custkey = c_custkey) WHERE nth <= 2"
    ),
    "udtf_topk": sql(("mips",), "SELECT query_id, rank, doc_id, score FROM mips WHERE rank <= 3"),
    "query_sums_by_maps": sql(("qproj",), f"SELECT query_id AS bag_id, (rep * {CELLS * PROJ} + cell * {PROJ} + j)::INT AS place, v FROM qproj WHERE v <> 0"),
    "stream_encode": sql(("dproj",), f"SELECT bag_id, (rep * {CELLS * PROJ} + cell * {PROJ} + j)::INT AS place, v FROM dproj"),
    "stream_sliding_bags": (
        "SELECT user_id, (epoch_us(date_trunc('hour', ts)) - h * 3600000000)::BIGINT AS start_us, count(*)::BIGINT AS n, sum(('0x' || substr(md5(event_type), 1, 2))::BIGINT)::BIGINT AS s FROM events, range(2) r(h) "
        "GROUP BY ALL"
    ),
    "stream_distinct": "SELECT event_id FROM events",
    "cogrouped_rerank": sql(("maxsim", "mips"), _RERANKED),
    "stream_window_bags": "SELECT user_id, epoch_us(date_trunc('day', ts)) AS day_us, count(*)::BIGINT AS n, sum(('0x' || substr(md5(event_type), 1, 2))::BIGINT)::BIGINT AS s FROM events GROUP BY ALL",
}


def _documents_ranked(where: str = "true") -> str:
    """Documents by their best chunk's exact score, the whole retrieval by brute force."""
    return (
        f"SELECT query_id, rank, doc_id, score FROM (SELECT query_id, doc_id, score, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, doc_id)::INT AS rank FROM (SELECT query_id, "
        f"bag_id // 10000000 AS doc_id, max(score) AS score FROM text_scores GROUP BY ALL) WHERE {where}) WHERE rank <= {K}"
    )


SQL["flagship"] = sql(("text_scores",), _documents_ranked())
SQL["filtered_retrieval"] = sql(("text_scores",), _documents_ranked("doc_id IN (SELECT doc_id FROM labels WHERE quality = 1 AND toxic = 0)"))
SQL["text_recall"] = sql(
    ("text_scores",),
    f"SELECT n, avg(share) AS recall FROM (SELECT t.query_id, c.n, avg(CASE WHEN r.rank <= c.n THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END) AS share FROM ({SQL['containment_truth']}) t LEFT JOIN ({_documents_ranked()}) r "
    "ON r.query_id = t.query_id AND r.doc_id = t.doc_id, (VALUES (1), (5), (10)) c(n) GROUP BY ALL) GROUP BY n",
)
SQL["stream_sessions"] = SQL["session_bags"]
SQL["stream_purchases"] = SQL["interval_events"]
SQL["pq_search_by_joins"] = SQL["pq_search"]
SQL["carve_stats"] = f"SELECT avg(groups) AS groups, avg(vectors) / avg(groups) AS fewer FROM ({SQL['carve_clusters']})"
SQL["storage_ratio"] = sql(
    ("tok",),
    f"SELECT {DIM} * avg(n) AS floats_bag, 10240.0::DOUBLE AS floats_encoding, 40960.0::DOUBLE AS bytes_encoding, 1280.0::DOUBLE AS bytes_code, 32.0::DOUBLE AS ratio "
    "FROM (SELECT count(DISTINCT pos) AS n FROM tok GROUP BY bag_id)",
)
