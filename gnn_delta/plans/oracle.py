"""SQL (DuckDB) that recomputes everything from the final graph, to hold results against."""

from __future__ import annotations

from .model import LayerSpec, ModelSpec


def with_sql(ctes: list[tuple[str, str]], select: str) -> str:
    return "WITH " + ",\n".join(f"{n} AS MATERIALIZED ({q})" for n, q in ctes) + f"\n{select}"


def features_sql(d: int, source: str = "v") -> str:
    return f"SELECT vid, " + ", ".join(f"((31 * vid + 7 * {k}) % 17 - 8) / 8.0::DOUBLE AS h{k}" for k in range(d)) + f" FROM {source}"


def second_features_sql(d: int, source: str = "v") -> str:
    return "SELECT vid, " + ", ".join(f"(CAST((vid + 1) * {2 * k + 3} * 2654435761 // 4096 AS BIGINT) % 257 - 128) / 64.0::DOUBLE AS h{k}" for k in range(d)) + f" FROM {source}"


def _dense(xs: list[str], matrix, bias=None) -> list[str]:
    out = []
    for j in range(len(matrix[0])):
        terms = [f"{x} * {float(row[j])!r}::DOUBLE" for x, row in zip(xs, matrix, strict=True) if row[j] != 0]
        if bias is not None:
            terms.insert(0, f"{float(bias[j])!r}::DOUBLE")
        out.append(" + ".join(terms) or "0.0::DOUBLE")
    return out


def layer_ctes(spec: LayerSpec, edges: str, before: str, name: str) -> list[tuple[str, str]]:
    d = spec.d_in
    deg = f"{name}_deg"
    ctes = []
    factor = "e.w * " if spec.agg == "wsum" else spec.custom.weight.format(w="e.w") + " * " if spec.custom else ""
    sent = "b.h{i}"
    join = f"FROM {edges} e JOIN {before} b ON b.vid = e.src"
    if spec.agg == "norm":
        ctes.append((deg, f"SELECT v.vid, count(e.dst) AS degree FROM v LEFT JOIN {edges} e ON e.dst = v.vid GROUP BY v.vid"))
        join += f" JOIN {deg} q ON q.vid = e.src"
        sent = "b.h{i} / sqrt(greatest(q.degree, 1))"
    if spec.agg in ("max", "min"):
        sums = ", ".join(f"{spec.agg}(b.h{i}) AS s{i}" for i in range(d))
    else:
        sums = ", ".join(f"sum({factor}{sent.format(i=i)}) AS s{i}" for i in range(d))
    if spec.agg == "attention":
        dot = " + ".join(f"b.h{i} * z.h{i}" for i in range(d))
        ctes.append((f"{name}_e", f"SELECT e.dst, exp(tanh(({dot}) / 8)) AS k, {', '.join(f'b.h{i}' for i in range(d))} {join} JOIN {before} z ON z.vid = e.dst"))
        ctes.append((f"{name}_a", f"SELECT dst AS vid, count(*) AS c, {', '.join(f'sum(k * h{i}) / sum(k) AS s{i}' for i in range(d))} FROM {name}_e GROUP BY dst"))
    else:
        ctes.append((f"{name}_a", f"SELECT e.dst AS vid, count(*) AS c, {sums} {join} GROUP BY e.dst"))
    s = [f"coalesce(a.s{i}, 0)" for i in range(d)]
    c = "coalesce(a.c, 0)"
    full = lambda x: f"CASE WHEN {c} > 0 THEN {x} ELSE 0.0 END"
    mean = [full(f"{x} / {c}") for x in s]
    x = {"mean": mean, "norm": [full(f"{y} / sqrt({c})") for y in s], "sum_mean": s + mean}.get(spec.agg, s)
    if spec.custom:
        x = [full(spec.custom.finish.format(s=y, c=c)) for y in s]
    own = [f"o.h{i}" for i in range(d)]
    relu = lambda q: f"CASE WHEN ({q}) > 0 THEN ({q}) ELSE 0.0 END"
    source = f"FROM v LEFT JOIN {name}_a a ON a.vid = v.vid" + (f" JOIN {before} o ON o.vid = v.vid" if spec.self_dependent else "")
    if spec.conv == "gin":
        inner = ", ".join(f"{a} + {1 + spec.eps!r} * {b} AS u{i}" for i, (a, b) in enumerate(zip(x, own, strict=True)))
        ctes.append((f"{name}_u", f"SELECT v.vid, {inner} {source}"))
        ctes.append((f"{name}_m", f"SELECT vid, {', '.join(f'{relu(q)} AS m{j}' for j, q in enumerate(_dense([f'u{i}' for i in range(d)], spec.w)))} FROM {name}_u"))
        z, source, vid = _dense([f"m{i}" for i in range(len(spec.w[0]))], spec.w_self, spec.bias), f"FROM {name}_m", "vid"
    else:
        ctes.append((f"{name}_x", f"SELECT v.vid, {', '.join(f'{q} AS x{i}' for i, q in enumerate(x))}{''.join(f', {q} AS o{i}' for i, q in enumerate(own)) if spec.conv == 'sage' else ''} {source}"))
        z = _dense([f"x{i}" for i in range(len(x))], spec.w, spec.bias)
        if spec.conv == "sage":
            z = [f"{a} + {b}" for a, b in zip(z, _dense([f"o{i}" for i in range(d)], spec.w_self), strict=True)]
        source, vid = f"FROM {name}_x", "vid"
    h = [relu(q) if spec.act == "relu" else q for q in z]
    ctes.append((name, f"SELECT {vid} AS vid, {', '.join(f'{q} AS h{j}' for j, q in enumerate(h))} {source}"))
    return ctes


def full_ctes(model: ModelSpec, edges: str, features: str = "h_0", prefix: str = "h") -> list[tuple[str, str]]:
    """CTEs h_1 .. h_L over edges and features (vid, h0..)."""
    ctes, before = [], features
    for i, spec in enumerate(model.layers, 1):
        ctes += layer_ctes(spec, edges, before, f"{prefix}_{i}")
        before = f"{prefix}_{i}"
    return ctes


def long_select(source: str, d: int, digits: int | None = None, key: str = "vid") -> str:
    x = "x" if digits is None else f"round(x + 3e-8, {digits})"
    return f"SELECT {key}, CAST(k AS BIGINT) AS k, CASE WHEN {x} = 0 THEN 0.0 ELSE {x} END AS x FROM (SELECT {key}, unnest(range({d})) AS k, unnest([{', '.join(f'h{i}' for i in range(d))}]) AS x FROM {source})"


def label_sql(source: str, d: int) -> str:
    xs = f"[{', '.join(f'h{i}' for i in range(d))}]"
    return f"SELECT vid, CAST(list_position({xs}, list_max({xs})) - 1 AS BIGINT) AS label FROM {source}"


def final_ctes(where: str = "true", edges: str = "snap") -> list[tuple[str, str]]:
    """CTEs last, e_new and f_new: the graph after the updates of ``upd`` that satisfy ``where``."""
    return [
        ("u", f"SELECT * FROM upd WHERE {where}"),
        ("last_e", "SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY src, dst ORDER BY seq DESC, kind DESC, w DESC) AS rn FROM u WHERE kind <> 'feat_set') WHERE rn = 1"),
        ("last_f", "SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY seq DESC) AS rn FROM u WHERE kind = 'feat_set') WHERE rn = 1"),
        ("e_new", f"SELECT src, dst, w FROM {edges} e WHERE NOT EXISTS (SELECT 1 FROM last_e x WHERE x.src = e.src AND x.dst = e.dst) UNION ALL SELECT src, dst, coalesce(w, 1.0) FROM last_e WHERE kind = 'edge_add'"),
    ]


def features_after_sql(d: int) -> str:
    return "SELECT h_0.vid, " + ", ".join(f"CASE WHEN f.src IS NULL THEN h_0.h{k} ELSE f.f{k} END AS h{k}" for k in range(d)) + " FROM h_0 LEFT JOIN last_f f ON f.src = h_0.vid"
