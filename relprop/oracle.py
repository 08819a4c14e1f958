"""SQL text of the exact checks: written for DuckDB, from specs and lattice parameters, apart from the DataFrame code."""

from __future__ import annotations

from .graph import needed_tables
from .params import LatticeParams
from .schema import DATES, STAR_FKS, STAR_SPECS, Catalog, dated


def num(x: float) -> str:
    return f"({x!r}::DOUBLE)"


def source(table: str, catalog: Catalog) -> str:
    """The table, with the parts of its date where its spec has them."""
    c = DATES.get(table)
    if not c or f"{c}_year" not in catalog.specs[table].categorical:
        return table
    return f"(SELECT *, year({c})::VARCHAR AS {c}_year, month({c})::VARCHAR AS {c}_month, day({c})::VARCHAR AS {c}_day, (isodow({c}) - 1)::VARCHAR AS {c}_weekday FROM {table})"


def star(tables: list[str], dates: bool = False) -> Catalog:
    """The star catalog without frames."""
    return Catalog.build([dated(s) if dates else s for s in STAR_SPECS if s.name in tables], [k for k in STAR_FKS if k.src in tables and k.dst in tables])


def lattice_category(p: LatticeParams, domain: str, column: str, j: int) -> str:
    text = f"'{p.seed}:{domain}:' || {column} || ':{j}'"
    return f"coalesce(((('0x' || substr(md5({text}), 1, 8))::BIGINT % 2001) - 1000)::DOUBLE / 4000, 0.0)"


def rep_sql(catalog: Catalog, target: str, depth: int, p: LatticeParams, kind: str = "relu", head: str = "linear", digits: int = 6) -> str:
    """Key columns and rounded logit of a prediction after ``depth`` rounds."""
    from .features import feature_columns

    ctes: list[str] = []
    hs = [f"h_{j}" for j in range(p.d)]
    for t, spec in catalog.specs.items():
        cols = []
        for f, c in enumerate(feature_columns(catalog, t)):
            for j in range(p.d):
                if c in spec.numeric:
                    unit = f"(({c}::DOUBLE - (SELECT min({c}) FROM {t})) / nullif((SELECT max({c}) - min({c}) FROM {t}), 0)::DOUBLE)"
                    cols.append(f"greatest(0.0, coalesce({unit}, 0.0) * {num(p.weight(f'{t}.{c}.w', 0, j))} + {num(p.weight(f'{t}.{c}.b', 0, j))}) AS e{f}_{j}")
                else:
                    cols.append(f"{lattice_category(p, spec.domain(c), c, j)} AS e{f}_{j}")
        keep = list(dict.fromkeys([*spec.key, *(k.column for k in catalog.forward(t))]))
        ctes.append(f"enc_{t} AS (SELECT {', '.join([*keep, *cols])} FROM {source(t, catalog)})")
        for k in catalog.backward(t):
            ctes.append(f"delta_{k.src}_{k.column} AS (SELECT avg(ln(1 + coalesce(n, 0))) AS v FROM {t} LEFT JOIN (SELECT {k.column} AS fk, count(*) AS n FROM {k.src} GROUP BY 1) ON fk = {spec.key[0]})")

    def message(t: str, before: int, name: str, width: int, shape: str) -> str:
        """One block over the stack of fields; ``before`` is the round whose vectors are read, 0 for zero vectors."""
        spec = catalog.specs[t]
        fields = [[f"e{f}_{j}" for j in range(p.d)] for f in range(len(feature_columns(catalog, t)))]
        joins, zero = "", ["0.0"] * p.d
        for n, k in enumerate(sorted(catalog.forward(t), key=lambda k: k.name)):
            if not before:
                fields.append(zero)
                continue
            joins += f" LEFT JOIN h{before}_{k.dst} AS f{n} ON f{n}.{catalog.key(k.dst)[0]} = x.{k.column}"
            fields.append([f"coalesce(f{n}.{h}, 0.0)" for h in hs])
        for n, k in enumerate(sorted(catalog.backward(t), key=lambda k: k.name)):
            if not before:
                fields.append(zero)
                continue
            aggs = ", ".join(f"{fn}({h}) AS {s}_{h}" for s, fn in (("mean", "avg"), ("max", "max"), ("min", "min")) for h in hs)
            joins += f" LEFT JOIN (SELECT {k.column} AS fk, count(*) AS deg, {aggs} FROM h{before}_{k.src} GROUP BY 1) AS b{n} ON b{n}.fk = x.{spec.key[0]}"
            s = f"(ln(1 + b{n}.deg) / (SELECT v FROM delta_{k.src}_{k.column}))"
            out = []
            for j in range(p.d):
                terms = [f"b{n}.{st}_h_{i} * ({num(p.weight(f'agg.{k.name}.{st}.s0', i, j))} + {s} * {num(p.weight(f'agg.{k.name}.{st}.s1', i, j))} + {num(p.weight(f'agg.{k.name}.{st}.s2', i, j))} / {s})" for st in ("mean", "max", "min") for i in range(p.d)]
                out.append(f"coalesce({' + '.join(terms)}, 0.0)")
            fields.append(out)
        outs = []
        for j in range(width):
            total = " + ".join([num(p.weight(f"{name}.bias", 0, j)), *(f"{v[i]} * {num(p.weight(f'{name}.w{f}', i, j))}" for f, v in enumerate(fields) for i in range(p.d))])
            if shape == "fm":
                # Every pair of fields by itself, the inner product of its two vectors.
                pairs = [f"({a[i]}) * ({b[i]})" for n, a in enumerate(fields) for b in fields[n + 1 :] for i in range(p.d) if "0.0" not in (a[i], b[i])]
                total += "".join(f" + {x}" for x in pairs)
            outs.append(f"{f'greatest(0.0, {total})' if shape == 'relu' else total} AS h_{j}")
        keep = list(dict.fromkeys([*spec.key, *(k.column for k in catalog.forward(t))]))
        return f"SELECT {', '.join(f'x.{c}' for c in keep)}, {', '.join(outs)} FROM enc_{t} AS x{joins}"

    need = needed_tables(catalog, target, depth)
    for k in range(1, depth + 1):
        for t in sorted(need[k]):
            ctes.append(f"h{k}_{t} AS ({message(t, k - 1, f'row.{t}', p.d, kind)})")
    ctes.append(f"out AS ({message(target, depth, f'head.{target}', 1, head)})")
    return f"WITH {', '.join(ctes)} SELECT {', '.join(catalog.key(target))}, round(h_0, {digits}) AS logit FROM out"
