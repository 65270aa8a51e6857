"""ANSI SQL building blocks for the oracles of the queries."""

from __future__ import annotations

from .functions.features import SPLIT_GRAIN, VIEWS, ansi_text

Weights = list[list[float]]


def hashed(*parts: str) -> str:
    """SQL of the 52-bit hash; parts are SQL expressions."""
    return f"('0x' || substr(md5(concat_ws('|', {', '.join(parts)})), 1, 13))::bigint"


def r6(e: str) -> str:
    return f"(round({e}, 6) + 0.0::double)"


def literal(w: Weights) -> str:
    return "[" + ", ".join("[" + ", ".join(f"{v!r}::double" for v in row) + "]" for row in w) + "]"


def view(name: str) -> str:
    """CTEs that end with ex(row_id, y, x, split)."""
    v = VIEWS[name]
    row_id = f"({v.id_text})::bigint" if v.id_is_key else hashed(v.id_text)
    source = f"{v.table} join {v.join} using (doc_id)" if v.join else v.table
    before = ""
    if v.trigrams:
        before = f"""
        tri as (select doc_id, {hashed('substr(text, i, 3)')} % {v.width} as bucket, count(*) as n
          from (select doc_id, text, unnest(range(1, length(text) - 1)) as i from {v.table} where length(text) > 2) group by 1, 2),
        shares as (select d.doc_id, any_value(d.lang) as lang, list(coalesce(t.n, 0)::double / greatest(length(d.text), 1) order by b.b) as x
          from {v.table} d cross join (select unnest(range(0, {v.width})) as b) b left join tri t on t.doc_id = d.doc_id and t.bucket = b.b group by d.doc_id),"""
        source, x = "shares", "x"
    else:
        x = ansi_text(v.array) if v.array else "[" + ", ".join(f"({ansi_text(e)})::double" for e in v.features) + "]"
    y = "label::int" if v.label_is_code else "(dense_rank() over (order by label) - 1)::int"
    cut = round(v.fraction * SPLIT_GRAIN)
    head = f"""{before}
      raw as (select {row_id} as row_id, {ansi_text(v.label)} as label, {x} as x from {source}),
      coded as (select row_id, {y} as y, x, case when {hashed("'split'", "0", "row_id")} % {SPLIT_GRAIN} < {cut} then 'train' else 'test' end as split from raw where label is not null)"""
    if not v.scaled:
        return head + ", ex as (select row_id, y, x, split from coded)"
    means = ", ".join(f"avg(x[{j}]) as m{j}, stddev_pop(x[{j}]) as s{j}" for j in range(1, v.d + 1))
    z = ", ".join(f"case when s{j} = 0 then 0 else (x[{j}] - m{j}) / s{j} end" for j in range(1, v.d + 1))
    return head + f""", scaler as (select {means} from coded where split = 'train'), ex as (select row_id, y, [{z}] as x, split from coded cross join scaler)"""


def dot(a: str, b: str) -> str:
    return f"list_inner_product({a}, {b})"


def residuals(source: str, w: str, m: int, name: str = "res") -> str:
    """CTE name: source with l (scores), p (probabilities) and r (residuals); w: SQL of the weights, one list per class."""
    scores = ", ".join(dot("x", f"({w})[{c}]") for c in range(1, m + 1))
    p = ", ".join(f"exp(l[{c}] - list_max(l))" for c in range(1, m + 1))
    return f"""{name}_l as (select *, [{scores}] as l from {source}),
      {name}_e as (select *, [{p}] as e from {name}_l),
      {name} as (select *, list_transform(e, lambda v: v / list_sum(e)) as p, list_transform(e, lambda v, i: v / list_sum(e) - case when i = y + 1 then 1 else 0 end) as r from {name}_e)"""


def cells(source: str, m: int, d: int, weight: str = "1.0::double", keys: str = "") -> str:
    """SELECT of (keys, cls, component, g): weighted sums of r x^T."""
    k = f"{keys}, " if keys else ""
    group = f"group by {k}c, j"
    return f"""select {k}(c - 1)::int as cls, (j - 1)::int as component, sum({weight} * r[c] * x[j]) as g
      from {source} cross join (select unnest(range(1, {m + 1})) as c) cross join (select unnest(range(1, {d + 1})) as j) {group}"""


def stats(source: str, d: int, name: str = "strata") -> str:
    mean = ", ".join(f"avg(x[{j}])" for j in range(1, d + 1))
    spread = " + ".join(f"var_pop(x[{j}])" for j in range(1, d + 1))
    return f"{name} as (select stratum, min(y)::int as y, count(*) as n_i, [{mean}] as mean, {spread} as v_i from {source} group by stratum)"


def train(name: str = "train") -> str:
    return f"{name} as (select row_id, y, x from ex where split = 'train')"


def quantile(per_class: int, source: str = "train", name: str = "assigned") -> str:
    return f"{name} as (select row_id, y, x, (y * {per_class} + ntile({per_class}) over (partition by y order by x[1], row_id) - 1)::int as stratum from {source})"


def starts(per_class: int, axis: int, source: str = "train", name: str = "a0") -> str:
    """CTEs of bins cut at the values of rank ceil(n i / per_class) along one feature, from 0, in each class."""
    x = f"x[{axis + 1}]"
    cuts = ", ".join(f"list_sort(list({x}))[ceil(count(*) * ({i} / {per_class}.0::double))::int]" for i in range(1, per_class))
    return f"""{name}_c as (select y, list_distinct([{cuts}]) as cuts from {source} group by y),
      {name} as (select row_id, y, x, (y * {per_class} + len(list_filter(cuts, lambda c: c < {x})))::int as stratum from {source} join {name}_c using (y))"""


def built(per_class: int, rule: str, iters: int, d: int, axis: int = 0, name: str = "assigned", prefix: str = "b") -> str:
    """CTEs of the builder of one start: rounds, statistics {prefix}s, and all rows assigned by them."""
    text = starts(per_class, axis, name=f"{prefix}0")
    for i in range(iters):
        text += f", {stats(f'{prefix}{i}', d, f'{prefix}s{i}')}, {assign(f'{prefix}{i}', f'{prefix}s{i}', rule, f'{prefix}{i + 1}')}"
    return f"{text}, {stats(f'{prefix}{iters}', d, f'{prefix}s')}, {assign(f'{prefix}0', f'{prefix}s', rule, name)}"


def moved(source: str, w: str, m: int, d: int, name: str, eps: str = "1e-9") -> str:
    """CTEs of one round of the dispersion rule on the gradients at w (SQL of the weights)."""
    mean = "[" + ", ".join("[" + ", ".join(f"avg(r[{c}] * x[{j}])" for j in range(1, d + 1)) + "]" for c in range(1, m + 1)) + "]"
    own = "list_inner_product(r, r) * list_inner_product(x, x)"
    cross = " + ".join(f"s.r[{c}] * list_inner_product(c.g[{c}], s.x)" for c in range(1, m + 1))
    norm = " + ".join(f"list_inner_product(g[{c}], g[{c}])" for c in range(1, m + 1))
    return f"""{residuals(source, w, m, f'{name}_r')},
      {name}_m as (select stratum, y, avg({own}) as q, {mean} as g from {name}_r group by stratum, y),
      {name}_s as (select *, {norm} as norm, sqrt(greatest(q - ({norm}), 0) + {eps}) as sigma from {name}_m),
      {name} as (select row_id, y, x, stratum from (
        select s.row_id, s.y, s.x, c.stratum, row_number() over (partition by s.row_id order by
          round(({own.replace('r,', 's.r,').replace(' r)', ' s.r)').replace('(x, x)', '(s.x, s.x)')} - 2 * ({cross}) + c.norm + {eps}) / c.sigma + c.sigma, 9), c.stratum) as place
        from {name}_r s join {name}_s c on c.y = s.y) where place = 1)"""


def gradient_counts(source: str, w: str, m: int, d: int, b: int, name: str) -> str:
    """CTEs that end with name: strata with greedy draws by the dispersion of their gradients at w."""
    return f"""{residuals(source, w, m, f'{name}_r')}, {name}_q as (select stratum, min(y)::int as y, count(*) as n_i, sum(list_inner_product(r, r) * list_inner_product(x, x)) as squares from {name}_r group by stratum),
      {name}_c as ({cells(f'{name}_r', m, d, keys='stratum')}), {name}_v as (select stratum, y, n_i, greatest(squares - g2 / n_i, 0) / n_i as v_i from {name}_q join (select stratum, sum(g * g) as g2 from {name}_c group by stratum) using (stratum)),
      {greedy(f'{name}_v', b, name)}"""


def assign(source: str, strata: str, rule: str, name: str, eps: str = "1e-6") -> str:
    dist = "list_sum(list_transform(list_zip(s.x, c.mean), lambda p: (p[1] - p[2]) * (p[1] - p[2])))"
    sigma = f"sqrt(c.v_i + {eps})"
    cost = {"euclid": dist, "frozen": f"({dist} + {eps}) / {sigma}", "dispersion": f"({dist} + {eps}) / {sigma} + {sigma}"}[rule]
    return f"""{name} as (select row_id, y, x, stratum from (
        select s.row_id, s.y, s.x, c.stratum, row_number() over (partition by s.row_id order by round({cost}, 9), c.stratum) as place
        from {source} s join {strata} c on c.y = s.y) where place = 1)"""


def positions(source: str, name: str = "indexed", buckets: int = 64) -> str:
    return f"""{name} as (select *, row_number() over (partition by stratum order by bucket, row_id) - 1 as pos
      from (select *, ({hashed("'bucket'", "row_id")} % {buckets})::int as bucket from {source}))"""


def greedy(strata: str, b: int, name: str = "counted") -> str:
    return f"""{name}_k as (select count(*) as k, sum(n_i * sqrt(v_i)) as w from {strata}),
      {name}_g as (select stratum, j, round((case when w > 0 then n_i::double * n_i * v_i else n_i::double * n_i end) / (j * (j + 1)), 9) as gain
        from {strata} cross join {name}_k cross join (select unnest(range(1, {b})) as j) where j <= {b} - k),
      {name}_w as (select stratum, count(*) as won from (select stratum, row_number() over (order by gain desc, stratum, j) as place from {name}_g) cross join {name}_k where place <= {b} - k group by stratum),
      {name} as (select s.*, (1 + coalesce(won, 0))::int as b_i from {strata} s left join {name}_w using (stratum))"""


def allocated(strata: str, b: int, kind: str, rounding: str, name: str) -> str:
    """CTEs that end with name: strata with b_i by a kind of weight and a rounding."""
    w = {"dispersion": "n_i * sqrt(v_i)", "proportional": "n_i::double", "equal": "1.0::double"}[kind]
    if rounding == "greedy":
        return f"{name}_in as (select stratum, y, n_i, v_i as true_v, ({w}) * ({w}) / (n_i::double * n_i) as v_i from {strata}), {greedy(f'{name}_in', b, f'{name}_out')}, {name} as (select stratum, n_i, true_v as v_i, b_i from {name}_out)"
    share = f"{name}_s as (select *, round(case when sum({w}) over () > 0 then {w} / sum({w}) over () else n_i / sum(n_i) over () end * ({b} - count(*) over ()), 9) as spare, count(*) over () as k from {strata})"
    if rounding == "remainder":
        return f"""{share}, {name}_p as (select *, row_number() over (order by round(spare - floor(spare), 9) desc, stratum) as place, {b} - k - sum(floor(spare)) over () as rest from {name}_s),
          {name} as (select stratum, n_i, v_i, (1 + floor(spare) + case when place <= rest then 1 else 0 end)::int as b_i from {name}_p)"""
    return f"""{share}, {name}_p as (select *, round({hashed("'systematic'", '1')} / 4503599627370496.0::double, 6) as u, round(sum(spare) over (order by stratum rows between unbounded preceding and current row), 6) as upto,
        coalesce(round(sum(spare) over (order by stratum rows between unbounded preceding and 1 preceding), 6), 0) as before from {name}_s),
      {name} as (select stratum, n_i, v_i, (1 + floor(upto + u) - floor(before + u))::int as b_i from {name}_p)"""


def draws(counted: str, seed: int, first: int, last: int, name: str = "draws") -> str:
    """CTE of (t, stratum, r, pos, draw_weight) for strata with n_i and b_i."""
    return f"""{name} as (select t::int as t, stratum, r::int as r, {hashed(str(seed), 't', 'stratum', 'r')} % n_i as pos, n_i::double / ((select sum(n_i) from {counted}) * b_i) as draw_weight
      from (select t, stratum, n_i, b_i, unnest(range(1, b_i + 1)) as r from {counted} cross join (select unnest(range({first}, {last + 1})) as t)))"""


def single(source: str, b: int, name: str = "counted") -> str:
    return f"{name} as (select 0 as stratum, count(*) as n_i, {b} as b_i from {source})"
