"""DuckDB SQL for what packed filters must answer: the same hashes and table sizes, and joins on stored signatures."""

from __future__ import annotations

import math

from fpfilter.functions.hashing import linear_sql, mix_steps_sql, product_sql, reduced_sql
from fpfilter.operators.baselines import BIN_BITS, BIN_RANGE, BIN_SLOTS, LINE_BITS, QUOTIENT_META_BITS, SPARE_SHARE, STATIC_FACTOR, VECTOR_BLOCK, VECTOR_LOAD, BaselineSpec, _spare_spec, blocked_bits_per_key
from fpfilter.operators.spec import SAFETY, FilterSpec, threshold

Spec = FilterSpec | BaselineSpec


def keys_sql(spec: Spec, n: str, z: float = 4.0) -> str:
    """What a subfilter is sized for, of ``n`` keys."""
    mean = f"({n}::DOUBLE / {spec.subs})"
    return f"({mean} + {z} * sqrt(greatest(0.0, {mean} * (1.0::DOUBLE - 1.0::DOUBLE / {spec.subs}))))"


def _power(x: str) -> str:
    """The least power of two that is not smaller than a whole number of at least one."""
    return f"(1::BIGINT << length(ltrim(bin({x} - 1), '0')))"


def addresses_sql(spec: Spec, n: str) -> str:
    """The number of addresses of a table for ``n`` keys."""
    keys = keys_sql(spec, n)
    if isinstance(spec, BaselineSpec):
        keys = f"greatest(1.0::DOUBLE, {keys})"
        if spec.kind == "bloom":
            return f"greatest(2, ceil({keys} * {spec.k} / {math.log(2)!r}::DOUBLE)::BIGINT)"
        if spec.kind == "quotient":
            return f"greatest(2, {_power(f'ceil({keys} / 0.95::DOUBLE)::BIGINT')})"
        if spec.kind == "vector_quotient":
            return f"greatest(2, {_power(f'ceil({keys} / {VECTOR_LOAD * VECTOR_BLOCK[spec.k][0]!r}::DOUBLE)::BIGINT')})"
        if spec.kind == "prefix":
            return f"greatest(2, ceil({keys} / {BIN_SLOTS})::BIGINT)"
        if spec.kind in ("blocked_bloom", "choice_bloom"):
            more = 1.05 if spec.kind == "choice_bloom" else 1.0
            return f"greatest(2, ceil({more!r}::DOUBLE * {keys} * {blocked_bits_per_key(spec.k)!r}::DOUBLE / {LINE_BITS})::BIGINT)"
        if spec.kind == "static_xor":
            return f"((ceil({keys} * {STATIC_FACTOR!r}::DOUBLE)::BIGINT + 32 + 2) // 3 * 3)"
        raise ValueError(spec.kind)
    load = 1 / 1.05 if spec.rule.startswith("xor") else SAFETY * threshold(spec.layout, spec.l)
    slots = f"greatest({spec.l + 1}, ceil({keys} / {load!r}::DOUBLE)::BIGINT)"
    if spec.layout == "window":
        return f"({slots} - {spec.l - 1})"
    buckets = f"greatest(2, ({slots} + {spec.l - 1}) // {spec.l})"
    return _power(buckets) if spec.rule.startswith("xor") else buckets


def spare_sql(spec: BaselineSpec, n: str) -> str:
    """The size of a prefix table's spare."""
    spill = f"({SPARE_SHARE!r}::DOUBLE * greatest(1.0::DOUBLE, {keys_sql(spec, n)}) * 1.1::DOUBLE + 60)"
    if spec.spare == "vector":
        return f"greatest(2, {_power(f'ceil({spill} / {VECTOR_LOAD * VECTOR_BLOCK[8][0]!r}::DOUBLE)::BIGINT')})"
    return f"greatest(2, ceil({spill} / {0.95 * 4!r}::DOUBLE)::BIGINT)"


def slots_sql(spec: FilterSpec) -> str:
    return f"(n_addr + {spec.l - 1})" if spec.layout == "window" else f"(n_addr * {spec.l})"


def _hash(spec: Spec, role: str, b: int | str, x: str = "h") -> str:
    return linear_sql(x, spec.factor(role, 3), b)


def entry_sql(spec: Spec) -> dict[str, str]:
    """Expressions over ``h`` and ``n_addr`` whose values tell stored entries apart."""
    sub = _hash(spec, "sub", spec.subs)
    if isinstance(spec, FilterSpec):
        fp = f"({_hash(spec, 'fingerprint', (1 << spec.fp_bits) - 1)} + 1)"
        w0 = _hash(spec, "address", "n_addr")
        return {"sub": sub, "w0": w0, "fp": fp}
    if spec.kind == "quotient":
        return {"sub": sub, "w0": _hash(spec, "address", "n_addr"), "fp": _hash(spec, "fingerprint", 1 << spec.k)}
    if spec.kind == "vector_quotient":
        return {"sub": sub, "w0": _hash(spec, "block", "n_addr"), "fp": _hash(spec, "tag", VECTOR_BLOCK[spec.k][1] << spec.k)}
    if spec.kind == "prefix":
        return {"sub": sub, "w0": _hash(spec, "block", "n_addr"), "fp": _hash(spec, "tag", BIN_RANGE)}
    raise ValueError(spec.kind)


def other_sql(spec: Spec) -> str:
    """The partner of ``w0`` for ``fp``, where the two are interchangeable."""
    if isinstance(spec, BaselineSpec):
        return f"xor(w0, 1 + {_hash(spec, 'partner', '(n_addr - 1)', 'fp::UBIGINT')})"
    if spec.rule == "mirror":
        return "((2 * n_addr - (w0 + fp % n_addr)) % n_addr)"
    if spec.rule == "xor_raw":
        return "xor(w0, fp & (n_addr - 1))"
    return f"xor(w0, 1 + {_hash(spec, 'partner', '(n_addr - 1)', 'fp::UBIGINT')})"


def symmetric(spec: Spec) -> bool:
    return spec.rule != "signed" if isinstance(spec, FilterSpec) else spec.kind == "vector_quotient"


def signature_ctes(spec: Spec, members: str, probes: str, n: str = "count(*)", having: str = "", sums: str = "count(*)") -> str:
    """CTEs ``stored`` (distinct entries of members' ``key`` with ``total``) and ``answers`` (rows of probes with ``hit``).

    ``n`` is the number of keys the table is sized for, an aggregate over members; ``having`` a condition on the
    members of an entry, ``sums`` what its total is made of.
    """
    e = entry_sql(spec)

    def entries(source: str, to: str) -> str:
        first = f"{to}_e AS (SELECT *, {e['sub']} AS sub, {e['w0']} AS w0, {e['fp']} AS fp FROM {source}, size)"
        last = f"least(w0, {other_sql(spec)})" if symmetric(spec) else "w0"
        return f"{first},\n{to} AS (SELECT * EXCLUDE (w0), {last} AS w0 FROM {to}_e)"

    return f"""
members AS ({members}),
probes AS ({probes}),
size AS (SELECT {addresses_sql(spec, 'n')} AS n_addr FROM (SELECT {n} AS n FROM members)),
{mix_steps_sql('members', 'key', 'mm')},
{mix_steps_sql('probes', 'key', 'pm')},
{entries('mm', 'me')},
stored AS MATERIALIZED (SELECT sub, w0, fp, {sums} AS total FROM me GROUP BY sub, w0, fp {having}),
{entries('pm', 'pe')},
answers AS (SELECT pe.*, total, s.fp IS NOT NULL AS hit FROM pe LEFT JOIN stored s USING (sub, w0, fp))"""


def bloom_ctes(spec: BaselineSpec, members: str, probes: str) -> str:
    """As :func:`signature_ctes`, by sets of positions: a key is found when all of its positions are set."""

    def positions(source: str, to: str) -> str:
        first, step = _hash(spec, "address", "n_addr"), _hash(spec, "offset", "(n_addr - 1)")
        return f"""{to}_e AS (SELECT *, {_hash(spec, 'sub', spec.subs)} AS sub, {first} AS a, 1 + {step} AS b FROM {source}, size),
{to} AS (SELECT {to}_e.*, (a + i * b) % n_addr AS spot FROM {to}_e, range({spec.k}) t(i))"""

    return f"""
members AS ({members}),
probes AS (SELECT row_number() OVER () AS row_id, * FROM ({probes})),
size AS (SELECT {addresses_sql(spec, 'n')} AS n_addr FROM (SELECT count(*) AS n FROM members)),
{mix_steps_sql('members', 'key', 'mm')},
{mix_steps_sql('probes', 'key', 'pm')},
{positions('mm', 'me')},
stored AS MATERIALIZED (SELECT DISTINCT sub, spot FROM me),
{positions('pm', 'pe')},
found AS (SELECT row_id, count(s.spot) = {spec.k} AS hit FROM pe LEFT JOIN stored s USING (sub, spot) GROUP BY row_id),
answers AS (SELECT probes.*, hit FROM probes JOIN found USING (row_id))"""


def blocked_ctes(spec: BaselineSpec, members: str, probes: str) -> str:
    """As :func:`bloom_ctes`, with positions inside one line a key."""

    def positions(source: str, to: str) -> str:
        shift = f"((h::UHUGEINT + CASE i {' '.join(f'WHEN {i} THEN {0x9E3779B97F4A7C15 * (i + 1) & (1 << 64) - 1}::UHUGEINT' for i in range(spec.k))} END) % 18446744073709551616::UHUGEINT)::UBIGINT"
        return f"""{to}_e AS (SELECT * EXCLUDE (h), {_hash(spec, 'sub', spec.subs)} AS sub, {_hash(spec, 'block', 'n_addr')} AS line, {shift} AS key_ FROM {source}, size, range({spec.k}) t(i)),
{mix_steps_sql(f'{to}_e', 'key_', f'{to}_m')},
{to} AS (SELECT *, line * {LINE_BITS} + (h >> 55)::BIGINT AS spot FROM {to}_m)"""

    return f"""
members AS ({members}),
probes AS (SELECT row_number() OVER () AS row_id, * FROM ({probes})),
size AS (SELECT {addresses_sql(spec, 'n')} AS n_addr FROM (SELECT count(*) AS n FROM members)),
{mix_steps_sql('members', 'key', 'mm')},
{mix_steps_sql('probes', 'key', 'pm')},
{positions('mm', 'me')},
stored AS MATERIALIZED (SELECT DISTINCT sub, spot FROM me),
{positions('pm', 'pe')},
found AS (SELECT row_id, count(s.spot) = {spec.k} AS hit FROM pe LEFT JOIN stored s USING (sub, spot) GROUP BY row_id),
answers AS (SELECT probes.*, hit FROM probes JOIN found USING (row_id))"""


def prefix_ctes(spec: BaselineSpec, members: str, probes: str) -> str:
    """As :func:`signature_ctes`: each bin's smallest entries in the bin, the others by their signature in the spare."""
    e, spare = entry_sql(spec), _spare_spec(spec)
    s = entry_sql(spare)
    last = f"least(w0, {other_sql(spare)})" if symmetric(spare) else "w0"

    def in_spare(source: str, to: str, *more: str) -> str:
        """Signatures in the spare of rows with ``own``, ``bin`` and ``fp``."""
        keep = "".join(f", {c}" for c in more)
        return f"""{mix_steps_sql(f"(SELECT own{keep}, bin * {BIN_RANGE} + fp AS k2 FROM {source})", 'k2', f'{to}_1')},
{to}_2a AS (SELECT * EXCLUDE (h), h AS k3 FROM {to}_1),
{to}_3 AS (SELECT own{keep}, k3 AS h, n_spare AS n_addr FROM {to}_2a, size),
{to}_4 AS (SELECT own{keep}, {s['w0']} AS w0, {s['fp']} AS fp, n_addr FROM {to}_3),
{to} AS (SELECT own{keep}, {last} AS spot, fp AS print FROM {to}_4)"""

    return f"""
members AS ({members}),
probes AS (SELECT row_number() OVER () AS row_id, * FROM ({probes})),
size AS (SELECT {addresses_sql(spec, 'n')} AS n_addr, {spare_sql(spec, 'n')} AS n_spare FROM (SELECT count(*) AS n FROM members)),
{mix_steps_sql('members', 'key', 'mm')},
{mix_steps_sql('probes', 'key', 'pm')},
me AS (SELECT DISTINCT {e['sub']} AS own, {e['w0']} AS bin, {e['fp']} AS fp FROM mm, size),
ranked AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY own, bin ORDER BY fp) AS r FROM me),
bins AS (SELECT own, bin, max(r) > {BIN_SLOTS} AS forwards, max(fp) FILTER (r <= {BIN_SLOTS}) AS most FROM ranked GROUP BY own, bin),
over AS (SELECT own, bin, fp FROM ranked WHERE r > {BIN_SLOTS}),
{in_spare('over', 'so')},
spare AS MATERIALIZED (SELECT DISTINCT own, spot, print FROM so),
pe AS MATERIALIZED (SELECT pm.* EXCLUDE (h), {e['sub']} AS own, {e['w0']} AS bin, {e['fp']} AS fp FROM pm, size),
{in_spare('pe', 'sp', 'row_id')},
via AS (SELECT row_id FROM sp SEMI JOIN spare USING (own, spot, print)),
kept AS (SELECT own, bin, fp FROM ranked WHERE r <= {BIN_SLOTS}),
answers AS (
    SELECT pe.* EXCLUDE (fp), CASE WHEN forwards AND pe.fp > most THEN via.row_id IS NOT NULL ELSE kept.fp IS NOT NULL END AS hit
    FROM pe LEFT JOIN bins USING (own, bin) LEFT JOIN kept ON kept.own = pe.own AND kept.bin = pe.bin AND kept.fp = pe.fp LEFT JOIN via USING (row_id)
)"""


def accuracy_sql(members: str, probes: str, specs: list[FilterSpec], log2_ratio: bool = True) -> str:
    """The exact part of the accuracy report of every specification; products of hashes are computed once a key."""
    roles = ("sub", "address", "fingerprint")

    def products(source: str, to: str) -> str:
        return f"{to} AS MATERIALIZED (SELECT {', '.join(f'{product_sql("h", specs[0].factor(r, 3))} AS p_{r}' for r in roles)} FROM {source})"

    base = f"""WITH members AS ({members}), probes AS ({probes}),
c AS (SELECT count(*) AS n FROM members), o AS (SELECT count(*) AS n FROM probes),
{mix_steps_sql('members', 'key', 'mm')},
{mix_steps_sql('probes', 'key', 'pm')},
{products('mm', 'mp')},
{products('pm', 'pp')}"""
    parts = []
    for spec in specs:
        i = f"{spec.name}_{spec.k}"
        entry = f"{reduced_sql('p_sub', spec.subs)} AS sub, {reduced_sql('p_address', 'n_addr')} AS w0, {reduced_sql('p_fingerprint', (1 << spec.fp_bits) - 1)} AS fp"
        slots = f"({slots_sql(spec)} * {spec.subs})"
        base += f""",
z_{i} AS (SELECT {addresses_sql(spec, 'n')} AS n_addr, n FROM c),
s_{i} AS MATERIALIZED (SELECT DISTINCT {entry} FROM mp, z_{i}),
p_{i} AS (SELECT {entry} FROM pp, z_{i})"""
        ratio = f", CASE WHEN positives > 0 THEN round(log2(positives / o.n) + {spec.k}, 6) END AS log2_ratio" if log2_ratio else ""
        parts.append(f"""SELECT '{spec.name}' AS variant, {spec.k} AS k, z_{i}.n AS n_keys, x.n_stored, {slots} AS n_slots,
round(x.n_stored / {slots}, 9) AS load, round(({slots} * {spec.slot_bits}) / (z_{i}.n * {spec.k}), 9) AS overhead,
o.n AS probes, y.positives, 0 AS false_negatives{ratio} FROM z_{i}, o, (SELECT count(*) AS n_stored FROM s_{i}) x, (SELECT count(*) AS positives FROM p_{i} SEMI JOIN s_{i} USING (sub, w0, fp)) y""")
    return base + "\n" + "\nUNION ALL\n".join(parts)


def space_sql(specs: list[Spec], members: str) -> str:
    """``variant, k, status, overhead, false_negatives`` of tables with one subfilter, by the sizes that kinds need."""
    base = f"WITH members AS ({members}), c AS (SELECT count(*) AS n FROM members),\n{mix_steps_sql('members', 'key', 'mm')}"
    parts = []
    for i, spec in enumerate(specs):
        n_addr, source = addresses_sql(spec, "n"), "c"
        if isinstance(spec, FilterSpec):
            bits = f"{slots_sql(spec)} * {spec.slot_bits}"
        elif spec.kind == "quotient":  # the last run may end beyond the last quotient
            e = entry_sql(spec)
            base += f""",
q{i}_z AS (SELECT {n_addr} AS n_addr FROM c),
q{i}_e AS (SELECT DISTINCT {e['w0']} AS q, {e['fp']} AS r FROM mm, q{i}_z),
q{i}_r AS (SELECT q, row_number() OVER (ORDER BY q, r) - 1 AS i FROM q{i}_e),
q{i} AS (SELECT max(slot) + 1 AS used FROM (SELECT i + max(q - i) OVER (ORDER BY i) AS slot FROM q{i}_r))"""
            source, bits = f"c, q{i}", f"(greatest(n_addr, used) + 63) // 64 * 64 * {spec.k + QUOTIENT_META_BITS!r}::DOUBLE"
        elif spec.kind == "prefix":
            spare = spare_sql(spec, "n") + (f" * {LINE_BITS}" if spec.spare == "vector" else " * 4 * 12")
            bits = f"n_addr * {BIN_BITS} + {spare}"
        else:
            unit = {"bloom": 1, "blocked_bloom": LINE_BITS, "choice_bloom": LINE_BITS, "vector_quotient": LINE_BITS, "static_xor": spec.k}[spec.kind]
            bits = f"n_addr * {unit}"
        parts.append(f"SELECT '{spec.name}' AS variant, {spec.k} AS k, 'ok' AS status, round(ceil({bits}) / (n * {spec.k}), 9) AS overhead, 0 AS false_negatives FROM (SELECT *, {n_addr} AS n_addr FROM {source})")
    return base + "\n" + "\nUNION ALL\n".join(parts)


def lines_sql(specs: list[Spec], members: str, line_bits: int = 512) -> str:
    """``variant, k, slot_bits, keys, lines``: distinct lines of the slots at both addresses of each key, summed."""
    base, parts = f"WITH members AS ({members}), c AS (SELECT count(*) AS n FROM members),\n{mix_steps_sql('members', 'key', 'mm')}", []
    for spec in specs:
        i = f"{spec.name}_{spec.k}"
        if isinstance(spec, BaselineSpec):
            first, step = (_hash(spec, role, b) for role, b in (("address", "n_addr"), ("offset", "(n_addr - 1)")))
            lines = {
                "bloom": f"len(list_distinct([{', '.join(f'({first} + {j} * (1 + {step})) % n_addr // {line_bits}' for j in range(spec.k))}]))",
                "blocked_bloom": "1",
                "choice_bloom": f"1 + ({_hash(spec, 'block', 'n_addr')} <> {_hash(spec, 'extra', 'n_addr')})::INTEGER",
                "vector_quotient": "2",  # the other block is never the first
            }[spec.kind]
            parts.append(f"SELECT '{spec.name}' AS variant, {spec.k} AS k, 0 AS slot_bits, count(*) AS keys, sum({lines})::BIGINT AS lines FROM mm, (SELECT {addresses_sql(spec, 'n')} AS n_addr FROM c)")
            continue
        e, step = entry_sql(spec), _hash(spec, "offset", "(n_addr - 1)", "fp::UBIGINT")
        slot = lambda at: f"({at} * {spec.slot_bits * (1 if spec.layout == 'window' else spec.l)})"
        ends = [f"{slot(at)} // {line_bits}" for at in ("w0", "w1")] + [f"({slot(at)} + {spec.l * spec.slot_bits - 1}) // {line_bits}" for at in ("w0", "w1")]
        base += f""",
a_{i} AS (SELECT n_addr, {e['w0']} AS w0, {e['fp']} AS fp FROM mm, (SELECT {addresses_sql(spec, 'n')} AS n_addr FROM c)),
b_{i} AS (SELECT w0, (w0 + 1 + {step}) % n_addr AS w1 FROM a_{i})"""
        parts.append(f"SELECT '{spec.name}' AS variant, {spec.k} AS k, {spec.slot_bits} AS slot_bits, count(*) AS keys, sum(len(list_distinct([{', '.join(ends)}])))::BIGINT AS lines FROM b_{i}")
    return base + "\n" + "\nUNION ALL\n".join(parts)
