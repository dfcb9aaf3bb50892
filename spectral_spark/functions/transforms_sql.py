"""Dense transforms and solves as plain SQL: sums over basis functions, quadratic per line, the same text in any engine.

A basis table has a row per mode and point: (m, j, b, w, o) with the function's value, its projection weight and its
frequency. Projecting a line is sum(v * b * w), and summing coefficient * b gives it back.
"""

from __future__ import annotations

#: Per transform: first and last mode, first and last point (in intervals n), value at k, j, and the weight of end points.
_KINDS = {
    "dct1": ("0", "{n}", "0", "{n}", "cos(pi() * k * j / {n})", "CASE WHEN j = 0 OR j = {n} THEN 1.0 ELSE 2.0 END"),
    "dct2": ("0", "{n} - 1", "0", "{n} - 1", "cos(pi() * k * (j + 0.5) / {n})", "2.0"),
    "dct3": ("0", "{n} - 1", "0", "{n} - 1", "cos(pi() * (k + 0.5) * j / {n})", "CASE WHEN j = 0 THEN 1.0 ELSE 2.0 END"),
    "dct4": ("0", "{n} - 1", "0", "{n} - 1", "cos(pi() * (k + 0.5) * (j + 0.5) / {n})", "2.0"),
    "dst1": ("1", "{n} - 1", "1", "{n} - 1", "sin(pi() * k * j / {n})", "2.0"),
    "dst2": ("1", "{n}", "0", "{n} - 1", "sin(pi() * k * (j + 0.5) / {n})", "2.0"),
    "dst3": ("0", "{n} - 1", "1", "{n}", "sin(pi() * (k + 0.5) * j / {n})", "CASE WHEN j = {n} THEN 1.0 ELSE 2.0 END"),
    "dst4": ("0", "{n} - 1", "0", "{n} - 1", "sin(pi() * (k + 0.5) * (j + 0.5) / {n})", "2.0"),
}


def _numbers(lo: str, hi: str, name: str) -> str:
    """DuckDB's range; Spark has the same function under another signature, see ``dense``."""
    return f"(SELECT CAST(range AS BIGINT) AS {name} FROM range({lo}, {hi} + 1))"


def dense(kind: str, view: str, n: int, key: str = "key", spark: bool = False) -> str:
    """``view(key, j, v)``, one row per line and point, to (key, k, y): the un-normalised forward sum of a kind, or of
    ``dft_re`` / ``dft_im``."""
    if kind.startswith("dft"):
        lo, hi, plo, phi = "0", f"{n} / 2" if spark else f"{n} // 2", "0", f"{n} - 1"
        value, weight = (f"cos(2 * pi() * k * j / {n})" if kind == "dft_re" else f"-sin(2 * pi() * k * j / {n})"), "1.0"
    else:
        lo, hi, plo, phi, value, weight = (s.format(n=n) for s in _KINDS[kind])
    modes = f"(SELECT id AS k FROM range({lo}, CAST({hi} + 1 AS BIGINT)))" if spark else _numbers(lo, hi, "k")
    return f"SELECT {key}, k, sum(v * ({weight}) * {value}) AS y FROM {view} CROSS JOIN {modes} AS modes WHERE j BETWEEN {plo} AND {phi} GROUP BY {key}, k"


def basis(kind: str, n: int, h: float) -> str:
    """A complete basis of a cell-centred line: ``ee``, ``oo``, ``oe``, ``eo`` (left, right parity) or ``pp``."""
    m, j, length = _numbers("0", f"{n} - 1", "m"), _numbers("0", f"{n} - 1", "j"), n * h
    at = f"(j + 0.5) / {n}.0"
    if kind == "pp":
        half = n // 2
        k = f"(CASE WHEN m < {half} THEN m ELSE m - {half} + 1 END)"
        b = f"CASE WHEN m < {half} THEN cos(2 * pi() * {k} * {at}) ELSE sin(2 * pi() * {k} * {at}) END"
        w, o = f"CASE WHEN m = 0 OR {k} = {half} THEN 1.0 ELSE 2.0 END / {n}", f"2 * pi() * {k} / {length!r}"
    else:
        k = {"ee": "m", "oo": "(m + 1)", "oe": "(m + 0.5)", "eo": "(m + 0.5)"}[kind]
        b = f"{'cos' if kind[0] == 'e' else 'sin'}(pi() * {k} * {at})"
        one = {"ee": "m = 0", "oo": f"m = {n - 1}"}.get(kind, "false")
        w, o = f"CASE WHEN {one} THEN 1.0 ELSE 2.0 END / {n}", f"pi() * {k} / {length!r}"
    return f"SELECT m, j, {b} AS b, {w} AS w, {o} AS o FROM {m} AS mm CROSS JOIN {j} AS jj"


def dense_solve_3d(cells: str, kinds: tuple[str, str, str], n: int, h: float, factor: str, out_kinds: tuple[str, str, str] | None = None) -> str:
    """(ix, iy, iz, v) of sum over modes of coefficient * ``factor`` * basis; ``factor`` is in ox, oy, oz. With ``out_kinds`` the
    functions that are summed differ from those projected on (a derivative turns sines into cosines of the same mode)."""
    out_kinds = out_kinds or kinds
    with_ = [f"f AS ({cells})"]
    for a, kind, out in zip("xyz", kinds, out_kinds):
        with_ += [f"from_{a} AS ({basis(kind, n, h)})", f"to_{a} AS ({_derived(kind, out, n, h)})"]
    omega = " ".join(f"JOIN (SELECT DISTINCT m, o AS o{a} FROM from_{a}) q{a} ON q{a}.m = m{a}" for a in "xyz")
    with_ += [
        "c1 AS (SELECT m AS mx, iy, iz, sum(v * b * w) AS c FROM f JOIN from_x ON j = ix GROUP BY m, iy, iz)",
        "c2 AS (SELECT mx, m AS my, iz, sum(c * b * w) AS c FROM c1 JOIN from_y ON j = iy GROUP BY mx, m, iz)",
        "c3 AS (SELECT mx, my, m AS mz, sum(c * b * w) AS c FROM c2 JOIN from_z ON j = iz GROUP BY mx, my, m)",
        f"g AS (SELECT mx, my, mz, c * ({factor}) AS c FROM c3 {omega})",
        "d1 AS (SELECT mx, my, j AS iz, sum(c * b) AS c FROM g JOIN to_z ON to_z.m = mz GROUP BY mx, my, j)",
        "d2 AS (SELECT mx, j AS iy, iz, sum(c * b) AS c FROM d1 JOIN to_y ON to_y.m = my GROUP BY mx, j, iz)",
    ]
    return "WITH " + ",\n".join(with_) + "\nSELECT j AS ix, iy, iz, sum(c * b) AS v FROM d2 JOIN to_x ON to_x.m = mx GROUP BY j, iy, iz"


def _derived(kind: str, out: str, n: int, h: float) -> str:
    if kind == out:
        return basis(kind, n, h)
    k = {"ee": "m", "oo": "(m + 1)", "oe": "(m + 0.5)", "eo": "(m + 0.5)"}[kind]
    return f"SELECT m, j, {'cos' if out[0] == 'e' else 'sin'}(pi() * {k} * (j + 0.5) / {n}.0) AS b FROM {_numbers('0', f'{n} - 1', 'm')} AS mm CROSS JOIN {_numbers('0', f'{n} - 1', 'j')} AS jj"


def spectral_factor(kernel: str, h: float) -> str:
    """The closed-form kernel in ox, oy, oz as SQL."""
    k2 = "(ox * ox + oy * oy + oz * oz)"
    if kernel == "lattice":
        base = "(" + " + ".join(f"pow(sin(o{a} * {h / 2!r}), 2) * {4 / h**2!r}" for a in "xyz") + ")"
        return f"CASE WHEN {base} > 0 THEN -1.0 / {base} ELSE 0.0 END"
    g = f"CASE WHEN {k2} > 0 THEN -1.0 / {k2} ELSE 0.0 END"
    if kernel.startswith("gauss"):
        q, terms, f = f"({k2} * {(2 * h) ** 2 / 2!r})", ["1.0"], 1
        for j in range(1, int(kernel[5:]) // 2):
            f *= j
            terms.append(f"pow({q}, {j}) / {f}.0")
        return f"({g}) * exp(-{q}) * ({' + '.join(terms)})"
    if kernel == "cutoff":
        return f"CASE WHEN {k2} < pow(pi() / {h!r}, 2) THEN {g} ELSE 0.0 END"
    return g
