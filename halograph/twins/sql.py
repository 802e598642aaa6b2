"""Builders of common table expressions. Each function returns a list of (name, body)."""

from __future__ import annotations

from halograph.functions.ring import PRIME
from halograph.sources.systems import LATTICE_SPACING, QUARTZ_CELL, QUARTZ_LONG, QUARTZ_SITES

Ctes = list[tuple[str, str]]


def select(ctes: Ctes, body: str) -> str:
    seen = dict(ctes)
    recursive = "RECURSIVE " if any(c.startswith("/*recursive*/") for c in seen.values()) else ""
    # edges are costly and read often: once is enough
    once = lambda n: "MATERIALIZED " if n.startswith(("edges", "line", "atoms", "owned", "halo", "xs", "wide_parts", "both_ends", "crossed")) else ""
    return f"WITH {recursive}" + ",\n".join(f"{n} AS {once(n)}({b})" for n, b in seen.items()) + f"\n{body}"


def quartz() -> Ctes:
    sites = ", ".join(str(s) for s in QUARTZ_SITES)
    lx, ly, lz = QUARTZ_CELL
    return [
        ("keys", "SELECT coalesce(max(o_orderkey), -1) + 1 AS n FROM orders"),
        ("wide", f"SELECT n, greatest(2, (SELECT max(i) FROM range(2000) r(i) WHERE i * i * i <= n // {QUARTZ_LONG})) AS width FROM keys"),
        ("size", "SELECT greatest(2, (n + 18 * width * width - 1) // (18 * width * width)) AS nx, width AS ny, width AS nz FROM wide"),
        ("cell", f"SELECT nx * {lx} AS lx, ny * {ly} AS ly, nz * {lz} AS lz FROM size"),
        ("basis", f"SELECT * FROM (VALUES {sites}) AS t(site, species, bx, b_y, bz)"),
        (
            "atoms",
            f"SELECT o_orderkey AS atom_id, species, (o_orderkey // 18 // (ny * nz)) * {lx} + bx AS x, (o_orderkey // 18 // nz % ny) * {ly} + b_y AS y, (o_orderkey // 18 % nz) * {lz} + bz AS z"
            " FROM orders, size JOIN basis ON site = o_orderkey % 18",
        ),
    ]


def cloud() -> Ctes:
    at = lambda i: f"CAST(floor(CAST(embedding[{i}] AS DOUBLE) * 1000) AS BIGINT)"
    return [("cell", "SELECT 2000 AS lx, 2000 AS ly, 2000 AS lz"), ("atoms", f"SELECT vec_id AS atom_id, label AS species, {at(1)} AS x, {at(2)} AS y, {at(3)} AS z FROM embeddings")]


def liquid() -> Ctes:
    order = "l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate"
    return [
        ("cell", "SELECT 1 AS lx, 1 AS ly, 1 AS lz"),
        (
            "atoms",
            f"SELECT l_orderkey * 64 + row_number() OVER (PARTITION BY l_orderkey ORDER BY {order}) AS atom_id, ascii(l_returnflag) * 2 + (l_linestatus = 'O')::INT AS species,"
            " date_diff('day', DATE '1995-01-01', l_shipdate::DATE) * (SELECT greatest(1, count(*) // 600) FROM lineitem) AS x, CAST(floor(l_quantity * 400) AS BIGINT) AS y, CAST(floor(l_extendedprice / 5) AS BIGINT) AS z"
            " FROM lineitem",
        ),
    ]


def lattice(width: int | None = None) -> Ctes:
    s = str(width) if width else "(SELECT greatest(1, max(i)) FROM range(2000) r(i) WHERE i * i * i <= n)"
    return [
        ("span", "SELECT min(p_partkey) AS low, max(p_partkey) - min(p_partkey) + 1 AS n FROM part"),
        ("side", f"SELECT {s} AS m, low, n FROM span"),
        ("cell", f"SELECT (n + m * m - 1) // (m * m) * {LATTICE_SPACING} AS lx, m * {LATTICE_SPACING} AS ly, m * {LATTICE_SPACING} AS lz FROM side"),
        ("keys", "SELECT p_partkey - low AS k, m FROM part, side"),
        ("atoms", f"SELECT k AS atom_id, CAST((k // (m * m) + k // m % m + k % m) % 2 AS INT) AS species, (k // (m * m)) * {LATTICE_SPACING} AS x, (k // m % m) * {LATTICE_SPACING} AS y, (k % m) * {LATTICE_SPACING} AS z FROM keys"),
    ]


def successor() -> Ctes:
    return [
        ("atoms", "SELECT p_partkey AS atom_id, CAST(p_size AS INT) AS species FROM part"),
        ("steps", "SELECT l_partkey AS src, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_partkey) AS dst FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem)"),
        ("edges", "SELECT src, dst, 0 AS ix, 0 AS iy, 0 AS iz, 0 AS dx, 0 AS dy, 0 AS dz, 0 AS d2, count(*) AS w FROM steps WHERE dst IS NOT NULL GROUP BY src, dst"),
    ]


def chain() -> Ctes:
    return [
        ("atoms", "SELECT conv_id * 1024 + turn AS atom_id, CAST(length(role) AS INT) AS species FROM conversations"),
        ("steps", "SELECT conv_id * 1024 + turn AS src, conv_id * 1024 + lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM conversations"),
        ("edges", "SELECT src, dst, 0 AS ix, 0 AS iy, 0 AS iz, 0 AS dx, 0 AS dy, 0 AS dz, 0 AS d2, 1 AS w FROM steps WHERE dst IS NOT NULL"),
    ]


def explicit(nodes: str, steps: str) -> Ctes:
    return [("atoms", nodes), ("steps", steps), ("edges", "SELECT src, dst, 0 AS ix, 0 AS iy, 0 AS iz, 0 AS dx, 0 AS dy, 0 AS dz, 0 AS d2, 1 AS w FROM steps")]


def hub() -> Ctes:
    return explicit(
        "SELECT r_regionkey::BIGINT * 4 AS atom_id, 0 AS species FROM region UNION ALL SELECT n_nationkey::BIGINT * 4 + 1, 1 FROM nation UNION ALL SELECT s_suppkey * 4 + 2, 2 FROM supplier UNION ALL SELECT c_custkey * 4 + 3, 3 FROM customer",
        "SELECT c_custkey * 4 + 3 AS src, c_nationkey::BIGINT * 4 + 1 AS dst FROM customer UNION ALL SELECT s_suppkey * 4 + 2, s_nationkey::BIGINT * 4 + 1 FROM supplier UNION ALL SELECT n_nationkey::BIGINT * 4 + 1, n_regionkey::BIGINT * 4 FROM nation",
    )


def clusters() -> Ctes:
    return [("next_of", "SELECT doc_id AS src, lead(doc_id) OVER (PARTITION BY text ORDER BY doc_id) AS dst FROM documents")] + explicit(
        "SELECT doc_id AS atom_id, CAST(coalesce(1 + quality + 2 * toxic, 0) AS INT) AS species FROM documents LEFT JOIN labels USING (doc_id)",
        "SELECT src, dst FROM next_of WHERE dst IS NOT NULL UNION ALL SELECT dst, src FROM next_of WHERE dst IS NOT NULL",
    )


def sites() -> Ctes:
    host = "regexp_extract(url, '^[a-z]+://([^/]+)', 1)"
    return [("hosts", f"SELECT page_id, {host} AS host FROM pages")] + explicit(
        "SELECT page_id AS atom_id, CAST(length(host) AS INT) AS species FROM hosts", "SELECT a.page_id AS src, b.page_id AS dst FROM hosts a JOIN hosts b ON a.host = b.host AND a.page_id <> b.page_id"
    )


def edges(cutoff: int, periodic: bool = True, weight: str = "ring") -> Ctes:
    """Every pair whose slabs along x touch; the nearest image of each, so boxes must be twice the cutoff wide, and three
    slabs of the cutoff long."""
    image = lambda a: f"CASE WHEN 2 * (s.{a} - t.{a}) > l{a} THEN -1 WHEN 2 * (s.{a} - t.{a}) < -l{a} THEN 1 ELSE 0 END" if periodic else "0"
    pairs = ", ".join([f"{image(a)} AS i{a}" for a in "xyz"] + [f"s.{a} - t.{a} AS r{a}" for a in "xyz"])
    n = f"(lx // {cutoff})"
    slab = f"least(x * {n} // lx, {n} - 1)" if periodic else f"CAST(floor(x / {cutoff}.0) AS BIGINT)"
    beside = f"(b + k + {n}) % {n}" if periodic else "b + k"
    return [
        ("slabs", f"SELECT a.*, {slab} AS b FROM atoms a, cell"),
        ("around", f"SELECT a.*, {beside} AS c FROM slabs a, cell, (VALUES (-1), (0), (1)) t(k)"),
        ("pairs", f"SELECT s.atom_id AS src, t.atom_id AS dst, {pairs}, lx, ly, lz FROM around s JOIN slabs t ON s.c = t.b AND s.atom_id <> t.atom_id, cell"),
        ("moved", "SELECT src, dst, ix, iy, iz, rx + ix * lx AS dx, ry + iy * ly AS dy, rz + iz * lz AS dz FROM pairs"),
        ("near", f"SELECT *, dx * dx + dy * dy + dz * dz AS d2 FROM moved WHERE abs(dx) <= {cutoff} AND abs(dy) <= {cutoff} AND abs(dz) <= {cutoff} AND dx * dx + dy * dy + dz * dz <= {cutoff * cutoff}"),
        ("edges", f"SELECT *, {weight_of(cutoff, weight)} AS w FROM near"),
    ]


def rod_edges(cutoff: int, reach: int) -> Ctes:
    """A box narrower than the cutoff along y and z, whose images are all listed there; along x slabs of the cutoff meet."""
    shifts = f"generate_series(-{reach}, {reach})"
    return [
        ("images", f"SELECT b.i AS iy, c.i AS iz FROM {shifts} b(i), {shifts} c(i)"),
        ("slabs", f"SELECT a.*, least(x * (lx // {cutoff}) // lx, lx // {cutoff} - 1) AS b FROM atoms a, cell"),
        ("around", f"SELECT a.*, (b + k + lx // {cutoff}) % (lx // {cutoff}) AS c FROM slabs a, cell, (VALUES (-1), (0), (1)) t(k)"),
        ("pairs", "SELECT s.atom_id AS src, t.atom_id AS dst, CASE WHEN 2 * (s.x - t.x) > lx THEN -1 WHEN 2 * (s.x - t.x) < -lx THEN 1 ELSE 0 END AS ix, s.x - t.x AS rx, s.y - t.y AS ry, s.z - t.z AS rz, lx, ly, lz FROM around s JOIN slabs t ON s.c = t.b, cell"),
        ("moved", "SELECT src, dst, ix, iy, iz, rx + ix * lx AS dx, ry + iy * ly AS dy, rz + iz * lz AS dz FROM pairs, images"),
        ("edges", f"SELECT *, dx * dx + dy * dy + dz * dz AS d2 FROM moved WHERE dx * dx + dy * dy + dz * dz <= {cutoff * cutoff} AND (src <> dst OR ix <> 0 OR iy <> 0 OR iz <> 0)"),
    ]


def weight_of(cutoff: int, kind: str) -> str:
    c = cutoff * cutoff
    if kind == "smooth":
        gap = f"(({c} - d2) // 1000 % {PRIME})"
        return f"({gap} * {gap} % {PRIME})"
    return f"(({c} - d2) * 16 // {c})"


def walls(p: int, axis: str = "x") -> Ctes:
    return [("assign", f"SELECT atom_id, CAST(greatest(0, least({p - 1}, {axis} * {p} // l{axis})) AS INT) AS part_id FROM atoms, cell")]


def id_walls(p: int) -> Ctes:
    return [
        ("bounds", "SELECT min(atom_id) AS low, max(atom_id) - min(atom_id) + 1 AS length FROM atoms"),
        ("assign", f"SELECT atom_id, CAST(greatest(0, least({p - 1}, (atom_id - low) * {p} // length)) AS INT) AS part_id FROM atoms, bounds"),
    ]


def owners() -> Ctes:
    return [("owned", "SELECT e.*, s.part_id AS p_src, t.part_id AS part_id FROM edges e JOIN assign s ON s.atom_id = e.src JOIN assign t ON t.atom_id = e.dst"), ("halo", "SELECT DISTINCT part_id, src AS atom_id, 1 AS hop, p_src AS owner FROM owned WHERE p_src <> part_id")]


def buckets() -> Ctes:
    return [
        (
            "buckets",
            "SELECT part_id, 'PURE' AS kind, part_id AS peer, atom_id FROM assign WHERE atom_id NOT IN (SELECT atom_id FROM halo)"
            " UNION ALL SELECT owner, 'TO', part_id, atom_id FROM halo UNION ALL SELECT part_id, 'FROM', owner, atom_id FROM halo",
        )
    ]


def part_counts() -> Ctes:
    """part_id, n nodes, h border nodes, e edges of every part."""
    n = lambda t: f"(SELECT part_id, count(*) AS c FROM {t} GROUP BY part_id)"
    return [("counts", f"SELECT part_id, a.c AS n, coalesce(h.c, 0) AS h, coalesce(e.c, 0) AS e FROM {n('assign')} a LEFT JOIN {n('halo')} h USING (part_id) LEFT JOIN {n('owned')} e USING (part_id)")]


def line(bond_cutoff: int | None = None) -> Ctes:
    where = f"WHERE d2 <= {bond_cutoff * bond_cutoff}" if bond_cutoff is not None else ""
    keys = ", ".join(f"{s}.{c} AS {s}_{c}" for s in "fe" for c in ("src", "dst", "ix", "iy", "iz"))
    return [
        ("bonds", f"SELECT * FROM edges {where}"),
        ("line", f"SELECT {keys}, f.dst AS center, f.dx * e.dx + f.dy * e.dy + f.dz * e.dz AS dot FROM bonds f JOIN bonds e ON f.dst = e.src WHERE NOT (f.src = e.dst AND f.ix = -e.ix AND f.iy = -e.iy AND f.iz = -e.iz)"),
    ]


def init(width: int = 1, smooth: bool = False) -> Ctes:
    scale = f" * (n % {PRIME}) % {PRIME}" if smooth else ""
    counts = " JOIN (SELECT species, count(*) AS n FROM atoms GROUP BY species) USING (species)" if smooth else ""
    return [("s0", "SELECT atom_id, species, " + ", ".join(f"((1 + species) * {c + 1} % {PRIME}){scale} AS h{c}" for c in range(width)) + f" FROM atoms{counts}")]


def ring_layer(k: int, width: int = 1, update: str = "h + a") -> Ctes:
    """State k from state k - 1; ``update`` is written in h and the reduced message sum a."""
    sums = ", ".join(f"sum(w * h{c}) % {PRIME} AS a{c}" for c in range(width))
    new = ", ".join("CAST((" + update.replace("h", f"s.h{c}").replace("a", f"coalesce(a{c}, 0)") + f") % {PRIME} AS BIGINT) AS h{c}" for c in range(width))
    return [
        (f"m{k}", f"SELECT dst AS atom_id, {sums} FROM edges JOIN s{k - 1} ON s{k - 1}.atom_id = src GROUP BY dst"),
        (f"s{k}", f"SELECT s.atom_id, s.species, {new} FROM s{k - 1} s LEFT JOIN m{k} USING (atom_id)"),
    ]


def ring(layers: int, width: int = 1, update: str = "h + a") -> Ctes:
    out = init(width)
    for k in range(1, layers + 1):
        out += ring_layer(k, width, update)
    return out


def many_body_update(nu: int) -> str:
    """h + a + a^2 + ... with each power reduced; a stays below the prime, so no product passes 64 bits."""
    power, total = "a", "h + a"
    for _ in range(nu - 1):
        power = f"({power} * a % {PRIME})"
        total += f" + {power}"
    return total


def light(layers: int, smooth: bool = False) -> Ctes:
    out = init(1, smooth)
    out.append(("v0", "SELECT atom_id, species, h0, 0 AS vx, 0 AS vy, 0 AS vz FROM s0"))
    pm = lambda x: f"((({x}) % {PRIME} + {PRIME}) % {PRIME})"
    for k in range(1, layers + 1):
        vs = ", ".join(f"{pm(f'sum({pm(f'(w * h0 % {PRIME}) * d{a}')} + w * v{a})')} AS m{a}" for a in "xyz")
        out.append((f"g{k}", f"SELECT dst AS atom_id, sum(w * h0) % {PRIME} AS mh, {vs} FROM edges JOIN v{k - 1} ON v{k - 1}.atom_id = src GROUP BY dst"))
        out.append((f"u{k}", f"SELECT v.atom_id, species, h0, coalesce(mh, 0) AS mh, " + ", ".join(f"CAST((v{a} + coalesce(m{a}, 0)) % {PRIME} AS BIGINT) AS v{a}" for a in "xyz") + f" FROM v{k - 1} v LEFT JOIN g{k} USING (atom_id)"))
        out.append((f"v{k}", f"SELECT atom_id, species, CAST((h0 + mh + vx * vx % {PRIME} + vy * vy % {PRIME} + vz * vz % {PRIME}) % {PRIME} AS BIGINT) AS h0, vx, vy, vz FROM u{k}"))
    return out


def invariant_bond(layers: int) -> Ctes:
    """Over edges and line; w of a bond is that of its edge."""
    key = ("src", "dst", "ix", "iy", "iz")
    on = lambda a, b, pre: " AND ".join(f"{a}.{c} = {b}.{pre}_{c}" for c in key)
    pm = lambda x: f"((({x}) % {PRIME} + {PRIME}) % {PRIME})"
    out = init() + [("b0", f"SELECT {', '.join(key)}, w % {PRIME} AS b FROM bonds")]
    for k in range(1, layers + 1):
        out.append((f"q{k}", f"SELECT {', '.join(f'e_{c}' for c in key)}, sum({pm('dot')} * b % {PRIME}) % {PRIME} AS a FROM line JOIN b{k - 1} p ON {on('p', 'line', 'f')} GROUP BY ALL"))
        out.append((f"b{k}", f"SELECT {', '.join(f'p.{c}' for c in key)}, CAST((b + coalesce(a, 0)) % {PRIME} AS BIGINT) AS b FROM b{k - 1} p LEFT JOIN q{k} q ON {on('p', 'q', 'e')}"))
        out.append((f"c{k}", f"SELECT dst AS atom_id, sum(b) AS t FROM b{k} GROUP BY dst"))
        out.append((f"m{k}", f"SELECT dst AS atom_id, sum(w * h0) AS a FROM edges JOIN s{k - 1} ON s{k - 1}.atom_id = src GROUP BY dst"))
        out.append((f"s{k}", f"SELECT s.atom_id, s.species, CAST((s.h0 + coalesce(a, 0) + coalesce(t, 0)) % {PRIME} AS BIGINT) AS h0 FROM s{k - 1} s LEFT JOIN m{k} USING (atom_id) LEFT JOIN c{k} USING (atom_id)"))
    return out


def ring_forces(layers: int, slope: str = "1") -> Ctes:
    """Reverse pass over s0 ... and m1 ...; ``slope`` is the update's derivative in the message sum a."""
    out: Ctes = [(f"r{layers}", f"SELECT atom_id, 1 AS g FROM s{layers}")]
    for k in range(layers, 0, -1):
        steep = slope.replace("a", "coalesce(a0, 0)")
        out.append((f"t{k}", f"SELECT r.atom_id, ({steep}) % {PRIME} * g % {PRIME} AS t FROM r{k} r LEFT JOIN m{k} USING (atom_id)"))
        out.append((f"o{k}", f"SELECT src, dst, ix, iy, iz, dx, dy, dz, w * t % {PRIME} AS back, h0 * t % {PRIME} AS q FROM edges JOIN t{k} ON t{k}.atom_id = dst JOIN s{k - 1} ON s{k - 1}.atom_id = src"))
        out.append((f"r{k - 1}", f"SELECT r.atom_id, CAST((g + coalesce(b, 0)) % {PRIME} AS BIGINT) AS g FROM r{k} r LEFT JOIN (SELECT src AS atom_id, sum(back) AS b FROM o{k} GROUP BY src) USING (atom_id)"))
    every = " UNION ALL ".join(f"SELECT src, dst, ix, iy, iz, dx, dy, dz, q FROM o{k}" for k in range(1, layers + 1))
    out.append(("q", f"SELECT src, dst, dx, dy, dz, CAST(sum(q) AS BIGINT) AS q FROM ({every}) GROUP BY src, dst, ix, iy, iz, dx, dy, dz"))
    out.append(("pulls", "SELECT src AS atom_id, q * dx AS fx, q * dy AS fy, q * dz AS fz FROM q UNION ALL SELECT dst, -q * dx, -q * dy, -q * dz FROM q"))
    out.append(("forces", "SELECT atom_id, CAST(coalesce(sum(fx), 0) AS BIGINT) AS fx, CAST(coalesce(sum(fy), 0) AS BIGINT) AS fy, CAST(coalesce(sum(fz), 0) AS BIGINT) AS fz FROM atoms LEFT JOIN pulls USING (atom_id) GROUP BY atom_id"))
    return out


def _pm(x: str) -> str:
    return f"((({x}) % {PRIME} + {PRIME}) % {PRIME})"


KEY = "src, dst, ix, iy, iz"
TOTALS = ("forces", "SELECT atom_id, CAST(coalesce(sum(fx), 0) AS BIGINT) AS fx, CAST(coalesce(sum(fy), 0) AS BIGINT) AS fy, CAST(coalesce(sum(fz), 0) AS BIGINT) AS fz FROM atoms LEFT JOIN pulls USING (atom_id) GROUP BY atom_id")


def light_forces(layers: int, cutoff: int, smooth: bool = False) -> Ctes:
    """Reverse pass over v0 ... and u1 ... of a model of one channel."""
    out: Ctes = [(f"r{layers}", f"SELECT atom_id, 1 AS gh, 0 AS gx, 0 AS gy, 0 AS gz FROM v{layers}")]
    for k in range(layers, 0, -1):
        sides = ", ".join(_pm(f"g{a} + 2 * (v{a} * gh % {PRIME})") + f" AS s{a}" for a in "xyz")
        out.append((f"t{k}", f"SELECT r.atom_id, gh AS sh, {sides} FROM r{k} r JOIN u{k} USING (atom_id)"))
        turned = " + ".join(_pm(f"w * d{a}") + f" * s{a} % {PRIME}" for a in "xyz")
        q = " + ".join(_pm(_pm(f"h0 * d{a}") + f" + v{a}") + f" * s{a} % {PRIME}" for a in "xyz")
        moved = ", ".join(f"w * s{a} % {PRIME} AS back{a}, (w * h0 % {PRIME}) * s{a} % {PRIME} AS p{a}" for a in "xyz")
        out.append((f"o{k}", f"SELECT {KEY}, dx, dy, dz, d2, (w * sh % {PRIME} + {turned}) % {PRIME} AS bh, (h0 * sh % {PRIME} + {q}) % {PRIME} AS q, {moved} FROM edges JOIN t{k} ON t{k}.atom_id = dst JOIN v{k - 1} ON v{k - 1}.atom_id = src"))
        back = f"(SELECT src AS atom_id, sum(bh) AS bh, sum(backx) AS backx, sum(backy) AS backy, sum(backz) AS backz FROM o{k} GROUP BY src)"
        news = f"CAST((t.sh + coalesce(bh, 0)) % {PRIME} AS BIGINT) AS gh, " + ", ".join(f"CAST((s{a} + coalesce(back{a}, 0)) % {PRIME} AS BIGINT) AS g{a}" for a in "xyz")
        out.append((f"r{k - 1}", f"SELECT t.atom_id, {news} FROM t{k} t LEFT JOIN {back} USING (atom_id)"))
    c = cutoff * cutoff
    pull = lambda a: f"q * (({c} - d2) // 1000 % {PRIME}) % {PRIME} * d{a} - 250 * p{a}" if smooth else f"32 * q * d{a} - {c} * p{a}"
    every = " UNION ALL ".join(f"SELECT src, dst, {', '.join(f'{pull(a)} AS f{a}' for a in 'xyz')} FROM o{k}" for k in range(1, layers + 1))
    out.append(("pulled", every))
    out.append(("pulls", "SELECT src AS atom_id, fx, fy, fz FROM pulled UNION ALL SELECT dst, -fx, -fy, -fz FROM pulled"))
    return [*out, TOTALS]


def bond_forces(layers: int, cutoff: int) -> Ctes:
    """Reverse pass over s0 ..., b0 ... and line of the model with bonds."""
    key = ("src", "dst", "ix", "iy", "iz")
    on = lambda a, b, pre: " AND ".join(f"{a}.{c} = {b}.{pre}_{c}" for c in key)
    named = lambda pre: ", ".join(f"{pre}_{c}" for c in key)
    c2 = cutoff * cutoff
    out: Ctes = [(f"r{layers}", f"SELECT atom_id, 1 AS g FROM s{layers}"), (f"e{layers}", f"SELECT {KEY}, 0 AS gb FROM bonds")]
    pulls = []
    for k in range(layers, 0, -1):
        out.append((f"x{k}", f"SELECT {KEY}, CAST((gb + g) % {PRIME} AS BIGINT) AS gb FROM e{k} JOIN r{k} ON r{k}.atom_id = dst"))
        out.append((f"y{k}", f"SELECT {named('f')}, {named('e')}, {_pm('dot')} * gb % {PRIME} AS back, b * gb % {PRIME} AS slope FROM line JOIN x{k} x ON {on('x', 'line', 'e')} JOIN b{k - 1} p ON {on('p', 'line', 'f')}"))
        out.append((f"e{k - 1}", f"SELECT {', '.join(f'x.{c}' for c in key)}, CAST((gb + coalesce(t, 0)) % {PRIME} AS BIGINT) AS gb FROM x{k} x LEFT JOIN (SELECT {named('f')}, sum(back) AS t FROM y{k} GROUP BY ALL) y ON {on('x', 'y', 'f')}"))
        out.append((f"o{k}", f"SELECT src, dst, dx, dy, dz, w * g % {PRIME} AS back, h0 * g % {PRIME} AS q FROM edges JOIN r{k} ON r{k}.atom_id = dst JOIN s{k - 1} ON s{k - 1}.atom_id = src"))
        out.append((f"r{k - 1}", f"SELECT r.atom_id, CAST((g + coalesce(b, 0)) % {PRIME} AS BIGINT) AS g FROM r{k} r LEFT JOIN (SELECT src AS atom_id, sum(back) AS b FROM o{k} GROUP BY src) USING (atom_id)"))
        turned = ", ".join(f"{c2} * {_pm(f'slope * e.d{a}')} AS u{a}, {c2} * {_pm(f'slope * f.d{a}')} AS w{a}" for a in "xyz")
        out.append((f"z{k}", f"SELECT f.src AS a, f.dst AS b, e.dst AS c, {turned} FROM y{k} y JOIN bonds f ON {on('f', 'y', 'f')} JOIN bonds e ON {on('e', 'y', 'e')}"))
        pulls.append(f"SELECT src AS atom_id, 32 * q * dx AS fx, 32 * q * dy AS fy, 32 * q * dz AS fz FROM o{k} UNION ALL SELECT dst, -32 * q * dx, -32 * q * dy, -32 * q * dz FROM o{k}")
        pulls.append(f"SELECT a, -ux, -uy, -uz FROM z{k} UNION ALL SELECT b, ux - wx, uy - wy, uz - wz FROM z{k} UNION ALL SELECT c, wx, wy, wz FROM z{k}")
    first = "SELECT src, dst, dx, dy, dz, gb FROM bonds JOIN e0 USING (src, dst, ix, iy, iz)"
    pulls.append(f"SELECT src, 32 * gb * dx, 32 * gb * dy, 32 * gb * dz FROM ({first}) UNION ALL SELECT dst, -32 * gb * dx, -32 * gb * dy, -32 * gb * dz FROM ({first})")
    return [*out, ("pulls", " UNION ALL ".join(pulls)), TOTALS]
