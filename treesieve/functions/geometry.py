"""Geometry: values made of scalars, predicates and metrics as expressions, and what volumes say of them.

A geometry is an ``E`` of op ``geom`` whose value is (kind, dimensions) and whose arguments are its
scalars. Kernels turn a predicate over two geometries into scalar expressions, so Catalyst compiles
them and any SQL engine can run the same formula. Predicates follow the nine-intersection reading:
interiors are relative to an object's own dimension, so a point is its own interior, and
``contains`` asks that interiors meet.

The rules need no kernel code: a varying geometry is replaced by the box that its scalars' bounds
give, and a table says for each predicate and varying side what must hold (``maybe``) and what is
enough (``always``). Where a member may touch the border of a tight volume, closed covering is used
on the necessary side and strict inclusion on the sufficient side of contains and within.
"""

from __future__ import annotations

from collections.abc import Callable

from .expr import E, FALSE, KERNELS, TRUE, AnalysisError, both, either, fn, greatest_, least_, lit, negate, walk
from .intervals import GEOMETRIC, Env, bounds

sqrt, absolute = fn("root"), fn("abs")


def _geom(kind: str, dims: int, *args) -> E:
    from .expr import wrap

    return E("geom", tuple(map(wrap, args)), (kind, dims))


def Point(*xs) -> E:  # noqa: N802
    return _geom("point", len(xs), *xs)


def Box(lo, hi) -> E:  # noqa: N802
    return _geom("box", len(lo), *lo, *hi)


def Sphere(centre, r) -> E:  # noqa: N802
    return _geom("sphere", len(centre), *centre, r)


def Segment(a, b) -> E:  # noqa: N802
    return _geom("segment", len(a), *a, *b)


def Ray(origin, direction) -> E:  # noqa: N802
    return _geom("ray", len(origin), *origin, *direction)


def Triangle(a, b, c) -> E:  # noqa: N802
    return _geom("triangle", len(a), *a, *b, *c)


USER_VOLUMES: dict[str, Callable[[E], tuple[list[E], list[E]]]] = {}
USER_KERNELS: dict[tuple[str, str, str], Callable[[E, E], E]] = {}


def register_geometry(kind: str, volume: Callable[[E], tuple[list[E], list[E]]], kernels: dict[tuple[str, str], Callable[[E, E], E]]) -> Callable[..., E]:
    """A user's geometry type: ``volume`` gives its box, kernels map (predicate, other kind) to an expression.
    Rules go by predicate and box alone, so it is prunable at once. Returns its constructor."""
    USER_VOLUMES[kind] = volume
    for (name, other), k in kernels.items():
        USER_KERNELS[name, kind, other] = k
    return lambda dims, *args: _geom(kind, dims, *args)


def parts(g: E) -> list[list[E]]:
    """The vectors (and the radius) that a geometry is made of."""
    n = g.value[1]
    return [list(g.args[i : i + n]) for i in range(0, len(g.args), n)]


def box_of(g: E) -> tuple[list[E], list[E]] | None:
    """Corners of the smallest box; None if it has none."""
    kind, p = g.value[0], parts(g)
    if kind in USER_VOLUMES:
        return USER_VOLUMES[kind](g)
    if kind == "point":
        return p[0], p[0]
    if kind == "box":
        return p[0], p[1]
    if kind == "sphere":
        r = p[1][0]
        return [c - r for c in p[0]], [c + r for c in p[0]]
    if kind in ("segment", "triangle"):
        return [least_(*x) for x in zip(*p, strict=True)], [greatest_(*x) for x in zip(*p, strict=True)]
    return None


# ---- kernels -------------------------------------------------------------------------------------

Corners = tuple[list[E], list[E]]


def meets(a: Corners, b: Corners) -> E:
    return both(*(x <= y for x, y in zip(a[0], b[1], strict=True)), *(x <= y for x, y in zip(b[0], a[1], strict=True)))


def covers_box(a: Corners, b: Corners) -> E:
    return both(*(x <= y for x, y in zip(a[0], b[0], strict=True)), *(x <= y for x, y in zip(b[1], a[1], strict=True)))


def strictly(a: Corners, b: Corners) -> E:
    """b lies in the interior of a."""
    return both(*(x < y for x, y in zip(a[0], b[0], strict=True)), *(x < y for x, y in zip(b[1], a[1], strict=True)))


def _interiors_meet(a: Corners, b: Corners) -> E:
    out = []
    for al, ah, bl, bh in zip(*a, *b, strict=True):
        flat_a, flat_b = al.eq(ah), bl.eq(bh)
        out.append(either(both(al < bh, bl < ah), both(flat_a, flat_b, al.eq(bl))))
        # a flat side needs to lie strictly inside the other, which the strict comparisons say; two flat sides must agree
    return both(*out)


def _contains_box(a: Corners, b: Corners) -> E:
    return both(covers_box(a, b), _interiors_meet(a, b))


def sub(a: list[E], b: list[E]) -> list[E]:
    return [x - y for x, y in zip(a, b, strict=True)]


def dot(a: list[E], b: list[E]) -> E:
    out = a[0] * b[0]
    for x, y in zip(a[1:], b[1:], strict=True):
        out = out + x * y
    return out


def cross(a: list[E], b: list[E]) -> list[E]:
    return [a[1] * b[2] - a[2] * b[1], a[2] * b[0] - a[0] * b[2], a[0] * b[1] - a[1] * b[0]]


def gap2(a: Corners, b: Corners) -> E:
    """Squared smallest distance of two boxes."""
    each = [greatest_(bl - ah, al - bh, 0.0) for al, ah, bl, bh in zip(*a, *b, strict=True)]
    return dot(each, each)


def reach2(a: Corners, b: Corners) -> E:
    """Squared largest distance of points of two boxes."""
    each = [greatest_(absolute(bh - al), absolute(ah - bl)) for al, ah, bl, bh in zip(*a, *b, strict=True)]
    return dot(each, each)


def _segment2(p: list[E], a: list[E], b: list[E]) -> E:
    ab, ap = sub(b, a), sub(p, a)
    size = dot(ab, ab)
    t = E("case", (lit(0.0) < size, least_(1.0, greatest_(0.0, dot(ap, ab) / size)), lit(0.0)))
    rest = [x - t * y for x, y in zip(ap, ab, strict=True)]
    return dot(rest, rest)


def _triangle2(p: list[E], a: list[E], b: list[E], c: list[E]) -> E:
    """Squared distance of a point and a triangle: to the plane if the point is over it, else to the nearest side."""
    u, v, w = sub(b, a), sub(c, a), sub(p, a)
    uu, uv, vv, wu, wv = dot(u, u), dot(u, v), dot(v, v), dot(w, u), dot(w, v)
    det = uu * vv - uv * uv
    s, t = vv * wu - uv * wv, uu * wv - uv * wu
    over = both(lit(0.0) < det, lit(0.0) <= s, lit(0.0) <= t, (s + t) <= det)
    n = cross(u, v)
    h = dot(w, n)
    sides = least_(_segment2(p, a, b), _segment2(p, b, c), _segment2(p, c, a))
    return E("case", (over, h * h / dot(n, n), sides))


def hit_time(ray: E, tri: E) -> E:
    """Ray parameter of the hit of a triangle, by determinants; null without a hit."""
    (o, d), (a, b, c) = parts(ray), parts(tri)
    u, v = sub(b, a), sub(c, a)
    h = cross(d, v)
    det = dot(u, h)
    inv = E("case", (det.eq(0.0), lit(None), lit(1.0) / det))
    s = sub(o, a)
    x = dot(s, h) * inv
    q = cross(s, u)
    y, t = dot(d, q) * inv, dot(v, q) * inv
    return E("case", (both(absolute(det) > 1e-12, lit(0.0) <= x, lit(0.0) <= y, (x + y) <= 1.0, lit(0.0) <= t), t, lit(None)))


def slab(ray: E, box: Corners) -> tuple[E, E]:
    """Entry and exit parameter of a ray and a box; it meets the box if entry <= exit."""
    o, d = parts(ray)
    ins, outs = [lit(0.0)], []
    for x, v, lo, hi in zip(o, d, *box, strict=True):
        flat = v.eq(0.0)
        inside = both(lo <= x, x <= hi)
        a, b = (lo - x) / E("case", (flat, lit(1.0), v)), (hi - x) / E("case", (flat, lit(1.0), v))
        ins.append(E("case", (flat, E("case", (inside, lit(float("-inf")), lit(float("inf")))), least_(a, b))))
        outs.append(E("case", (flat, lit(float("inf")), greatest_(a, b))))
    return greatest_(*ins), least_(*outs)


def _triangles_meet(p: E, q: E) -> E:
    """Separating axes: the normals, the crosses of sides, and for coplanar ones the sides' normals."""
    a, b = parts(p), parts(q)
    sides = [[sub(t[(i + 1) % 3], t[i]) for i in range(3)] for t in (a, b)]
    normals = [cross(s[0], s[1]) for s in sides]
    axes = [*normals, *(cross(x, y) for x in sides[0] for y in sides[1]), *(cross(n, s) for n, ss in zip(normals, sides, strict=True) for s in ss)]

    def together(axis: list[E]) -> E:
        x, y = [dot(axis, v) for v in a], [dot(axis, v) for v in b]
        return both(least_(*x) <= greatest_(*y), least_(*y) <= greatest_(*x))

    return both(*map(together, axes))


def _pair(name: str, a: E, b: E) -> E:
    ka, kb = a.value[0], b.value[0]
    if (name, ka, kb) in USER_KERNELS:
        return USER_KERNELS[name, ka, kb](a, b)
    if (name, kb, ka) in USER_KERNELS and name in ("intersects", "disjoint", "equals", "touches", "distmin", "distmax"):
        return USER_KERNELS[name, kb, ka](b, a)
    boxy = {"point", "box"}
    pa, pb = parts(a), parts(b)
    if name == "disjoint":
        return negate(_pair("intersects", a, b))
    if name == "within":
        return _pair("contains", b, a)
    if ka in boxy and kb in boxy:
        x, y = box_of(a), box_of(b)
        table: dict[str, Callable[[], E]] = {
            "intersects": lambda: meets(x, y), "covers": lambda: covers_box(x, y), "contains": lambda: _contains_box(x, y),
            "equals": lambda: both(*(p.eq(q) for p, q in zip([*x[0], *x[1]], [*y[0], *y[1]], strict=True))),
            "touches": lambda: both(meets(x, y), negate(_interiors_meet(x, y))), "distmin": lambda: sqrt(gap2(x, y)), "distmax": lambda: sqrt(reach2(x, y)),
        }
        return table[name]()
    if "sphere" in (ka, kb) and {ka, kb} <= boxy | {"sphere"}:
        if ka == kb:
            d, r, s = sqrt(dot(sub(pa[0], pb[0]), sub(pa[0], pb[0]))), pa[1][0], pb[1][0]
            table = {"intersects": lambda: d <= r + s, "covers": lambda: d + s <= r, "contains": lambda: d + s <= r, "equals": lambda: both(d.eq(0.0), r.eq(s)), "touches": lambda: d.eq(r + s), "distmin": lambda: greatest_(d - r - s, 0.0), "distmax": lambda: d + r + s}
            return table[name]()
        ball, other = (a, b) if ka == "sphere" else (b, a)
        c, r = parts(ball)[0], parts(ball)[1][0]
        near, far = gap2((c, c), box_of(other)), reach2((c, c), box_of(other))
        if name in ("intersects", "touches"):
            return near <= r * r if name == "intersects" else near.eq(r * r)
        if name in ("covers", "contains") and ball is a:
            return far <= r * r if name == "covers" or other.value[0] == "box" else far < r * r
        if name in ("covers", "contains"):
            return covers_box(box_of(other), box_of(ball)) if other.value[0] == "box" else both(FALSE)
        if name in ("distmin", "distmax"):
            return greatest_(sqrt(near) - r, 0.0) if name == "distmin" else sqrt(far) + r
        return FALSE
    if "ray" in (ka, kb):
        ray, other = (a, b) if ka == "ray" else (b, a)
        if other.value[0] == "triangle":
            t = hit_time(ray, other)
            if name == "intersects":
                return t.not_null()
            if name in ("distmin", "hit"):  # travel from the origin to the hit
                return t * sqrt(dot(parts(ray)[1], parts(ray)[1]))
        if other.value[0] == "box" and name == "intersects":
            t = slab(ray, box_of(other))
            return t[0] <= t[1]
    if {ka, kb} == {"point", "triangle"}:
        p, t = (a, b) if ka == "point" else (b, a)
        q = parts(p)[0]
        if name == "distmin":
            return sqrt(_triangle2(q, *parts(t)))
        if name == "distmax":
            return sqrt(greatest_(*(dot(sub(q, v), sub(q, v)) for v in parts(t))))
        if name in ("intersects", "touches"):
            return _triangle2(q, *parts(t)).eq(0.0)
    if {ka, kb} == {"point", "segment"} and name == "distmin":
        p, t = (a, b) if ka == "point" else (b, a)
        return sqrt(_segment2(parts(p)[0], *parts(t)))
    if ka == kb == "triangle" and name == "intersects":
        return _triangles_meet(a, b)
    raise AnalysisError(f"{name} is not defined for {ka} and {kb}")


# ---- rules ---------------------------------------------------------------------------------------


def _volume(g: E, env: Env) -> tuple[Corners | None, bool]:
    """The box of a geometry or, if it varies, of all that a node holds; whether it varies."""
    varies = any(x.op == "col" and env(*x.value) is not None for x in walk(g))
    box = box_of(g)
    if box is None or not varies:
        return box, varies
    lo, hi = [bounds(x, env)[0] for x in box[0]], [bounds(x, env)[1] for x in box[1]]
    return (None if None in lo or None in hi else (lo, hi)), varies


def _touch(u: E, box: Corners) -> E:
    """Whether a uniform geometry may meet a box: exact for spheres and rays, else by its own box."""
    if u.value[0] == "sphere":
        c, r = parts(u)[0], parts(u)[1][0]
        return gap2((c, c), box) <= r * r * (1 + 1e-12)
    if u.value[0] == "ray":
        t = slab(u, box)
        return t[0] <= t[1] + absolute(t[1]) * 1e-12
    own = box_of(u)
    return TRUE if own is None else meets(own, box)


def _swallows(u: E, box: Corners, strict: bool) -> E:
    """Whether a uniform geometry certainly covers a box (its interior does, if strict)."""
    if u.value[0] in ("box", "point"):
        return (strictly if strict else covers_box)(box_of(u), box)
    if u.value[0] == "sphere":
        c, r = parts(u)[0], parts(u)[1][0]
        return reach2((c, c), box) < r * r * (1 - 1e-12)
    return FALSE


def _rule(name: str) -> Callable[[tuple[E, ...], Env], tuple[E, E]]:
    def of(args: tuple[E, ...], env: Env) -> tuple[E, E]:
        a, b = args
        (va, vary_a), (vb, vary_b) = _volume(a, env), _volume(b, env)
        if not vary_a and not vary_b:
            same = _pair(name, a, b)
            return same, same
        if va is None and vary_a or vb is None and vary_b:
            return FALSE, TRUE
        if vary_a and vary_b:
            touch = meets(va, vb)
            if name == "disjoint":
                return negate(touch), TRUE
            return FALSE, touch
        u, v, left = (b, va, False) if vary_a else (a, vb, True)  # left: the uniform one comes first
        touch, own = _touch(u, v), box_of(u)
        around = TRUE if own is None else covers_box(v, own)
        if name == "intersects":
            return _swallows(u, v, False), touch
        if name == "disjoint":
            return negate(touch), negate(_swallows(u, v, False))
        if name == "touches":
            return FALSE, touch
        if name == "equals":
            return FALSE, around
        holds = name in ("contains", "covers")
        if holds == left:  # u has to hold the member
            return _swallows(u, v, name != "covers"), touch
        return FALSE, around  # the member has to hold u, so the volume does

    return of


def _metric(name: str) -> Callable[[tuple[E, ...], Env], tuple[E | None, E | None]]:
    def of(args: tuple[E, ...], env: Env) -> tuple[E | None, E | None]:
        a, b = args
        (va, vary_a), (vb, vary_b) = _volume(a, env), _volume(b, env)
        if not vary_a and not vary_b:
            same = _pair(name, a, b)
            return same, same
        ray = next((g for g in (a, b) if g.value[0] == "ray"), None)
        if ray is not None:
            box = vb if ray is a else va
            if box is None:
                return lit(0.0), None
            t, speed = slab(ray, box), sqrt(dot(parts(ray)[1], parts(ray)[1]))
            return greatest_(t[0], 0.0) * speed * (1 - 1e-12), greatest_(t[1], 0.0) * speed * (1 + 1e-12)
        if va is None or vb is None:
            return lit(0.0), None
        return sqrt(gap2(va, vb)) * (1 - 1e-12), sqrt(reach2(va, vb)) * (1 + 1e-12)

    return of


def _order(op: str) -> Callable[[E, E, int], E]:
    def of(a: E, b: E, dim: int) -> E:
        """All of a before all of b in one dimension; a scalar comparison, so scalar rules bound it."""
        x, y = box_of(a)[1][dim], box_of(b)[0][dim]
        return x < y if op == "<" else x <= y

    return of


le, lt = _order("<="), _order("<")


def _predicate(name: str) -> Callable[[E, E], E]:
    op = f"g.{name}"
    KERNELS[op] = lambda a, b: _pair(name, a, b)
    GEOMETRIC[op] = _metric(name) if name.startswith("dist") else _rule(name)

    def make(a: E, b: E) -> E:
        _pair(name, a, b)  # an undefined pair of kinds is found here
        return E(op, (a, b))

    return make


contains, covers, disjoint, intersects, equals, touches, within, distmin, distmax = map(_predicate, ("contains", "covers", "disjoint", "intersects", "equals", "touches", "within", "distmin", "distmax"))
