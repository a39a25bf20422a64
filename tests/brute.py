"""The definitions in plain Python, for small whole-number points."""


def d2(a, b):
    return sum((x - y) ** 2 for x, y in zip(a, b))


def beats(o, q, r):
    pairs = [(abs(a - c), abs(b - c)) for a, b, c in zip(o, q, r)]
    return all(x <= y for x, y in pairs) and any(x < y for x, y in pairs)


def eps_results(points, query, eps, closed=True):
    fits = (lambda v: v <= eps * eps) if closed else (lambda v: v < eps * eps)
    return {i for i, p in points.items() if i not in query and all(fits(d2(p, points[q])) for q in query)}


def knn_results(points, query, k, keep_queries=False):
    out = set()
    for i, p in points.items():
        if i in query and not keep_queries:
            continue
        others = [q for q in query if q != i]
        near = sorted((d2(p, x), j) for j, x in points.items() if j != i)[: k - (i in query)]
        if len(query) <= k and others and set(others) <= {j for _, j in near}:
            out.add(i)
    return out


def skyline_results(points, query):
    return {i for i, p in points.items() if i not in query and not any(j not in (i, q) and beats(x, points[q], p) for q in query for j, x in points.items())}
