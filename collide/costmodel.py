"""Operation counts of the methods, and the choices that follow from them."""

from __future__ import annotations

from math import log2


def predict(method: str, n: int, d: int, k: int = 2500, n_sub: int = 8, iterations: int = 10, alpha: float = 0.05, beta: float = 0.005, trees: int = 4, bits: int = 16, regions: int = 256, links: int = 25, books: int = 2, codewords: int = 256, gamma: float = 0.01) -> dict[str, float]:
    """index operations, index space (values) and query operations, up to constants."""
    root = k**0.5
    beta_n = max(2.0, beta * n)
    if method == "indexed":
        return {"index": n * (root * d * iterations + n_sub), "space": root * d + n * n_sub, "query": n * (alpha * n_sub + beta * d + log2(beta_n)) + root * (d + alpha * root * log2(max(root, 2)))}
    if method == "scan":
        return {"index": 0.0, "space": 0.0, "query": n * d + n_sub * n * log2(n) + n * log2(beta_n) + beta * n * d}
    if method == "exact_knn":
        return {"index": 0.0, "space": 0.0, "query": float(n * d)}
    if method == "encoded_projection_trees":
        return {"index": trees * bits * n * (d + log2(regions)), "space": float(trees * bits * n), "query": n * (beta * d + trees * bits * log2(regions))}
    if method == "rotated_product_quantiser":
        return {"index": n * (root + codewords) * d * iterations, "space": n * (books * log2(codewords) + log2(root)) + (root + codewords) * d, "query": n * (gamma * books + beta * d) + (root + codewords) * d}
    if method == "projection_forest":
        return {"index": trees * n * d * log2(n), "space": float(trees * d * n), "query": trees * d * log2(n) + beta * n * d}
    if method == "layered_graph":
        return {"index": n * d * log2(n), "space": float(n * links), "query": d * log2(n)}
    if method == "tree_graph_hybrid":
        return {"index": n * d * log2(n), "space": float(n * (d + links)), "query": d * log2(n)}
    raise ValueError(f"no formula for {method}")


METHODS = ("exact_knn", "scan", "indexed", "encoded_projection_trees", "rotated_product_quantiser", "projection_forest", "layered_graph", "tree_graph_hybrid")


def choose_layout(queries: int, alpha: float, n: int, n_sub: int, hit_bytes: int = 24) -> str:
    """Forward scans all codes once for the whole block; inverted reads and shuffles the hits of each query. For many
    queries the forward scan counts in Arrow."""
    forward = n * (8 + 2 * n_sub)
    inverted = queries * alpha * n * n_sub * (10 + hit_bytes)
    if inverted < forward:
        return "inverted"
    return "arrow" if queries >= 32 else "forward"


def clusterings(n_sub: int, parts: int = 2) -> int:
    """How many clusterings an index needs."""
    return n_sub * parts


def cumulative_cost(t_index: float, t_query: float, q: int) -> float:
    """Seconds to build and to answer q queries."""
    return t_index + q * t_query


def break_even(a: tuple[float, float], b: tuple[float, float]) -> float | None:
    """Queries after which method b, given as (index, query) seconds, overtakes a; None if never, 0 if from the start."""
    if b[0] <= a[0]:
        return 0.0 if b[1] <= a[1] else None
    return (b[0] - a[0]) / (a[1] - b[1]) if b[1] < a[1] else None
