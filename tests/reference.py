"""Sequential versions of the methods, written without the engine's code."""

import hashlib
import heapq
import math


def h32(text):
    return int(hashlib.md5(text.encode()).hexdigest()[:8], 16)


def neighbours(edges):
    adj = {}
    for u, v, w in edges:
        adj.setdefault(u, {})[v] = min(w, adj.get(u, {}).get(v, w))
        adj.setdefault(v, {})[u] = min(w, adj.get(v, {}).get(u, w))
    return adj


def search(adj, s):
    dist, heap = {}, [(0, s)]
    while heap:
        d, u = heapq.heappop(heap)
        if u in dist:
            continue
        dist[u] = d
        for v, w in adj[u].items():
            if v not in dist:
                heapq.heappush(heap, (d + w, v))
    return dist


def diameter(adj):
    return max(max(search(adj, s).values()) for s in adj)


def staged(edges, tau, seed, delta, gamma=4 * math.log(2)):
    """Center and path weight of every node."""
    adj = neighbours(edges)
    n = len(adj)
    log_n = math.log2(n)
    center, dist, path, settled = {}, {}, {}, set()
    stage = 0
    while (left := n - len(center)) and left >= 8 * tau * log_n:
        p = gamma * tau * log_n / left
        for v in adj:
            if v not in center and h32(f"{seed}:{stage}:{v}") < p * 2**32:
                center[v], dist[v], path[v] = v, 0, 0
        goal = math.ceil(left / 2)
        while True:
            changed = False
            offers = {}
            for u in center:
                base = 0 if u in settled else dist[u]
                if base < delta:
                    for v, w in adj[u].items():
                        if w <= delta and base + w <= delta and v not in settled:
                            offers.setdefault(v, []).append((base + w, center[u], path[u] + w))
            for v, got in offers.items():
                best = min(got)
                if v not in dist or best[0] < dist[v]:
                    dist[v], center[v], path[v] = best
                    changed = True
            if len(center) - len(settled) >= goal:
                break
            if not changed:
                delta *= 2
        settled = set(center)
        stage += 1
    for v in adj:
        center.setdefault(v, v)
        path.setdefault(v, 0)
    return center, path


def rescaled(edges, radius, seed):
    """Center, path weight and iteration of every node: all clusters grow by twice the radius until nothing changes."""
    adj = neighbours(edges)
    n, reach = len(adj), 2 * radius
    last = max(1, math.ceil(math.log2(n)))
    center, dist, path, when, start = {}, {}, {}, {}, {}
    for i in range(1, last + 1):
        for v in adj:
            if v not in center and (i == last or h32(f"{seed + 1}:{i}:{v}") < min(1, 2**i / n) * 2**32):
                center[v], dist[v], path[v] = v, 0, 0
        changed = True
        while changed:
            changed, offers = False, {}
            for u in center:
                # a settled node speaks for its cluster's center along an edge of weight d + w - reach, for one iteration
                base = start.get(u) if u in when else dist[u]
                if base is not None and base < reach:
                    for v, w in adj[u].items():
                        if w <= reach and base + w <= reach and v not in when:
                            offers.setdefault(v, []).append((max(0, base + w), center[u], path[u] + w))
            for v, got in offers.items():
                best = min(got)
                if v not in dist or best[0] < dist[v]:
                    dist[v], center[v], path[v] = best
                    changed = True
        start = {v: dist[v] - reach for v in center if v not in when}
        when |= {v: i for v in center if v not in when}
        if len(when) == n:
            break
    return center, path, when
