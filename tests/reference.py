"""A plain replay of the composite sketch, written apart from the engine, for comparison."""

from mixedsketch.spec import PRIME


class Matrix:
    def __init__(self, spec):
        self.spec = spec
        self.count = {}

    def column(self, j, key):
        a, b = self.spec.row(j)
        return (a * key + b) % PRIME % self.spec.K

    def add(self, key, v):
        for j in range(self.spec.H):
            at = j, self.column(j, key)
            self.count[at] = self.count.get(at, 0) + v
        return self.ask(key)

    def ask(self, key):
        return min(self.count.get((j, self.column(j, key)), 0) for j in range(self.spec.H))

    def squares(self):
        return [sum(c * c for (row, _), c in self.count.items() if row == j) for j in range(self.spec.H)]


class Part:
    def __init__(self, spec):
        self.spec, self.matrix, self.slot = spec, Matrix(spec), {}

    def feed(self, key, v):
        s = self.slot
        if key in s:
            cnt, old, avg = s[key]
            s[key] = (cnt + v, old, self.spec.w * v + (1 - self.spec.w) * avg)
        elif len(s) < self.spec.C:
            s[key] = (v, 0, float(v))
        else:
            est = self.matrix.add(key, v)
            small = sorted((c, k) for k, (c, _, _) in s.items())[0][1]
            if est > s[small][0]:
                gain = s[small][0] - s[small][1]
                del s[small]
                if gain:
                    self.matrix.add(small, gain)
                s[key] = (est, est, float(v))

    def ask(self, key):
        return self.slot[key][0] if key in self.slot else self.matrix.ask(key)

    def f2(self, extra=lambda key, avg: 0):
        return min(self.matrix.squares()) + sum((c + extra(k, a)) ** 2 - o**2 for k, (c, o, a) in self.slot.items())


def owner(spec, key):
    a, b = spec.owner
    return (a * key + b) % PRIME % spec.P


def replay(rows, spec, buffered=True):
    """(parts, open buffers) after rows of (seq, key, weight); producers take turns by seq."""
    parts = [Part(spec) for _ in range(spec.P)]
    buffers = {}
    for seq, key, v in sorted(rows):
        o = owner(spec, key)
        if not buffered:
            parts[o].feed(key, v)
            continue
        b = buffers.setdefault((seq % spec.P, o), {})
        b[key] = b.get(key, 0) + v
        if len(b) >= spec.C or (spec.B is not None and sum(b.values()) >= spec.B):
            for k, c in b.items():
                parts[o].feed(k, c)
            b.clear()
    return parts, buffers
