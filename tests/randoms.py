"""Random paths, ontologies and tiny graphs."""

from pathlore.oracle.brute import TinyGraph


def path(rng, size=2, nest=2):
    k = rng.random()
    if size == 0 or k < 0.4:
        c = rng.random()
        if c < 0.55:
            return rng.choice(["", "^"]) + rng.choice("rstu")
        if c < 0.75:
            return ":" + rng.choice("ABCD")
        if c < 0.82:
            return f"[p>={rng.randint(0, 3)}]"
        if c < 0.92:
            return "{" + rng.choice(["", "^"]) + rng.choice("rs") + (f",k>={rng.randint(0, 2)}" if rng.random() < 0.6 else "," + rng.choice(["", "^"]) + rng.choice("tu")) + "}"
        return f"{{k>={rng.randint(0, 2)}}}"
    if k < 0.65:
        return path(rng, size - 1, nest) + "/" + path(rng, size - 1, nest)
    if k < 0.75:
        return "(" + path(rng, size - 1, nest) + "|" + path(rng, size - 1, nest) + ")"
    if k < 0.85:
        return "(" + path(rng, size - 1, nest) + ")" + rng.choice("*+?")
    return "<" + path(rng, size, nest - 1) + ">" if nest else rng.choice("rs")


def query(rng):
    form, p, p2 = rng.random(), path(rng, 3), path(rng)
    if form < 0.4:
        return f"ans(x,y) <- {p}(x,y)"
    if form < 0.7:
        return f"ans(x) <- {p}(x,w)"
    if form < 0.8:
        return f"ans(x) <- {p}(w,x)"
    return f"ans(x,y) <- {p}(x,y) & {p2}(y,z)"


def ontology(rng, n):
    role = lambda: rng.choice(["", "^"]) + rng.choice("rstuv")
    name = lambda: rng.choice("ABCD")
    forms = [
        (0.25, lambda: f"role {role()} < {role()}"),
        (0.08, lambda: f"role {{k>={rng.randint(0, 2)}}} < {role()}"),
        (0.17, lambda: f"concept {name()} < {name()}"),
        (0.15, lambda: f"concept exists {role()} < {name()}"),
        (0.07, lambda: f"concept {{p>={rng.randint(1, 3)}}} < {name()}"),
        (0.18, lambda: f"concept {name()} < exists {role()}"),
        (0.04, lambda: f"concept exists {role()} < exists {role()}"),
        (0.03, lambda: f"concept {{p>={rng.randint(1, 3)}}} < exists {role()}"),
        (0.03, lambda: f"concept {name()} < exists {role()}.{name()}"),
    ]
    return "\n".join(rng.choices([f for _, f in forms], [w for w, _ in forms])[0]() for _ in range(n))


def graph(rng, most=4):
    n = rng.randint(1, most)
    nodes = {i: ({x for x in "ABCD" if rng.random() < 0.2}, {"p": rng.randint(0, 3)} if rng.random() < 0.5 else {}) for i in range(n)}
    edges = [(rng.choice("rstu"), rng.randrange(n), rng.randrange(n), {"k": rng.randint(0, 2)} if rng.random() < 0.6 else {}) for _ in range(rng.randint(0, 2 * most))]
    return TinyGraph.of(nodes, edges)
