"""Rule sets of the published sizes, generated, with queries whose measures follow from products and sums by hand.

The published rule sets and queries are not at hand; only their sizes and measures are. Each rule set here has the published
number of rules and is built such that the query shapes give the published sizes, atoms and joins:

- a class with n classes below it is rewritten into n + 1 queries; in a chain of atoms whose variables are all
  distinguished the sizes multiply, and decomposition makes the explored queries a sum;
- a role with its inverse is rewritten into 2; where a class is implied by the role, elimination drops its atom.
"""

from __future__ import annotations

from functools import cache

from ontospark.logic.parse import parse_ontology


def tree(root: str, below: int, fan: int = 6) -> list[str]:
    """Rules of a taxonomy with `below` classes under the root, each with at most `fan` classes right under it."""
    names = [root, *(f"{root}_{i}" for i in range(1, below + 1))]
    return [f"{names[i]}(X) => {names[(i - 1) // fan]}(X)" for i in range(1, below + 1)]


def role(name: str, source: str | None, target: str | None, inverse: bool = True) -> list[str]:
    """Domain, range and inverse of a role."""
    out = [f"{name}(X,Y) => {source}(X)"] * bool(source) + [f"{name}(X,Y) => {target}(Y)"] * bool(target)
    return out + ([f"{name}(X,Y) => {name}_of(Y,X)", f"{name}_of(X,Y) => {name}(Y,X)"] if inverse else [])


def _padded(rules: list[str], total: int) -> str:
    """Up to the published number of rules: one more taxonomy that the queries don't touch."""
    if len(rules) > total:
        raise ValueError(f"{len(rules)} rules")
    return "\n".join(rules + tree("other", total - len(rules)))


#: A wide taxonomy in which no atom implies another: 222 rules.
TAXONOMY = _padded([r for name, below in (("subject", 14), ("person", 9), ("event", 23), ("place", 2), ("work", 36), ("era", 4), ("guild", 4), ("town", 2), ("trade", 1)) for r in tree(name, below)], 222)
TAXONOMY_Q = {
    1: "p(A) <- subject(A)",
    2: "p(A,B) <- person(A), took_part(A,B), notable(A)",
    3: "p(A,B) <- event(A), set_in(A,B), place(B)",
    4: "p(A,B) <- work(A), made_in(A,B), era(B)",
    5: "p(A,B,C) <- guild(A), town(B), trade(C), based_in(A,B), held(B,C), ran(A,C), known(D)",
}
#: Published: size, atoms, joins, explored (elimination changes nothing); components, explored and generated after decomposition.
TAXONOMY_ROWS = {1: (15, 15, 0, 15, 1, 15, 14), 2: (10, 30, 30, 10, 3, 12, 9), 3: (72, 216, 144, 72, 3, 28, 25), 4: (185, 555, 370, 185, 3, 43, 40), 5: (30, 210, 270, 30, 7, 14, 7)}

#: Roles with inverses, domains and ranges: 53 rules. A class of a role has its own tree below it.
ROLES = _padded(
    tree("asset", 5) + role("holds", "holder", "paper") + tree("holder", 5) + tree("paper", 7)
    + role("lists", "paper_list", "quote") + role("trades", "desk", "book") + tree("desk", 3) + tree("book", 4) + role("pays", "payer", "bill"),
    53,
)
ROLES_Q = {
    1: "p(A) <- asset(A)",
    2: "p(A,B) <- holder(A), holds(A,B), paper(B)",
    3: "p(A,B,C) <- desk(A), trades(A,B), book(B), pays(B,C), bill(C)",
    4: "p(A,B,C) <- holder(A), holds(A,B), paper(B), pays(B,C), bill(C)",
    5: "p(A,B,C,D) <- desk(A), trades(A,B), book(B), pays(B,C), bill(C), lists(B,D), quote(D)",
}
#: Published: size, atoms, joins and explored, before elimination and after it.
ROLES_ROWS = {1: (6, 6, 0, 6, 6, 6, 0, 6), 2: (160, 480, 320, 160, 2, 2, 0, 2), 3: (504, 2520, 2520, 504, 4, 8, 4, 4), 4: (960, 4800, 4800, 960, 4, 8, 4, 4), 5: (3024, 21168, 27216, 3024, 8, 24, 24, 8)}
#: By hand: sizes of the atoms' unions (a class counts itself, its tree, and two for each role that implies it), whose product is the size.
ROLES_UNIONS = {1: (6,), 2: (8, 2, 10), 3: (6, 2, 7, 2, 3), 4: (8, 2, 10, 2, 3), 5: (6, 2, 7, 2, 3, 2, 3)}

#: An organisation: 87 rules, some roles without an inverse.
STAFF = _padded(
    tree("unit", 33) + role("leads", "lead", "unit", inverse=False) + tree("lead", 2) + role("member", "fellow", "unit") + tree("fellow", 19)
    + role("teaches", "teacher", "course") + tree("teacher", 4) + tree("course", 3) + role("near", None, "site") + tree("site", 5),
    87,
)
STAFF_Q = {
    1: "p(A,B) <- near(A,B), wing(A)",
    2: "p(A,B) <- lead(A), leads(A,B), unit(B)",
    3: "p(A,B,C) <- chair(A), teacher(A), teaches(A,B), near(B,C), opens(B,C), site(C)",
    4: "p(A,B) <- fellow(A), member(A,B), unit(C)",
}
#: Published: size, atoms and joins, before elimination and after it. What is explored follows from other rules there; here it is the size.
STAFF_ROWS = {1: (2, 4, 2, 2, 2, 4, 2, 2), 2: (148, 444, 296, 148, 1, 1, 0, 1), 3: (224, 1344, 2016, 224, 4, 16, 20, 4), 4: (1628, 4884, 1628, 1628, 2, 2, 0, 2)}
STAFF_UNIONS = {1: (2, 1), 2: (4, 1, 37), 3: (1, 7, 2, 2, 1, 8), 4: (22, 2, 37)}

#: Cliques: 34 sticky rules; seven kinds of edges, triangles, squares, and products of flags.
CLIQUES = "\n".join(
    [f"kind_{i}(X,Y) => link(X,Y)" for i in range(1, 7)] + ["twin(X,Y) => link(X,Y)", "twin(X,Y) => link(Y,X)", "star(X) => link(X,Y)"]
    + ["link(X,Y), link(Y,Z), link(X,Z) => three(X,Y,Z)", "three(X,Y,Z), link(X,W), link(Y,W), link(Z,W) => four(X,Y,Z,W)"]
    + [f"flag_{i}(X), flag_{i + 1}(Y) => pair_{i}(X,Y)" for i in range(1, 12)] + [f"pair_{i}(X,Y) => mixed(X,Y)" for i in range(1, 12)] + ["star(X) => flag_1(X)"]
)
CLIQUES_Q = {1: "p(A,B) <- link(A,B)", 2: "p(A,B) <- mixed(A,B)", 3: "p(A,B,C) <- three(A,B,C)", 4: "p(A,B,C,D) <- four(A,B,C,D)"}
#: By hand, over programs: views, and the size of the flat union that they stand for (9 ways for a distinguished edge).
CLIQUES_ROWS = {1: (1, 9), 2: (13, 24), 3: (2, 1 + 9**3), 4: (3, 1 + 9**3 * (1 + 9**3))}


def _deep() -> tuple[str, str]:
    """154 linear rules, deep and with invented values, and 19 constraints: what a device does for an ability."""
    rules = [r for k in range(1, 9) for r in (*role(f"helps_{k}", f"device_{k}", f"ability_{k}"), f"device_{k}(X) => helps_{k}(X,Y)", f"ability_{k}(X) => part_of(X,Y)", f"device_{k}(X) => device(X)", f"ability_{k}(X) => ability(X)", f"helps_{k}(X,Y) => helps(X,Y)")]
    rules += [f"level_{i}(X) => level_{i + 1}(X)" for i in range(1, 11)] + ["level_11(X) => device_1(X)", "helps(X,Y) => device(X)", "helps(X,Y) => ability(Y)", "device(X) => thing(X)", "ability(X) => thing(X)", "part_of(X,Y) => ability(Y)", "part_of(X,Y) => has_part(Y,X)", "has_part(X,Y) => part_of(Y,X)"]
    rules = "\n".join(rules) + "\n" + "\n".join(tree("tool", 154 - len(rules), 3))
    bans = [f"device_{i}(X), ability_{j}(X) => false" for i in range(1, 9) for j in (i, i % 8 + 1)] + [f"tool(X), ability_{i}(X) => false" for i in range(1, 4)]
    return rules, "\n".join(bans)


DEEP, DEEP_BANS = _deep()
DEEP_Q = {
    1: "p(A) <- thing(A)",
    2: "p(A) <- device(A), helps(A,B)",
    3: "p(A,B) <- helps(A,B), ability(B), part_of(B,C)",
    4: "p(A) <- helps(A,B), part_of(B,C), ability(C)",
}


@cache
def parsed(text: str):
    return parse_ontology(text)


def sizes() -> list[tuple[str, int, int]]:
    """Rules and constraints of every rule set."""
    named = {"taxonomy": TAXONOMY, "roles": ROLES, "staff": STAFF, "cliques": CLIQUES, "deep": DEEP + "\n" + DEEP_BANS}
    return [(k, len(parsed(t).tgds), len(parsed(t).ncs)) for k, t in named.items()]


__all__ = ["parsed", "role", "sizes", "tree"]
