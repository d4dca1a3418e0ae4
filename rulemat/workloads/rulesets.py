"""Rule sets of the experiments and of the worked examples."""

# Rule sets.
NEAR = """
@r1 near(x, y) <- hasNeighbour(x, y).
@r2 near(y, x) <- near(x, y).
@r3 near(x, z) <- near(x, y), near(y, z).
"""
JUDGE = """
@r4 nearCount(x, count(y)) <- near(x, y) group x.
@r5 medTemp(x, median(t)) <- near(x, y), temp(y, t) group x.
@r6 suspect(x, d) <- medTemp(x, m), temp(x, t), d := t - m, d > 5000.
"""
RS1 = NEAR + JUDGE

RS2 = """
@r1 q1(x, y) <- p1(x, y).
@r2 q1(y, x) <- q1(x, y).
@r3 q1(x, z) <- q1(x, y), q1(y, z).
@r4 q2(x, r) <- p2(x, n), p3(n, r).
@r5 q3(x, n) <- p4(x, s), p5(s, n).
@r6 q4(x, n) <- q3(x, n), p2(x, n).
@r7 q5(x, y) <- p1(x, y).
@r8 q6(x, z) <- q5(x, y), p1(y, z).
@r9 q5(x, z) <- q6(x, y), p1(y, z).
@r10 q7(x, n) <- q3(x, n), !p2(x, n).
@r11 q8(x, r) <- q8(x, n), p3(n, r).
@r12 q8(x, n) <- q1(x, y), q8(y, n).
@r13 q8(x, n) <- q5(x, y), q8(y, n).
@r14 q8(x, n) <- p2(x, n).
@r15 q9(x, n) <- q7(x, n), q6(x, y).
@r16 q9(x, n) <- q4(x, n).
@r17 q10(x, r) <- q8(x, r), q2(x, r).
@r18 q10(x, r) <- q9(x, n), p3(n, r).
"""
R10N = "@r10n q7(x, n) <- q3(x, n), !q4(x, n)."
RS3 = "\n".join(R10N if line.startswith("@r10 ") else line for line in RS2.splitlines())

REX = """
@r1 p1(x, y) <- e1(x, y).
@r2 p2(x, z) <- p1(x, y), p3(y, z).
@r3 p4(x, y) <- p2(x, y).
@r4 p3(x, y) <- p4(x, y).
@r5 p5(x, y) <- e2(x, y), !p2(x, y).
@r6 p6(x, y) <- p5(x, y), p7(x, y).
@r7 p7(x, y) <- p4(x, y), p6(x, y).
"""
REX_R8 = "@r8 p2(x, z) <- p3(x, y), p2(y, z)."
REX_FACTS = "e1(1,2). e1(2,3). e1(3,4). e2(1,7). e2(2,7). e2(5,6). p3(2,7). p3(7,1). p6(1,7). p6(2,7). p7(5,6)."
RDEL = """
@r1 a(x, y) <- e1(x, y).
@r2 b(x, z) <- a(x, y), c(y, z).
@r3 c(x, y) <- b(x, y).
@r7 b(x, z) <- b(x, y), b(y, z).
@r4 d(x, y) <- b(x, y), f(x, y).
@r5 f(x, y) <- g(x, y).
@r6 g(x, y) <- d(y, x).
"""
RDEL_FACTS = "e1(1,2). e1(3,4). c(2,3). c(4,5). f(1,5)."

#: Sets of rules that the experiments insert and delete.
UPDATES = {"r10_r15_r17": ["r10", "r15", "r17"], "r10_r15_r18": ["r10", "r15", "r18"], "r18": ["r18"], "r17": ["r17"], "r4": ["r4"], "r3": ["r3"], "r2": ["r2"]}
