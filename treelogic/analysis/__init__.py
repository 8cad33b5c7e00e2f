"""Static analysis of patterns: satisfiability, containment, equivalence, minimization.

Everything here has the size of a pattern (tens of nodes) and runs on the driver
before any table is touched; Spark sees the resulting pattern only.
"""
