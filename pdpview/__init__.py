"""Differentially private maintenance of materialized views over growing tables, on Spark.

The engine models what the methods compute and what an observer of sizes learns. It is not secure computation:
shares are ordinary columns and a Spark job recombines them (a trusted executor).
"""
