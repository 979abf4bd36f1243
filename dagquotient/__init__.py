"""Bisimulation partitions and structural indexes of very large labelled DAGs, as Spark plans."""
