"""Frequent label sequences on bounded paths of a DAG, as Spark DataFrame plans."""
