"""Adaptive training-subset selection, expressed as Spark DataFrame plans."""
