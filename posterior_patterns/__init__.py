"""Itemset scoring by model posterior, expressed as Spark plans."""
