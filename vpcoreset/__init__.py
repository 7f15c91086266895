"""Coresets for data whose columns are divided among parties, as Spark plans."""
