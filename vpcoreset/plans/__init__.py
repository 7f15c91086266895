"""Registered plans of the methods; each has a name, a Spark callable and, where SQL can say it, a twin."""
