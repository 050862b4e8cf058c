"""Carrier rows, graph views, walks and the context prefix coder, as Spark plans."""
