"""Single-machine algorithms that run inside Python workers; no Spark in here."""
