"""How plans are built and checked: lineage, engine choice, and SQL twins."""
