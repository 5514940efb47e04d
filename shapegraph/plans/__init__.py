"""Driver-side trees: paths, shapes, schemas, patterns, and their rewritings; nothing here touches data."""
