"""Plan builders: stored tables, numbering, iterated joins and winner determination."""
