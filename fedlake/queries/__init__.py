"""Named queries over the given tables, by area; importing a module registers its queries."""
