"""Query model and planning: everything that runs on the driver and depends on the size of the query only."""
