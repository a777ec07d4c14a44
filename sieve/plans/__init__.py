"""Planning helpers: scratch tables that cut lineage, strategy choice, legality rules."""
