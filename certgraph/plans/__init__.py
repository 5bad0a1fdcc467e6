"""Planning helpers: staging of intermediate tables, driver queries and their SQL oracles."""
