"""relmodel: query-time relational modelling on Spark. See README.md for a tour."""
