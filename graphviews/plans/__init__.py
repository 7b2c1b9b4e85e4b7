"""Query text, the plan algebras and the steps between them; nothing here runs Spark jobs."""
