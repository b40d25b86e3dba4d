"""Training-data operators. Nothing outside this subpackage imports it; its queries are in
``evigraph.llm.queries`` and are added to the entry point only where the subpackage exists."""
