"""Training-data operators: one module per operator, registered through :mod:`poiweave.llm.registry`."""
