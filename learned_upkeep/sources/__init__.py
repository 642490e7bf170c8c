"""Tables, fixtures and the registry of model versions."""
