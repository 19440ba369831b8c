"""Model roles: what the methods ask of models, and clients that answer."""
