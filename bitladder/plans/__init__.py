"""The user surface: models and indexes."""
