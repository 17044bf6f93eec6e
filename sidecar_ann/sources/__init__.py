"""Storage: snapshot log, blob container, blob layouts, readers."""
