"""Tables with explicit schemas, file formats and model stores."""
