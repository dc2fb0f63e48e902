"""Tables, adapters to the canonical schema, and stores."""
