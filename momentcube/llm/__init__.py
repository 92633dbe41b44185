"""Operations of a training-data pipeline at scale; nothing outside this subpackage imports it."""
