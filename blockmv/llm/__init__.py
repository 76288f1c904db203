"""Operations of a training-data pipeline on Spark. Nothing outside this subpackage imports it."""
