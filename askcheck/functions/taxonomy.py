"""The label set: eight problem categories and the answerable ones, 13 subcategories."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

#: qtype, category, subcategory, definition, distinguishing trait, example on the given tables.
TAXONOMY = (
    ("ambiguous", "structural", "scope", "A quantifier can be taken over the whole collection or over each member of it.", "The readings differ in grouping, not in columns.", "total price for all priorities"),
    ("ambiguous", "structural", "attachment", "A modifier can belong to one part of a list or to all of it.", "The readings differ in which branch carries a filter.", "urgent and low orders above the mean price"),
    ("ambiguous", "semantic_mapping", "lexical_overlap", "A word fits several columns whose names look alike.", "The readings differ in one column of the same kind.", "the price of parts and orders"),
    ("ambiguous", "semantic_mapping", "entity", "A reference fits several entities that carry the same attribute.", "The readings differ in the table that is asked.", "account balances"),
    ("ambiguous", "lexical_vagueness", "vagueness", "A term has no objective bound.", "The readings differ in a threshold that the schema cannot give.", "large orders"),
    ("ambiguous", "missing_user_knowledge", "user_knowledge", "The answer depends on a fact only the person asking has.", "One reading for each value of that fact.", "orders of my segment"),
    ("ambiguous", "conflicting_knowledge", "conflict", "The knowledge base defines a concept in incompatible ways.", "The question is clear; the definitions disagree.", "the score of each status"),
    ("unanswerable", "missing_schema", "missing_entity", "A table or column that the question needs does not exist.", "The topic belongs to the domain, the element is absent.", "the warehouse of each part"),
    ("unanswerable", "missing_schema", "missing_relationship", "Both entities exist but no path of keys links them.", "The join is missing, not the tables.", "benchmark items cited by each document"),
    ("unanswerable", "missing_external_knowledge", "external_knowledge", "An objective fact of the domain is neither stored nor defined.", "No dialogue with the user would supply it.", "order totals in a foreign currency"),
    ("unanswerable", "improper", "improper", "The request has nothing to do with the data, or is no query.", "Outside the domain, small talk, or a change of data.", "please erase my account"),
    ("answerable", "answerable", "plain", "Schema and question suffice.", "One reading.", "orders per status"),
    ("answerable", "answerable", "with_evidence", "One reading, once a given piece of evidence is applied.", "The evidence defines a term that the schema lacks.", "count of heavy orders, heavy being defined"),
)
SUBCATEGORIES = tuple(t[2] for t in TAXONOMY)
TYPE_OF = {t[2]: t[0] for t in TAXONOMY}
CATEGORY_OF = {t[2]: t[1] for t in TAXONOMY}
STYLES = ("formal", "colloquial", "interrogative")
DIFFICULTIES = ("simple", "moderate", "complex", "highly_complex")


def taxonomy(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(TAXONOMY), "qtype string, category string, subcategory string, definition string, trait string, example string")
