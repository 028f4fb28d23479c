"""The input table: eleven text columns, and the order in which they were read."""

from __future__ import annotations

from pyspark.sql import types as T

COLUMNS = ("id", "title", "author", "editor", "pub_date", "venue", "volume", "issue", "page", "type", "publisher")
INPUT = T.StructType([T.StructField(c, T.StringType()) for c in COLUMNS])

# Resource types and the public classes they are exported as.
TYPE_CLASSES = {
    "journal article": "fabio:JournalArticle",
    "book chapter": "fabio:BookChapter",
    "proceedings article": "fabio:ProceedingsPaper",
    "journal issue": "fabio:JournalIssue",
    "book": "fabio:Book",
    "journal volume": "fabio:JournalVolume",
    "dataset": "fabio:DataFile",
    "web content": "fabio:WebContent",
    "report": "fabio:ReportDocument",
    "reference book": "fabio:ReferenceBook",
    "reference entry": "fabio:ReferenceEntry",
    "journal": "fabio:Journal",
    "proceedings": "fabio:AcademicProceedings",
    "book series": "fabio:BookSeries",
    "dissertation": "fabio:Thesis",
    "standard": "fabio:SpecificationDocument",
    "book section": "fabio:ExpressionCollection",
    "series": "fabio:Series",
    "peer review": "fr:ReviewVersion",
    "book part": "doco:Part",
    "book set": "fabio:BookSet",
}
# Predicates and the public terms they are exported as.
PREDICATES = {
    "a": "rdf:type",
    "title": "dcterms:title",
    "pub_date": "prism:publicationDate",
    "embodied_as": "frbr:embodiment",
    "first_page": "prism:startingPage",
    "last_page": "prism:endingPage",
    "part_of": "frbr:partOf",
    "seq_value": "fabio:hasSequenceIdentifier",
    "has_role": "pro:isDocumentContextFor",
    "role_kind": "pro:withRole",
    "held_by": "pro:isHeldBy",
    "next_role": "pro:hasNext",
    "name": "foaf:name",
    "given": "foaf:givenName",
    "family": "foaf:familyName",
    "has_id": "own:hasIdentifier",
    "id_scheme": "own:identifierScheme",
    "id_value": "own:identifierValue",
    "snap_of": "prov:specializationOf",
    "derived_from": "prov:wasDerivedFrom",
    "by": "prov:wasAttributedTo",
    "primary_source": "prov:hadPrimarySource",
    "generated_at": "prov:generatedAtTime",
    "invalidated_at": "prov:invalidatedAtTime",
    "described": "dcterms:description",
    "delta_text": "own:hasUpdateStatement",
}
# Where the public vocabularies live.
VOCABULARIES = {
    "rdf": "http://www.w3.org/1999/02/22-rdf-syntax-ns#",
    "dcterms": "http://purl.org/dc/terms/",
    "prism": "http://prismstandard.org/namespaces/basic/2.0/",
    "frbr": "http://purl.org/vocab/frbr/core#",
    "fabio": "http://purl.org/spar/fabio/",
    "pro": "http://purl.org/spar/pro/",
    "foaf": "http://xmlns.com/foaf/0.1/",
    "prov": "http://www.w3.org/ns/prov#",
    "fr": "http://purl.org/spar/fr/",
    "doco": "http://purl.org/spar/doco/",
    "own": "https://example.org/terms/",
}


def absolute(term: str) -> str:
    """A term of a vocabulary written out."""
    prefix, _, name = term.partition(":")
    return VOCABULARIES[prefix] + name
TRIPLE = "s string, p string, o string, o_kind string"
